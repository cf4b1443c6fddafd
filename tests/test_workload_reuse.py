"""Work that variants of one workload have in common is done once, with the same results."""

import pickle
import re
from dataclasses import replace

import numpy as np
import pytest

from varlink.functions.text import hashed_word_vector
from varlink.operators import baselines as B
from varlink.operators.embed import WordEncoder
from varlink.plans import workloads

SF = "/root/testdata/sf0.001"
SMALL = workloads.Workload(values=20, train_datasets=30, hidden=8, width=4, word_width=16, per_class=10, train=workloads.TrainConfig(batch=8, steps_per_epoch=2, epochs=1, values=8))


def test_encoder_is_mean_of_word_vectors():
    encode = WordEncoder(None, 16)
    for text in ("", None, "12 3", "red Anvil red", "red Anvil red", "one two " * 50 + "three"):
        found = [hashed_word_vector(w, 16) for w in re.findall(r"[^\W\d_]{2,}", (text or "").lower())]
        assert encode.one(text) == pytest.approx(np.mean(found, axis=0) if found else np.zeros(16), abs=1e-12)
    assert len(encode.short) == 3 and not pickle.loads(pickle.dumps(encode)).short


def test_means_of_moments(spark):
    packed = spark.createDataFrame([("a", ["red anvil", "red anvil", "blue"]), ("b", ["green", "blue"])], "dataset_id string, values array<string>")
    pairs, encode = spark.createDataFrame([("a", "b")], "id_a string, id_b string"), WordEncoder(None, 8).one
    got = B.mean_word_vector_of_moments(B.text_moments(packed, encode), pairs).first()
    want = B.mean_word_vector_distance(packed, pairs, encode).first()
    assert got["method"] == want["method"] and got["d"] == pytest.approx(want["d"], abs=1e-9)


@pytest.mark.parametrize("kind, change", [("numeric", {"form": "raw"}), ("language", {"use_g": False})])
def test_variants_are_packed_once(spark, monkeypatch, kind, change):
    calls, pack = [], B.pack
    monkeypatch.setattr(B, "pack", lambda *a, **k: calls.append(1) or pack(*a, **k))
    first = workloads.packed_for_training(spark, SF, kind, replace(SMALL, seed=7))
    again = workloads.packed_for_training(spark, SF, kind, replace(SMALL, seed=7, **change))
    assert len(calls) == 1 and first.ids == again.ids and first.variable == again.variable
    workloads.packed_for_training(spark, SF, kind, replace(SMALL, seed=7, values=10))
    assert len(calls) == 2


def test_ablation_histograms_once(spark, monkeypatch):
    calls, made = [], workloads.C.value_histogram
    monkeypatch.setattr(workloads.C, "value_histogram", lambda *a, **k: calls.append(1) or made(*a, **k))
    rows = workloads.run_input_ablation(spark, SF, SMALL, epochs=1).collect()
    assert len(rows) == 16 and len(calls) == 4  # two settings with and without flags, not one for each variant
