"""The pipeline's near-duplicate stage against all pairs of whole shingle sets."""

import random

import numpy as np
import pytest

import corpus_pipeline
from varlink.llm import near_copies
from varlink.llm.common import load

from . import brute
from .conftest import messy_rows


def groups(docs, size=5, percent=80):
    """Smallest id of each document's component, over all pairs."""
    sets = []
    for _, t in docs:
        w = brute.WORD.findall((t or "").translate(brute.UPPER))
        sets.append({tuple(w[i : i + size]) for i in range(max(1, len(w) - size + 1))} if w else set())
    parent = list(range(len(docs)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, a in enumerate(sets):
        for j in range(i):
            if a == sets[j] or 100 * len(a & sets[j]) >= percent * len(a | sets[j]):
                parent[find(i)] = find(j)
    least = {}
    for i, (d, _) in enumerate(docs):
        if d is not None:
            least[find(i)] = min(d, least.get(find(i), d))
    return [least.get(find(i)) for i in range(len(docs))]


def edited_docs(seed):
    """Texts and copies with 0 to 12 words changed, added or left out, so similarities lie on both sides of 0.8."""
    rng = random.Random(seed)
    word = lambda: f"w{rng.randrange(3000)}"
    docs = []
    for _ in range(5):
        base = [word() for _ in range(rng.choice([30, 80, 200]))]
        for _ in range(14):
            copy = list(base)
            for _ in range(rng.randrange(13)):
                at = rng.randrange(len(copy))
                copy[at : at + 1] = rng.choice([[word()], [copy[at], word()], []])
            docs.append((len(docs), " ".join(copy)))
    return docs + [(len(docs) + i, " ".join(word() for _ in range(60))) for i in range(10)]


@pytest.mark.parametrize("limit", [1, 4, 1000])
def test_all_similar_pairs(spark, limit):
    docs = edited_docs(limit)
    grouped, _, comp = near_copies.group_similar(spark.createDataFrame(docs, "doc_id long, text string"), limit)
    want = groups(docs)
    assert [r[comp] for r in grouped.orderBy("doc_id").collect()] == want
    assert 10 < len(set(want)) < len(docs)


def test_blocks(spark, monkeypatch):
    """Blocks of any size give the pairs that all pairs of profiles give."""
    rng = np.random.default_rng(3)
    monkeypatch.setattr(near_copies, "BLOCK_SETS", 7)
    base = rng.integers(-(1 << 62), 1 << 62, 60)
    sets = {}
    for _ in range(40):
        s = np.unique(np.concatenate([rng.choice(base, 56, replace=False), rng.integers(-(1 << 62), 1 << 62, rng.integers(0, 5))]))
        sets[near_copies.set_name(s)] = s
    rows = [(1, len(sets), k, len(s), k if i % 3 else 0, near_copies.profile(s)) for i, (k, s) in enumerate(sets.items())]
    got = near_copies.block_pairs(spark.createDataFrame(rows, "key long, held long, node long, n int, root long, profile binary")).collect()
    want = set()
    for i, x in enumerate(rows):
        for y in rows[:i]:
            apart = sum(abs(p - q) for p, q in zip(x[5], y[5], strict=True))
            if x[4] != y[4] and (x[3] + y[3] - apart) * 180 >= 2 * (x[3] + y[3]) * 80:
                want.add((min(x[2], y[2]), max(x[2], y[2])))
    assert {tuple(r) for r in got} == want and len(got) == len(want) > 20


def test_hot_passage_and_wide_group(spark, monkeypatch):
    """Documents around one passage, and copies that are similar to some of their group only: all links are found by the
    heads and the exact search of the rest, whatever the limits."""
    rng = random.Random(8)
    word = lambda: f"w{rng.randrange(5000)}"
    passage, base = [word() for _ in range(60)], [word() for _ in range(90)]
    docs = [(i, " ".join(passage + [word() for _ in range(50)])) for i in range(40)]
    for i in range(60):
        copy = list(base)
        for _ in range(rng.randrange(6)):
            copy[rng.randrange(len(copy))] = word()
        docs.append((100 + i, " ".join(copy)))
    want = groups(docs)
    for joined, block in ((2, 5), (32, 512)):
        monkeypatch.setattr(near_copies, "JOINED_SETS", joined)
        monkeypatch.setattr(near_copies, "BLOCK_SETS", block)
        grouped, _, comp = near_copies.group_similar(spark.createDataFrame(docs, "doc_id long, text string"))
        assert [r[comp] for r in grouped.orderBy("doc_id").collect()] == want


def test_stage_drops_edited_copy(spark, sf_dir):
    words = [f"w{i}" for i in range(120)]
    docs = spark.createDataFrame([(1, " ".join(words)), (2, " ".join(words[:60] + ["other"] + words[61:])), (3, " ".join(words) + "\none more line of text here"), (4, " ".join(words[::-1]))], "doc_id long, text string")
    assert sorted(r["doc_id"] for r in corpus_pipeline.near_dedup(spark, docs, sf_dir).collect()) == [1, 4]


def test_given(spark, sf_dir):
    docs = [tuple(r) for r in load(spark, sf_dir, "documents").select("doc_id", "text").collect()]
    got = near_copies.drop_similar(load(spark, sf_dir, "documents"))
    assert {r["doc_id"] for r in got.collect()} == set(groups(docs))


def test_similar_messy(clashing, nothing):
    docs = [r[:2] for r in messy_rows()]
    grouped, _, comp = near_copies.group_similar(clashing)
    want = groups(docs)
    assert sorted(((r["doc_id"], r[comp]) for r in grouped.collect()), key=repr) == sorted(((d, c) for (d, _), c in zip(docs, want, strict=True)), key=repr)
    kept = near_copies.drop_similar(clashing)
    assert kept.columns == clashing.columns
    assert sorted(r["doc_id"] for r in kept.collect() if r["doc_id"] is not None) == sorted({c for c in want if c is not None})
    assert near_copies.drop_similar(nothing).count() == 0


def test_pipeline_by_similarity(spark, sf_dir):
    """All stages on what the one before kept, the near-duplicate stage by the rule of five words and 0.8, and the run."""
    docs = load(spark, sf_dir, "documents")
    for name, stage in corpus_pipeline.STAGES:
        before = {r["doc_id"]: r["text"] for r in docs.collect()}
        made = stage(spark, docs, sf_dir)
        after = spark.createDataFrame(made.collect(), made.schema)
        got = {r["doc_id"]: r["text"] for r in after.collect()}
        pairs = sorted(before.items())
        if name == "line_dedup":
            assert [got[i] for i, _ in pairs] == [x[2] for x in brute.line_dedup(pairs)]
        elif name == "near_dedup":
            assert set(got) == set(groups(pairs)) and all(got[i] == before[i] for i in got)
        elif name == "decontamination":
            items = [tuple(r) for r in load(spark, sf_dir, "benchmark").select("item_id", "text").collect()]
            assert set(got) == {i for (i, _), x in zip(pairs, brute.leaks(pairs, items), strict=True) if not x[1]}
        assert set(got) <= set(before) and after.columns[: len(docs.columns)] == docs.columns
        docs = after
    whole = corpus_pipeline.run(spark, sf_dir)
    assert sorted((r["doc_id"], r["copies"]) for r in whole.collect()) == sorted((r["doc_id"], r["copies"]) for r in docs.collect())
