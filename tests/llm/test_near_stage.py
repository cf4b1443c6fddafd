"""The pipeline's near-duplicate stage links fingerprints as well as similar sets."""

import corpus_pipeline

from . import brute
from .test_near_copies import groups


def test_stage_links_fingerprints(spark, sf_dir):
    """A line repeated often settles the fingerprint, and an edit among few words the similarity: each kind of link drops a
    document that the other keeps, and a chain over both is one group."""
    line = " ".join(f"w{i}" for i in range(12))
    tail = lambda k: " ".join(f"{k}{i}" for i in range(40))
    words = tail("x").split()
    edited = " ".join([*words[:20], "other", *words[21:]])
    texts = [(1, "\n".join([line] * 60 + [tail("a")])), (2, "\n".join([line] * 60 + [tail("b")])), (3, tail("x") + " " + tail("y")), (4, edited + " " + tail("y")), (5, tail("z")), (6, "\n".join([line] * 4 + [tail("b")]))]
    ids = [i for i, _ in texts]
    prints, similar = brute.components(ids, [brute.simhash(t) for _, t in texts]), groups(texts)
    assert prints == [1, 1, 3, 4, 5, 6] and similar == [1, 2, 3, 3, 5, 2]
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    assert sorted(r["doc_id"] for r in corpus_pipeline.near_dedup(spark, docs, sf_dir).collect()) == [1, 3, 5]
