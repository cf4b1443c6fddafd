"""Queries whose data was once written in the code read given tables."""

import pytest

from varlink.plans import registry, score_queries

_ = score_queries
SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name, tables", [("q29_label_cosine", {"part", "customer", "events", "documents"}), ("q30_jaro_winkler", {"part", "customer", "events", "documents"}), ("q31_drop_vague", {"part", "customer", "events", "documents"}), ("q38_bound", {"embeddings"})])
def test_reads_tables(spark, name, tables):
    df = registry.QUERIES[name](spark, SF)
    assert {f.rsplit("/", 1)[1].split(".")[0] for f in df.inputFiles()} == tables
    assert df.count() > 0
