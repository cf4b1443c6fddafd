"""The engine's functions and views for plain SQL."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from .text import jaro_winkler_udf


def register(spark: SparkSession, catalog: DataFrame | None = None, vectors: DataFrame | None = None) -> None:
    """Temporary functions ``sq_dist, match_score, match_probability, pair_loss`` (SQL bodies, inlined by Catalyst),
    ``jaro_winkler``, ``top_matches`` and ``align_columns``, and views ``catalog`` and ``vectors``."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sq_dist(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION match_score(ha ARRAY<DOUBLE>, hb ARRAY<DOUBLE>, ga DOUBLE, gb DOUBLE) RETURNS DOUBLE RETURN aggregate(zip_with(ha, hb, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x) + ga + gb")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION match_probability(d DOUBLE) RETURNS DOUBLE RETURN exp(-d)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pair_loss(d DOUBLE, y INT) RETURNS DOUBLE RETURN if(y = 1, d, -ln(-expm1(-greatest(d, 1e-7D))))")
    spark.udf.register("jaro_winkler", jaro_winkler_udf())
    spark.udtf.register("top_matches", TopMatches)
    spark.udtf.register("align_columns", AlignColumns)
    if catalog is not None:
        catalog.createOrReplaceTempView("catalog")
    if vectors is not None:
        vectors.createOrReplaceTempView("vectors")


@udtf(returnType="dataset_id string, d double, rank int")
class TopMatches:
    """``SELECT * FROM top_matches(TABLE(SELECT dataset_id, s FROM ...) WITH SINGLE PARTITION, query, k)``: the k nearest
    rows of a small table of vectors. A bounded heap is kept, not the rows."""

    def __init__(self):
        self.best: list[tuple[float, str]] = []
        self.k = 0

    def eval(self, row, query: list, k: int) -> None:
        self.k = k
        d = sum((x - y) ** 2 for x, y in zip(row["s"], query, strict=True))
        self.best = sorted([*self.best, (d, row["dataset_id"])])[:k]

    def terminate(self) -> Iterator[tuple]:
        for i, (d, name) in enumerate(self.best):
            yield name, d, i + 1




@udtf(returnType="col_a string, col_b string, p double")
class AlignColumns:
    """``SELECT * FROM align_columns(TABLE(SELECT col_a, col_b, p FROM ...) WITH SINGLE PARTITION)``: the one-to-one
    alignment of two schemas by two-way swaps. The rows are the pairs of two schemas' columns."""

    def __init__(self):
        self.p: dict[tuple[str, str], float] = {}

    def eval(self, row) -> None:
        self.p[row["col_a"], row["col_b"]] = row["p"]

    def terminate(self) -> Iterator[tuple]:
        import numpy as np

        from ..operators.alignment import align_two_opt

        rows, cols = (sorted({k[i] for k in self.p}) for i in (0, 1))
        m = np.array([[self.p.get((a, b), 0.0) for b in cols] for a in rows]).reshape(len(rows), len(cols))
        for i, j in align_two_opt(m):
            yield rows[i], cols[j], float(m[i, j])
