"""Schema alignment and table-union search."""

from __future__ import annotations

from itertools import permutations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scores import match_probability, match_score

# ------------------------------------------------------------------ one matrix


def align_greedy(p: np.ndarray) -> list[tuple[int, int]]:
    """Best remaining pair first; ties by row and column."""
    out, rows, cols = [], set(range(p.shape[0])), set(range(p.shape[1]))
    for i, j in sorted(np.ndindex(*p.shape), key=lambda x: (-p[x], x)):
        if i in rows and j in cols:
            out.append((i, j))
            rows.discard(i)
            cols.discard(j)
    return sorted(out)


def _two_opt(p: np.ndarray, match: np.ndarray) -> np.ndarray:
    """Swap the partners of two rows as long as the sum grows; columns without a row count as partners of nobody."""
    n, m = p.shape
    match = match.copy()
    better = True
    while better:
        better = False
        for i in range(n):
            for j in range(i + 1, n):
                if p[i, match[j]] + p[j, match[i]] > p[i, match[i]] + p[j, match[j]] + 1e-12:
                    match[i], match[j] = match[j], match[i]
                    better = True
            free = np.setdiff1d(np.arange(m), match)
            if len(free) and p[i, free].max() > p[i, match[i]] + 1e-12:
                match[i] = free[p[i, free].argmax()]
                better = True
    return match


def align_two_opt(p: np.ndarray, restarts: int = 5, seed: int = 1) -> list[tuple[int, int]]:
    """One-to-one alignment by two-way swaps, from the greedy alignment and ``restarts`` random ones; the best is kept."""
    if not p.size:
        return []
    if p.shape[0] > p.shape[1]:
        return sorted((i, j) for j, i in align_two_opt(p.T, restarts, seed))
    rng = np.random.default_rng(seed)
    starts = [np.array([j for _, j in align_greedy(p)])] + [rng.permutation(p.shape[1])[: p.shape[0]] for _ in range(restarts)]
    found = [_two_opt(p, s) for s in starts]
    best = max(found, key=lambda m: p[np.arange(len(m)), m].sum())
    return [(i, int(j)) for i, j in enumerate(best)]


def align_exact(p: np.ndarray) -> list[tuple[int, int]]:
    """The best one-to-one alignment by trying all; for at most about eight columns."""
    if p.shape[0] > p.shape[1]:
        return sorted((i, j) for j, i in align_exact(p.T))
    best = max(permutations(range(p.shape[1]), p.shape[0]), key=lambda m: sum(p[i, j] for i, j in enumerate(m)))
    return list(enumerate(best))


ALIGNERS = {"two_opt": align_two_opt, "greedy": align_greedy, "exact": align_exact}


# ------------------------------------------------------------------ DataFrames


def similarity_matrix(pairs_scored: DataFrame) -> DataFrame:
    """``group_id, col_a, col_b, p`` from any scorer's ``group_id, id_a, id_b, d``: p = exp(-d)."""
    return pairs_scored.select("group_id", F.col("id_a").alias("col_a"), F.col("id_b").alias("col_b"), F.exp(-F.col("d")).alias("p"))


def vector_similarity(va: DataFrame, vb: DataFrame) -> DataFrame:
    """``col_a, col_b, p`` of all column pairs of one kind of two schemas, from their vectors (tens of columns each)."""
    side = lambda v, k: v.select("kind", F.col("dataset_id").alias(f"col_{k}"), F.col("h").alias(f"h_{k}"), F.col("g").alias(f"g_{k}"))
    return side(va, "a").join(side(vb, "b"), "kind").select("col_a", "col_b", match_probability(match_score(F.col("h_a"), F.col("h_b"), F.col("g_a"), F.col("g_b"))).alias("p"))


def _matrix(frame: pd.DataFrame) -> tuple[list, list, np.ndarray]:
    rows, cols = sorted(frame["col_a"].unique()), sorted(frame["col_b"].unique())
    p = np.zeros((len(rows), len(cols)))
    p[[rows.index(x) for x in frame["col_a"]], [cols.index(x) for x in frame["col_b"]]] = frame["p"]
    return rows, cols, p


def align_schemas(matrix: DataFrame, method: str = "two_opt", restarts: int = 5, seed: int = 1) -> DataFrame:
    """``group_id, col_a, col_b, p``: the one-to-one alignment of every group (a pair of schemas)."""

    def one(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        rows, cols, p = _matrix(frame)
        found = ALIGNERS[method](p, restarts, seed) if method == "two_opt" else ALIGNERS[method](p)
        return pd.DataFrame([(key[0], rows[i], cols[j], p[i, j]) for i, j in found], columns=["group_id", "col_a", "col_b", "p"])

    return matrix.groupBy("group_id").applyInPandas(one, "group_id string, col_a string, col_b string, p double")


def prefix_goodness(alignment: DataFrame) -> DataFrame:
    """``group_id, c, log_p``: for each c the log of the product of the c best aligned pairs."""
    order = Window.partitionBy("group_id").orderBy(F.desc("p"), "col_a").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rank = Window.partitionBy("group_id").orderBy(F.desc("p"), "col_a")
    return alignment.select("group_id", F.row_number().over(rank).alias("c"), F.sum(F.log(F.greatest("p", F.lit(1e-12)))).over(order).alias("log_p"))


def max_c_alignment(alignment: DataFrame, background: DataFrame) -> DataFrame:
    """``group_id, c, goodness``: the c whose product ranks highest among those of background pairs of tables with the
    same c; equal goodness prefers more columns. Both inputs are :func:`align_schemas` results."""
    own, bg = prefix_goodness(alignment), prefix_goodness(background)
    both = own.withColumn("bg", F.lit(0)).unionByName(bg.withColumn("bg", F.lit(1)))
    steps = both.groupBy("c", "log_p").agg(F.sum("bg").alias("n"))
    below = Window.partitionBy("c").orderBy("log_p").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    share = steps.select("c", "log_p", ((F.sum("n").over(below)) / F.greatest(F.lit(1), F.sum("n").over(Window.partitionBy("c")))).alias("goodness"))
    ranked = own.join(share, ["c", "log_p"])
    order = Window.partitionBy("group_id").orderBy(F.desc("goodness"), F.desc("c"))
    return ranked.withColumn("r", F.row_number().over(order)).filter("r = 1").select("group_id", "c", "goodness", "log_p")


def union_search(column_pairs: DataFrame, k: int, background: DataFrame | None = None, method: str = "two_opt") -> DataFrame:
    """``query_table, table_id, rank, score, c``: tables ranked for union with each query table.

    ``column_pairs``: ``query_table, table_id, col_a, col_b, p`` of candidate tables (from nearest-neighbour search of
    the query's columns). With ``background`` (the same, of random table pairs) the score is the percentile of the best
    c-alignment; without it, the mean probability of the aligned columns over the query's columns.
    """
    key = lambda df: df.select(F.concat_ws("\u0001", "query_table", "table_id").alias("group_id"), "col_a", "col_b", "p")
    aligned = align_schemas(key(column_pairs), method)
    if background is not None:
        best = max_c_alignment(aligned, align_schemas(key(background), method)).select("group_id", F.col("goodness").alias("score"), "c", "log_p")
    else:
        size = column_pairs.groupBy("query_table").agg(F.countDistinct("col_a").alias("m"))
        best = aligned.groupBy("group_id").agg(F.sum("p").alias("total"), F.count("*").alias("c"), F.sum(F.log(F.greatest("p", F.lit(1e-12)))).alias("log_p"))
        best = best.withColumn("query_table", F.split("group_id", "\u0001")[0]).join(size, "query_table").select("group_id", (F.col("total") / F.col("m")).alias("score"), "c", "log_p")
    out = best.select(F.split("group_id", "\u0001")[0].alias("query_table"), F.split("group_id", "\u0001")[1].alias("table_id"), "score", "c", "log_p")
    order = Window.partitionBy("query_table").orderBy(F.desc("score"), F.desc("c"), F.desc("log_p"), "table_id")
    return out.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).drop("log_p")


def is_unionable(alignment: DataFrame, n_columns: DataFrame, share: float = 0.5, tau: float = 0.5) -> DataFrame:
    """``group_id, unionable``: enough of the columns (``group_id, n_columns``) are aligned with probability ``tau``."""
    good = alignment.filter(F.col("p") >= tau).groupBy("group_id").agg(F.count("*").alias("good"))
    return n_columns.join(good, "group_id", "left").select("group_id", (F.coalesce("good", F.lit(0)) >= share * F.col("n_columns")).alias("unionable"))


def union_tables(a: DataFrame, b: DataFrame, alignment: list[tuple[str, str]]) -> DataFrame:
    """``b``'s aligned columns under ``a``'s names, below ``a``; what is missing on a side is null."""
    names = {y: x for x, y in alignment}
    clash = set(a.columns)
    rest = {c: f"{c}_b" for c in b.columns if c not in names and c in clash}
    return a.unionByName(b.withColumnsRenamed({**names, **rest}), allowMissingColumns=True)
