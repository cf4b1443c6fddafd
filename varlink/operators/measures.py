"""Accuracy and cost measures."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from ..functions.sampling import priority
from ..functions.vectors import sq_dist


def roc_auc(scored: DataFrame, by: list[str] | None = None, d: str = "d", y: str = "y") -> DataFrame:
    """Chance that a matched pair (``y`` = 1) has the smaller ``d`` than an unmatched one, ties counting half.

    Ranks come from counts per distinct score, so ties cost nothing and the running sum is over distinct scores.
    """
    by = by or []
    steps = scored.groupBy(*by, F.col(d)).agg(F.sum((F.col(y) == 1).cast("double")).alias("pos"), F.sum((F.col(y) == 0).cast("double")).alias("neg"))
    upto = Window.partitionBy(*by).orderBy(d).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    steps = steps.withColumn("beyond", F.sum("neg").over(Window.partitionBy(*by)) - F.sum("neg").over(upto))
    wins = F.sum(F.col("pos") * (F.col("beyond") + F.col("neg") / 2))
    return steps.groupBy(*by).agg((wins / (F.sum("pos") * F.sum("neg"))).alias("auc"))


def _marked(ranked: DataFrame, truth: DataFrame) -> DataFrame:
    return ranked.join(truth.select("query_id", "dataset_id").distinct().withColumn("hit", F.lit(1)), ["query_id", "dataset_id"], "left").withColumn("hit", F.coalesce("hit", F.lit(0)))


def matches_at_k(ranked: DataFrame, truth: DataFrame, ks: tuple[int, ...] = (1, 5, 10), by: list[str] | None = None) -> DataFrame:
    """``k, matches, hit_rate, queries``: correct datasets among the top k, averaged over queries, and the share of
    queries with at least one. Queries without any ranked dataset count as 0 if they are in ``truth``."""
    by = by or []
    marked = _marked(ranked, truth)
    per = marked.select(*by, "query_id", "rank", "hit", F.explode(F.array(*[F.lit(k) for k in ks])).alias("k")).filter("rank <= k").groupBy(*by, "k", "query_id").agg(F.sum("hit").alias("matches"))
    return per.groupBy(*by, "k").agg(F.avg("matches").alias("matches"), F.avg((F.col("matches") > 0).cast("double")).alias("hit_rate"), F.count("*").alias("queries"))


def hit_rate_at_k(ranked: DataFrame, truth: DataFrame, ks: tuple[int, ...] = (1, 5, 10)) -> DataFrame:
    return matches_at_k(ranked, truth, ks).select("k", "hit_rate")


def calibrated_recall(match_scores: DataFrame, nomatch_scores: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Of the probabilities ``p`` of true matches, the share above the largest one of each query without a match,
    averaged over these queries. The thresholds are few (one a query), the matches many: their counts above every
    threshold come from one sorted union."""
    by = by or []
    best = nomatch_scores.groupBy(*by, "query_id").agg(F.max("p").alias("p")).select(*by, "p", F.lit(0).alias("n"), F.lit(1).alias("q"))
    both = match_scores.select(*by, "p", F.lit(1).alias("n"), F.lit(0).alias("q")).unionByName(best).groupBy(*by, "p").agg(F.sum("n").alias("n"), F.sum("q").alias("q"))
    above = Window.partitionBy(*by).orderBy(F.desc("p")).rowsBetween(Window.unboundedPreceding, -1)
    shares = both.withColumn("share", F.coalesce(F.sum("n").over(above), F.lit(0)) / F.sum("n").over(Window.partitionBy(*by)))
    return shares.groupBy(*by).agg((F.sum(F.col("share") * F.col("q")) / F.sum("q")).alias("recall"), F.sum("q").alias("queries"))


def alignment_precision(alignment: DataFrame, truth: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Correctly aligned among aligned columns: ``col_a, col_b`` against true pairs."""
    by = by or []
    m = alignment.join(truth.select(*by, "col_a", "col_b").distinct().withColumn("ok", F.lit(1)), [*by, "col_a", "col_b"], "left")
    return m.groupBy(*by).agg(F.avg(F.coalesce("ok", F.lit(0)).cast("double")).alias("precision"), F.count("*").alias("aligned"))


def precision_recall_at_k(ranked: DataFrame, truth: DataFrame, ks: tuple[int, ...], by: list[str] | None = None) -> DataFrame:
    """``k, precision, recall`` averaged over queries; precision is over k, recall over the query's true datasets."""
    by = by or []
    size = truth.select("query_id", "dataset_id").distinct().groupBy("query_id").agg(F.count("*").alias("n_true"))
    per = _marked(ranked, truth).select(*by, "query_id", "rank", "hit", F.explode(F.array(*[F.lit(k) for k in ks])).alias("k")).filter("rank <= k").groupBy(*by, "k", "query_id").agg(F.sum("hit").alias("hits"))
    return per.join(size, "query_id").groupBy(*by, "k").agg(F.avg(F.col("hits") / F.col("k")).alias("precision"), F.avg(F.col("hits") / F.col("n_true")).alias("recall"))


def index_recall(approx: DataFrame, exact: DataFrame, k: int) -> DataFrame:
    """Share of the exact top k that an index returns, over queries."""
    e, a = exact.filter(F.col("rank") <= k), approx.filter(F.col("rank") <= k).select("query_id", "dataset_id").withColumn("got", F.lit(1))
    return e.join(a, ["query_id", "dataset_id"], "left").agg(F.avg(F.coalesce("got", F.lit(0)).cast("double")).alias("recall"), F.countDistinct("query_id").alias("queries"))


def empirical_deviation(bags: DataFrame, pairs: DataFrame, n: int, eps: float, draws: int, vec: str = "vec", key: str = "row_key", width: int = 64) -> DataFrame:
    """Share of seeded draws of ``n`` values a side whose squared distance is off by more than ``eps``."""
    mean = lambda df, *by: df.groupBy(*by).agg(F.array(*[F.avg(F.col(vec)[i].cast("double")) for i in range(width)]).alias("m"), F.max(sq_dist(F.col(vec), F.transform(vec, lambda x: x * 0))).alias("b"))
    drawn = bags.withColumn("draw", F.explode(F.sequence(F.lit(1), F.lit(draws))))
    order = Window.partitionBy("draw", "dataset_id").orderBy(priority(F.col("draw"), F.col("dataset_id"), F.col(key)), key)
    sample = mean(drawn.withColumn("r", F.row_number().over(order)).filter(F.col("r") <= n), "draw", "dataset_id")
    whole = mean(bags, "dataset_id")
    side = lambda df, k, *by: df.select(*by, F.col("dataset_id").alias(f"id_{k}"), F.col("m").alias(f"m_{k}"), F.col("b").alias(f"b_{k}"))
    full = pairs.select("id_a", "id_b").join(side(whole, "a"), "id_a").join(side(whole, "b"), "id_b").select("id_a", "id_b", sq_dist(F.col("m_a"), F.col("m_b")).alias("d"), F.greatest("b_a", "b_b").alias("b"))
    part = pairs.select("id_a", "id_b").join(side(sample, "a", "draw"), "id_a").join(side(sample, "b", "draw"), ["draw", "id_b"]).select("id_a", "id_b", "draw", sq_dist(F.col("m_a"), F.col("m_b")).alias("d_n"))
    off = part.join(full, ["id_a", "id_b"]).select((F.abs(F.col("d_n") - F.col("d")) > eps).cast("double").alias("off"), "b")
    b = F.max("b")
    return off.agg(F.lit(n).alias("n"), F.lit(eps).alias("eps"), F.avg("off").alias("rate"), F.least(F.lit(1.0), 4 * F.exp(-F.lit(n) * eps * eps / (32 * b * b))).alias("bound"), F.count("*").alias("draws"))


def neighbour_purity(points: DataFrame, k: int = 5) -> DataFrame:
    """Share of each point's ``k`` nearest points (``x, y``; at most a few thousand) with its own variable."""
    a, b = points.alias("a"), points.alias("b")
    d = (F.col("a.x") - F.col("b.x")) ** 2 + (F.col("a.y") - F.col("b.y")) ** 2
    near = a.join(b, F.col("a.dataset_id") != F.col("b.dataset_id")).select(F.col("a.dataset_id").alias("dataset_id"), (F.col("a.variable") == F.col("b.variable")).cast("double").alias("same"), d.alias("d"), F.col("b.dataset_id").alias("other"))
    order = Window.partitionBy("dataset_id").orderBy("d", "other")
    return near.withColumn("r", F.row_number().over(order)).filter(F.col("r") <= k).groupBy("dataset_id").agg(F.avg("same").alias("purity"))


def observe_cost(df: DataFrame, name: str, run) -> tuple[int, float]:
    """Rows that pass ``df`` and the seconds of ``run(df)``, counted while it runs."""
    seen, began = Observation(name), time.time()
    run(df.observe(seen, F.count(F.lit(1)).alias("rows")))
    return seen.get["rows"], time.time() - began


def report(scored: DataFrame, keys: list[str], value: str, mode: str = "cube") -> DataFrame:
    """Mean of ``value`` over all combinations of ``keys`` (``cube``, ``rollup`` or the plain grouping sets)."""
    grouped = {"cube": scored.cube, "rollup": scored.rollup}.get(mode)
    agg = [F.grouping_id().alias("gid"), F.count("*").alias("n"), F.avg(value).alias(f"mean_{value}")]
    return grouped(*keys).agg(*agg) if grouped else scored.groupingSets([[k] for k in keys] + [[]], *keys).agg(*agg)


def report_wide(scored: DataFrame, rows: list[str], column: str, values: list[str], value: str) -> DataFrame:
    return scored.groupBy(*rows).pivot(column, values).agg(F.avg(value))


def top_adjustment(vectors: DataFrame, hist: DataFrame, k: int, value: str = "value_num") -> DataFrame:
    """The ``k`` datasets with the largest adjustment, with their commonest value and its share."""
    top = vectors.orderBy(F.desc("g"), "dataset_id").select("dataset_id", "g").limit(k)
    order = Window.partitionBy("dataset_id").orderBy(F.desc("weight"), value)
    best = hist.join(top, "dataset_id", "left_semi").withColumns({"r": F.row_number().over(order), "n": F.sum("weight").over(Window.partitionBy("dataset_id"))}).filter("r = 1")
    return top.join(best, "dataset_id").select("dataset_id", "g", F.col(value).alias("top_value"), (F.col("weight") / F.col("n")).alias("top_share"))


