"""Baselines: distances of dataset pairs by their values' distribution. All return ``id_a, id_b, method, d``; a smaller d
means more alike.

Those with exact aggregate forms run on histograms or moments inside Catalyst. Those that need a dense solve or a random
order get the two samples of a pair packed as arrays (bounded by the sub-sample size) and run as Arrow batches.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.sampling import below, priority
from ..functions.vectors import sq_dist
from . import statistics as S
from .columnize import dataset_stats, value_histogram

PAIR = ["id_a", "id_b"]


def _named(df: DataFrame, method: str, d: Column | str) -> DataFrame:
    return df.select(*PAIR, F.lit(method).alias("method"), (F.col(d) if isinstance(d, str) else d).alias("d"))


def _sides(per_dataset: DataFrame, pairs: DataFrame) -> DataFrame:
    """``pairs`` with the columns of both datasets, suffixed ``_a`` and ``_b``."""
    columns = [c for c in per_dataset.columns if c != "dataset_id"]
    a = per_dataset.select(F.col("dataset_id").alias("id_a"), *[F.col(c).alias(f"{c}_a") for c in columns])
    b = per_dataset.select(F.col("dataset_id").alias("id_b"), *[F.col(c).alias(f"{c}_b") for c in columns])
    return pairs.select(*PAIR).join(a, "id_a").join(b, "id_b")


def mean_sd_distance(cv: DataFrame, pairs: DataFrame) -> DataFrame:
    return _named(_sides(dataset_stats(cv), pairs), "mean_sd", F.abs(F.col("mean_a") - F.col("mean_b")) + F.abs(F.col("sd_a") - F.col("sd_b")))


# ------------------------------------------------------------------ on histograms


def _merged(hist: DataFrame, pairs: DataFrame, value: str) -> DataFrame:
    """``id_a, id_b, value, wa, wb``: every value of either side of each pair with both multiplicities."""
    side = lambda k: hist.select(F.col("dataset_id").alias(f"id_{k}"), F.col(value).alias("value"), F.col("weight").cast("double").alias("w"))
    a = pairs.select(*PAIR).join(side("a"), "id_a").select(*PAIR, "value", F.col("w").alias("wa"), F.lit(0.0).alias("wb"))
    b = pairs.select(*PAIR).join(side("b"), "id_b").select(*PAIR, "value", F.lit(0.0).alias("wa"), F.col("w").alias("wb"))
    return a.unionByName(b).groupBy(*PAIR, "value").agg(F.sum("wa").alias("wa"), F.sum("wb").alias("wb"))


def _shared(hist: DataFrame, pairs: DataFrame, value: str, *sums: Column) -> DataFrame:
    """Each pair with totals ``n``, squares ``q`` and distinct values ``u`` of both sides, and ``sums`` over the multiplicities
    ``w_a, w_b`` of shared values (null where none is shared).

    Values of either side's datasets meet once, and sums per pair are made before the shuffle; the list of pairs is joined
    to these sums and never to the values.
    """
    w = F.col("weight").cast("double")
    sizes = hist.groupBy("dataset_id").agg(F.sum(w).alias("n"), F.sum(w * w).alias("q"), F.count("*").alias("u"))
    side = lambda k: hist.select(F.col("dataset_id").alias(f"id_{k}"), F.col(value).alias("value"), w.alias(f"w_{k}")).join(pairs.select(f"id_{k}").distinct(), f"id_{k}", "left_semi")
    return _sides(sizes, pairs).join(side("a").join(side("b"), "value").groupBy(*PAIR).agg(*sums), PAIR, "left")


def ks_p(gap: Column, n1: Column, n2: Column) -> Column:
    e = n1 * n2 / (n1 + n2)
    lam = (F.sqrt(e) + 0.12 + F.lit(0.11) / F.sqrt(e)) * gap
    series = F.aggregate(F.sequence(F.lit(1), F.lit(100)), F.lit(0.0), lambda s, j: s + F.when(j % 2 == 1, F.lit(2.0)).otherwise(F.lit(-2.0)) * F.exp(-2.0 * j * j * lam * lam))
    return F.when(lam < 0.2, F.lit(1.0)).otherwise(F.least(F.lit(1.0), F.greatest(F.lit(0.0), series)))


def ks_gap(hist: DataFrame, pairs: DataFrame, value: str = "value_num") -> DataFrame:
    """``id_a, id_b, gap, n1, n2, p``. The running window of a pair is as long as its distinct values."""
    run = Window.partitionBy(*PAIR).orderBy("value").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    whole = Window.partitionBy(*PAIR)
    m = _merged(hist, pairs, value).withColumns({"ca": F.sum("wa").over(run), "cb": F.sum("wb").over(run), "na": F.sum("wa").over(whole), "nb": F.sum("wb").over(whole)})
    g = m.groupBy(*PAIR).agg(F.max(F.abs(F.col("ca") / F.col("na") - F.col("cb") / F.col("nb"))).alias("gap"), F.max("na").alias("n1"), F.max("nb").alias("n2"))
    return g.withColumn("p", ks_p(F.col("gap"), F.col("n1"), F.col("n2")))


def ks_distance(hist: DataFrame, pairs: DataFrame, value: str = "value_num") -> DataFrame:
    return _named(ks_gap(hist, pairs, value), "ks", 1 - F.col("p"))


def jaccard_distance(hist: DataFrame, pairs: DataFrame, value: str = "value_num") -> DataFrame:
    """One minus shared over all distinct values."""
    weighted = hist if "weight" in hist.columns else hist.withColumn("weight", F.lit(1))
    s = _shared(weighted, pairs, value, F.count("*").alias("shared"))
    shared = F.coalesce(F.col("shared"), F.lit(0)).cast("double")
    return _named(s, "jaccard", 1 - shared / (F.col("u_a") + F.col("u_b") - shared))


def jaccard_minhash(cv_values: DataFrame, pairs: DataFrame, value: str = "value_num", hashes: int = 128) -> DataFrame:
    """The same estimated from minima of seeded hashes: a fixed-size, mergeable state per dataset, for huge value sets."""
    mins = cv_values.groupBy("dataset_id").agg(F.array(*[F.min(F.xxhash64(F.lit(i), F.col(value))) for i in range(hashes)]).alias("mins"))
    same = F.aggregate(F.zip_with("mins_a", "mins_b", lambda x, y: (x == y).cast("double")), F.lit(0.0), lambda s, x: s + x)
    return _named(_sides(mins, pairs), "jaccard_minhash", 1 - same / hashes)


def likelihood_similarity(hist: DataFrame, pairs: DataFrame, value: str = "value_num", smoothing: float = 1.0) -> DataFrame:
    """Mean log-likelihood of each side's values under the other's smoothed histogram, both ways averaged and negated.

    A value that the other side lacks has the smoothing as its count, so beyond the shared values only totals count.
    """
    w = lambda k: F.col(f"w_{k}")
    log_of = lambda x: F.log(x + smoothing) - math.log(smoothing)
    s = _shared(hist, pairs, value, F.sum(w("a") * log_of(w("b"))).alias("ab"), F.sum(w("b") * log_of(w("a"))).alias("ba"), F.count("*").alias("shared"))
    filled = lambda c: F.coalesce(F.col(c), F.lit(0.0))
    union = F.col("u_a") + F.col("u_b") - filled("shared")
    one = lambda c, own, other: filled(c) / F.col(own) + math.log(smoothing) - F.log(F.col(other) + smoothing * union)
    return _named(s, "likelihood", -(one("ab", "n_a", "n_b") + one("ba", "n_b", "n_a")) / 2)


def probability_vector_distance(hist: DataFrame, pairs: DataFrame, value: str = "value_num") -> DataFrame:
    """Euclidean distance of the two vectors of value probabilities, from their squares and the product over shared values."""
    s = _shared(hist, pairs, value, F.sum(F.col("w_a") * F.col("w_b")).alias("cross"))
    square = lambda k: F.col(f"q_{k}") / F.col(f"n_{k}") / F.col(f"n_{k}")
    both = F.coalesce(F.col("cross"), F.lit(0.0)) / F.col("n_a") / F.col("n_b")
    return _named(s, "probability_vector", F.sqrt(F.greatest(square("a") + square("b") - 2 * both, F.lit(0.0))))


def bin_of(v: Column, edges: list[float]) -> Column:
    """Number of edges at or below ``v``."""
    return F.aggregate(F.array(*[F.lit(float(e)) for e in edges]), F.lit(0), lambda s, e: s + (v >= e).cast("int"))


def bin_join(values: DataFrame, bins: DataFrame, value: str = "value_num") -> DataFrame:
    """Values into intervals ``[low, high)`` of a small table of bins, as a range condition."""
    return values.join(F.broadcast(bins), (F.col(value) >= F.col("low")) & (F.col(value) < F.col("high")))


def histogram_features(cv: DataFrame, edges: list[float]) -> DataFrame:
    """Mean of the bin indicators of every dataset, as a histogram over bins: ``dataset_id, value_num, weight``."""
    return cv.groupBy("dataset_id", bin_of(F.col("value_num"), edges).cast("double").alias("value_num")).agg(F.count("*").alias("weight"))


def histogram_distance(cv: DataFrame, pairs: DataFrame, edges: list[float]) -> DataFrame:
    """Distance of mean bin indicators."""
    return probability_vector_distance(histogram_features(cv, edges), pairs).withColumn("method", F.lit("histogram"))


def mean_feature_distance(cv: DataFrame, pairs: DataFrame, features: list[Column]) -> DataFrame:
    """The general form: Euclidean distance of the means of any feature map, given as column expressions."""
    means = cv.groupBy("dataset_id").agg(F.array(*[F.avg(f.cast("double")) for f in features]).alias("m"))
    return _named(_sides(means, pairs), "mean_feature", F.sqrt(sq_dist(F.col("m_a"), F.col("m_b"))))


# ------------------------------------------------------------------ kernels in Catalyst


def _rbf(d: Column, bandwidth: Column | float) -> Column:
    b = bandwidth if isinstance(bandwidth, Column) else F.lit(float(bandwidth))
    return F.exp(-(d * d) / (2 * b * b))


def ordered_values(cv: DataFrame, seed: int = 5, key: str = "row_key") -> DataFrame:
    """Values of each dataset in seeded order: ``dataset_id, ordinal, value_num`` from 0."""
    p = priority(seed, F.col("dataset_id"), F.col(key))
    return cv.select("dataset_id", "value_num", (F.row_number().over(Window.partitionBy("dataset_id").orderBy(p, key, "value_num")) - 1).alias("ordinal"))


def mmd_linear_sql(cv: DataFrame, pairs: DataFrame, bandwidth: float, seed: int = 5) -> DataFrame:
    """Linear-time kernel discrepancy with a fixed bandwidth: each dataset is sorted once and folded into consecutive
    pairs, which then meet by ordinal."""
    v = ordered_values(cv, seed)
    folded = v.groupBy("dataset_id", F.floor(F.col("ordinal") / 2).alias("i")).agg(F.max(F.when(F.col("ordinal") % 2 == 0, F.col("value_num"))).alias("u"), F.max(F.when(F.col("ordinal") % 2 == 1, F.col("value_num"))).alias("v")).filter("u IS NOT NULL AND v IS NOT NULL")
    side = lambda k: folded.select(F.col("dataset_id").alias(f"id_{k}"), "i", F.col("u").alias(f"u{k}"), F.col("v").alias(f"v{k}"))
    m = pairs.select(*PAIR).join(side("a"), "id_a").join(side("b"), ["id_b", "i"])
    k = lambda x, y: _rbf(F.col(x) - F.col(y), bandwidth)
    return _named(m.groupBy(*PAIR).agg(F.avg(k("ua", "va") + k("ub", "vb") - k("ua", "vb") - k("va", "ub")).alias("x")), "mmd_linear", "x")


def mmd_quadratic_sql(hist: DataFrame, pairs: DataFrame, bandwidth: float) -> DataFrame:
    """All-pairs kernel discrepancy (each value with itself counted) on histograms of sub-samples."""
    probs = hist.select("dataset_id", "value_num", (F.col("weight") / F.sum("weight").over(Window.partitionBy("dataset_id"))).alias("p"))
    side = lambda k, n: probs.select(F.col("dataset_id").alias(f"id_{k}"), F.col("value_num").alias(f"x{n}"), F.col("p").alias(f"p{n}"))
    term = lambda a, b: (F.sum(F.col("p1") * F.col("p2") * _rbf(F.col("x1") - F.col("x2"), bandwidth)))
    own = side("a", 1).join(side("a", 2), "id_a").groupBy(F.col("id_a").alias("dataset_id")).agg(term(1, 2).alias("own"))
    cross = pairs.select(*PAIR).join(side("a", 1), "id_a").join(side("b", 2), "id_b").groupBy(*PAIR).agg(term(1, 2).alias("between"))
    return _named(_sides(own, pairs).join(cross, PAIR), "mmd_quadratic", F.col("own_a") + F.col("own_b") - 2 * F.col("between"))


def cf_moments(cv: DataFrame, freqs: list[float], mean: float, sd: float) -> DataFrame:
    """Mean smoothed sine and cosine features per dataset and frequency, values standardised by the given moments."""
    z = (F.col("value_num") - mean) / sd
    w = F.exp(-(z * z) / 2)
    each = F.explode(F.array(*[F.struct(F.lit(i).alias("j"), (w * F.sin(z * f)).alias("s"), (w * F.cos(z * f)).alias("c")) for i, f in enumerate(freqs)]))
    return cv.select("dataset_id", each.alias("x")).groupBy("dataset_id", "x.j").agg(F.avg("x.s").alias("mean_sin"), F.avg("x.c").alias("mean_cos"))


# ------------------------------------------------------------------ on packed samples


def pack(cv: DataFrame, value: str = "value_num", n: int = 1000, seed: int = 5, key: str = "row_key", sizes: DataFrame | None = None) -> DataFrame:
    """``dataset_id, values``: at most ``n`` values in seeded order, the published bound of a test's sample. Only these are
    gathered.

    With ``sizes`` (``dataset_id, n_values``) its datasets alone are packed, and their rows thinned by priority to about
    ``2 n + 100`` before any is sorted: fewer than n would be left by a deviation of sqrt(n) / sqrt(2) standard deviations or more.
    """
    p = priority(seed, F.col("dataset_id"), F.col(key))
    if sizes is not None:
        cv = cv.join(sizes.select("dataset_id", "n_values"), "dataset_id").filter((F.col("n_values") <= 2 * n + 100) | below((2 * n + 100) / F.col("n_values"), seed, F.col("dataset_id"), F.col(key)))
    ranked = cv.select("dataset_id", F.col(value).alias("value"), p.alias("p"), F.row_number().over(Window.partitionBy("dataset_id").orderBy(p, key)).alias("r")).filter(F.col("r") <= n)
    return ranked.groupBy("dataset_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("r", "value"))), lambda x: x["value"]).alias("values"))


def _on_arrays(packed: DataFrame, pairs: DataFrame, method: str, fn) -> DataFrame:
    @F.pandas_udf("double")
    def run(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([fn(np.asarray(list(x)), np.asarray(list(y))) for x, y in zip(a, b, strict=True)], dtype="float64")

    return _named(_sides(packed, pairs), method, run("values_a", "values_b"))


def mmd_linear(packed: DataFrame, pairs: DataFrame, bandwidth: float | str = "median") -> DataFrame:
    return _on_arrays(packed, pairs, "mmd_linear", lambda x, y: S.mmd_linear(x, y, S.median_bandwidth(x, y) if bandwidth == "median" else bandwidth))


def mmd_quadratic(packed: DataFrame, pairs: DataFrame, bandwidth: float | str = "median", estimator: str = "v") -> DataFrame:
    return _on_arrays(packed, pairs, "mmd_quadratic", lambda x, y: S.mmd_quadratic(x, y, S.median_bandwidth(x, y) if bandwidth == "median" else bandwidth, estimator))


def test_frequencies(j: int = 10, seed: int = 13) -> np.ndarray:
    return np.random.default_rng(seed).normal(size=j)


def smooth_cf_distance(packed: DataFrame, pairs: DataFrame, j: int = 10, seed: int = 13, output: str = "stat") -> DataFrame:
    freqs = test_frequencies(j, seed)

    def one(x, y):
        s = S.smooth_cf(x, y, freqs)
        return s if output == "stat" else 1 - S.chi2_survival_even(s, 2 * j)

    return _on_arrays(packed, pairs, "smooth_cf", one)


def ks_packed(packed: DataFrame, pairs: DataFrame) -> DataFrame:
    """The Kolmogorov-Smirnov distance on packed samples, for many pairs of small samples."""

    def one(x, y):
        v = np.concatenate([x, y])
        gap = np.abs(np.searchsorted(np.sort(x), v, "right") / len(x) - np.searchsorted(np.sort(y), v, "right") / len(y)).max()
        return 1 - S.ks_survival(float(gap), len(x), len(y))

    return _on_arrays(packed, pairs, "ks", one)


def mean_sd_packed(packed: DataFrame, pairs: DataFrame) -> DataFrame:
    sd = lambda x: x.std(ddof=1) if len(x) > 1 else 0.0
    return _on_arrays(packed, pairs, "mean_sd", lambda x, y: abs(x.mean() - y.mean()) + abs(sd(x) - sd(y)))


def jaccard_packed(packed: DataFrame, pairs: DataFrame) -> DataFrame:
    def one(x, y):
        a, b = set(x.tolist()), set(y.tolist())
        return 1 - len(a & b) / len(a | b)

    return _on_arrays(packed, pairs, "jaccard", one)


def hotelling_distance(packed: DataFrame, pairs: DataFrame, encode=None, ridge: float = 1e-6, diag: bool = False, output: str = "p") -> DataFrame:
    """Two-sample test on the mean vectors of the fields. ``values`` are vectors, or texts that ``encode`` turns into
    vectors."""

    def one(x, y):
        x, y = (np.stack([encode(v) for v in s]) if encode else np.stack([np.asarray(v, float) for v in s]) for s in (x, y))
        t2, p = S.hotelling(x, y, ridge, diag)
        return 1 - p if output == "p" else t2

    return _on_arrays(packed, pairs, "hotelling", one)


def vector_moments(vectors: DataFrame, value: str = "vec", weight: Column | None = None) -> DataFrame:
    """``dataset_id, n, mean, cross``: count, mean and centred sums of products (row by row) of all vectors of a dataset.

    A vector counts ``weight`` times. Partitions add up counts, sums and products in numpy; only these sums are shuffled, one row for each entry.
    """

    def run(batches):
        held: dict[str, list] = {}
        for batch in batches:
            ids, times = np.array(batch.column("dataset_id").to_pylist(), dtype=object), batch.column("w").to_numpy()
            x = batch.column(value).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(batch.num_rows, -1)
            for name in set(ids.tolist()):
                own, w = x[ids == name], times[ids == name]
                part = np.concatenate([[w.sum()], w @ own, (own.T @ (own * w[:, None])).ravel()])
                held[name] = held[name] + part if name in held else part
        for name, sums in held.items():
            yield pa.RecordBatch.from_pydict({"dataset_id": [name] * len(sums), "at": np.arange(len(sums), dtype=np.int32), "total": sums})

    parts = vectors.select("dataset_id", value, (F.lit(1.0) if weight is None else weight.cast("double")).alias("w")).filter(F.col(value).isNotNull()).mapInArrow(run, "dataset_id string, at int, total double")
    sums = parts.groupBy("dataset_id", "at").agg(F.sum("total").alias("total"))
    whole = sums.groupBy("dataset_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "total"))), lambda x: x["total"]).alias("s"))

    @F.pandas_udf("struct<n: double, mean: array<double>, cross: array<double>>")
    def split(s: pd.Series) -> pd.DataFrame:
        out = []
        for one in s:
            one = np.asarray(one)
            d = int((np.sqrt(4 * len(one) - 3) - 1) / 2)  # 1 + d + d * d entries
            n, total = one[0], one[1 : d + 1]
            out.append((n, total / n, one[d + 1 :] - np.outer(total, total).ravel() / n))
        return pd.DataFrame(out, columns=["n", "mean", "cross"])

    return whole.select("dataset_id", split("s").alias("m")).select("dataset_id", "m.*")


def text_moments(packed: DataFrame, encode) -> DataFrame:
    """:func:`vector_moments` of packed texts: each distinct text of a dataset is encoded once, whatever its pairs."""

    @F.pandas_udf("array<double>")
    def run(values: pd.Series) -> pd.Series:
        return values.map(lambda v: np.asarray(encode(v), float).tolist())

    texts = packed.select("dataset_id", F.explode("values").alias("value")).groupBy("dataset_id", "value").agg(F.count("*").alias("weight"))
    return vector_moments(texts.select("dataset_id", run("value").alias("vec"), "weight"), weight=F.col("weight"))


def hotelling_of_moments(moments: DataFrame, pairs: DataFrame, ridge: float = 1e-6, output: str = "p") -> DataFrame:
    """The full-covariance test of every pair, from :func:`vector_moments`: no dataset is sampled."""

    @F.pandas_udf("double")
    def run(na: pd.Series, ma: pd.Series, ca: pd.Series, nb: pd.Series, mb: pd.Series, cb: pd.Series) -> pd.Series:
        out = []
        for n1, m1, c1, n2, m2, c2 in zip(na, ma, ca, nb, mb, cb, strict=True):
            d = len(m1)
            t2, p = S.hotelling_moments(n1, np.asarray(m1), np.asarray(c1).reshape(d, d), n2, np.asarray(m2), np.asarray(c2).reshape(d, d), ridge)
            out.append(1 - p if output == "p" else t2)
        return pd.Series(out, dtype="float64")

    return _named(_sides(moments, pairs), "hotelling", run("n_a", "mean_a", "cross_a", "n_b", "mean_b", "cross_b"))


def mean_word_vector_of_moments(moments: DataFrame, pairs: DataFrame) -> DataFrame:
    """:func:`mean_word_vector_distance` from :func:`text_moments`, which have the means already."""
    return _named(_sides(moments.select("dataset_id", F.col("mean").alias("m")), pairs), "mean_word_vector", F.sqrt(sq_dist(F.col("m_a"), F.col("m_b"))))


def smooth_cf_of_histograms(hist: DataFrame, pairs: DataFrame, j: int = 10, seed: int = 13) -> DataFrame:
    """The smoothed characteristic-function statistic of every pair on whole datasets (``dataset_id, value_num, weight``).

    The features depend on the pair's pooled mean and deviation, so each distinct value meets each of its pairs once; sums
    are then those of :func:`vector_moments`.
    """
    freqs, w, v = test_frequencies(j, seed), F.col("weight").cast("double"), F.col("value_num")
    first = hist.groupBy("dataset_id").agg(F.sum(w).alias("n"), F.sum(w * v).alias("t"), F.sum(w * v * v).alias("q"))
    met = _sides(first, pairs).withColumn("pooled", (F.col("t_a") + F.col("t_b")) / (F.col("n_a") + F.col("n_b")))
    spread = F.sqrt(F.greatest((F.col("q_a") + F.col("q_b")) / (F.col("n_a") + F.col("n_b")) - F.col("pooled") ** 2, F.lit(0.0)))
    met = met.select(*PAIR, "pooled", F.when(spread > 0, spread).otherwise(F.lit(1.0)).alias("spread"))
    sides = met.withColumns({"side": F.explode(F.array(F.lit("a"), F.lit("b")))}).withColumn("dataset_id", F.when(F.col("side") == "a", F.col("id_a")).otherwise(F.col("id_b")))
    z = (v - F.col("pooled")) / F.col("spread")
    damp = F.exp(-(z * z) / 2)
    features = F.array(*[damp * f(z * float(x)) for x in freqs for f in (F.sin, F.cos)])
    key = F.to_json(F.array("id_a", "id_b", "side"))
    moments = vector_moments(hist.join(sides, "dataset_id").select(key.alias("dataset_id"), features.alias("vec"), "weight"), weight=F.col("weight"))
    part = F.from_json("dataset_id", "array<string>")
    moments = moments.select(part[0].alias("id_a"), part[1].alias("id_b"), part[2].alias("side"), "n", "mean", "cross")
    side = lambda k: moments.filter(F.col("side") == k).select(*PAIR, *[F.col(c).alias(f"{c}_{k}") for c in ("n", "mean", "cross")])

    @F.pandas_udf("double")
    def run(na: pd.Series, ma: pd.Series, ca: pd.Series, nb: pd.Series, mb: pd.Series, cb: pd.Series) -> pd.Series:
        rows = zip(na, ma, ca, nb, mb, cb, strict=True)
        return pd.Series([S.smooth_cf_moments(n1, np.asarray(m1), np.asarray(c1), n2, np.asarray(m2), np.asarray(c2)) for n1, m1, c1, n2, m2, c2 in rows], dtype="float64")

    return _named(side("a").join(side("b"), PAIR), "smooth_cf", run("n_a", "mean_a", "cross_a", "n_b", "mean_b", "cross_b"))


def mean_word_vector_distance(packed: DataFrame, pairs: DataFrame, encode) -> DataFrame:
    """Distance of the mean vectors of all fields; each dataset's mean is made once, then pairs meet."""

    @F.pandas_udf("array<double>")
    def mean(values: pd.Series) -> pd.Series:
        return pd.Series([np.mean([encode(v) for v in x], axis=0).tolist() for x in values])

    return _named(_sides(packed.select("dataset_id", mean("values").alias("m")), pairs), "mean_word_vector", F.sqrt(sq_dist(F.col("m_a"), F.col("m_b"))))


def two_sample(method: str, cv: DataFrame, pairs: DataFrame, **options) -> DataFrame:
    """One entry for the distribution tests: ``mean_sd, ks, jaccard, mmd_linear, mmd_quadratic, smooth_cf``."""
    if method == "mean_sd":
        return mean_sd_distance(cv, pairs)
    if method in ("ks", "jaccard"):
        return {"ks": ks_distance, "jaccard": jaccard_distance}[method](value_histogram(cv), pairs, **options)
    packed = pack(cv, n=options.pop("n", 1000))
    return {"mmd_linear": mmd_linear, "mmd_quadratic": mmd_quadratic, "smooth_cf": smooth_cf_distance}[method](packed, pairs, **options)


def ensemble_similarity(scores: list[DataFrame], background: list[DataFrame]) -> DataFrame:
    """Each measure turned into its percentile among background pairs, the best one taken as similarity: method
    ``ensemble`` with d = 1 - the best percentile. ``scores`` and ``background`` correspond."""
    parts = []
    for s, b in zip(scores, background, strict=True):
        # the share of background pairs that are farther apart, from one sorted union
        both = s.select(*PAIR, "d", F.lit(0).alias("bg")).unionByName(b.select(*PAIR, "d", F.lit(1).alias("bg")))
        steps = both.groupBy("d").agg(F.sum("bg").alias("n"))
        order = Window.orderBy(F.desc("d")).rowsBetween(Window.unboundedPreceding, -1)
        share = steps.select("d", (F.coalesce(F.sum("n").over(order), F.lit(0)) / F.sum("n").over(Window.partitionBy())).alias("percentile"))
        parts.append(s.select(*PAIR, "d").join(share, "d").select(*PAIR, "percentile"))
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.unionByName(p)
    return _named(whole.groupBy(*PAIR).agg((1 - F.max("percentile")).alias("x")), "ensemble", "x")
