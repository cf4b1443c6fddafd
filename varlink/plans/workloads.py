"""The experiment workloads on the given tables: train on the repository's tables, judge on held-out ones.

Every runner takes ``(spark, sf_dir, cfg)``. Training uses at most ``train_datasets`` packed datasets of at most
``values`` values each (documented bounds of the fit, the published 1,000 by default); embedding, search and measures
cover all datasets with all their values, and the two-sample tests take the same ``values`` of each. Models and prepared
tables are kept per session and configuration, so workloads that share a model train it once.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.sampling import priority, priority_bits, priority_sql
from ..functions.scores import match_probability, match_score
from ..nets.bilstm import CharBiLstm
from ..nets.mlp import SetNet
from ..nets.train import Packed, TrainConfig, train
from ..operators import alignment as A
from ..operators import baselines as B
from ..operators import columnize as C
from ..operators import measures as M
from ..operators import search as X
from ..operators import statistics as S
from ..operators import truth as G
from ..operators.embed import NumericEncoder, StringEncoder, WordEncoder, column_states, embed_datasets, of_states, query_vectors
from ..sources.scratch import cut
from ..sources.tables import load_table
from .registry import query
from .repository import FINE, LANGUAGE, STRINGS, Wide, long_of, repository_values, role_sql, sizes_of, sizes_sql, truth_of, wide_family, wide_flags


@dataclass(frozen=True)
class Workload:
    """Sizes of a run. The defaults suit one machine; the published sizes are ``paper_sizes()``."""

    values: int = 1000
    train_datasets: int = 2500
    hidden: int = 48
    width: int = 32
    word_width: int = 64
    units: int = 16
    per_class: int = 300
    queries: int = 40
    fractions: tuple[float, ...] = (0.25, 1.0)
    heldout: float = 0.3
    shift: float = 0.4
    flags: int = 0
    form: str = "bits"
    use_g: bool = True
    hold: str = ""  # tables whose name begins so are never trained on
    spare: float = 0.0  # share of the repository's tables that are not trained on
    unseen: int = 0  # regions whose customers, orders and line items are left out, and with them the even parts
    seed: int = 42
    strings: TrainConfig = field(default_factory=lambda: TrainConfig(step=2e-3, batch=8, steps_per_epoch=20, epochs=12, values=12))  # of the character network
    train: TrainConfig = field(default_factory=lambda: TrainConfig(step=2e-3, batch=32, steps_per_epoch=40, epochs=24, values=48))

    def __hash__(self) -> int:
        return hash(repr(self))


def paper_sizes() -> Workload:
    return Workload(values=1000, train_datasets=1_000_000, hidden=300, width=300, word_width=300, units=128, per_class=1000, queries=100, fractions=(1 / 16, 1 / 8, 1 / 4, 1 / 2, 1.0), strings=TrainConfig(batch=64, steps_per_epoch=31, epochs=50, values=1000), train=TrainConfig(batch=64, steps_per_epoch=31, epochs=50, values=1000))


_KEPT: dict = {}
_PACKED: dict = {}


def _keep(key: tuple, make):
    """What was made before for this key in this application."""
    if key not in _KEPT:
        _KEPT[key] = make()
    return _KEPT[key]


def _app(spark: SparkSession) -> str:
    return spark.sparkContext.applicationId


# ------------------------------------------------------------------ preparation

_FAMILIES = {"numeric": FINE, "language": LANGUAGE, "string": STRINGS}


def value_column(kind: str) -> str:
    return "value_num" if kind == "numeric" else "value_str"


def unseen_rows(spark: SparkSession, sf_dir: str, regions: int) -> DataFrame:
    """``family, key``: rows that the tables of :func:`state_tables` are made of, by the first part of their row key."""
    t = lambda n, *c: load_table(spark, sf_dir, n, list(c))
    home = t("nation", "n_nationkey", "n_regionkey").filter(F.col("n_regionkey") < regions)
    customers = t("customer", "c_custkey", "c_nationkey").join(F.broadcast(home), F.col("c_nationkey") == F.col("n_nationkey"), "left_semi")
    orders = t("orders", "o_orderkey", "o_custkey").join(customers, F.col("o_custkey") == F.col("c_custkey"), "left_semi")
    key = lambda df, name, *families: df.select(F.explode(F.array(*[F.lit(f) for f in families])).alias("family"), F.col(name).cast("string").alias("key"))
    parts = t("part", "p_partkey").filter("p_partkey % 2 = 0")
    return key(customers, "c_custkey", "customer").unionByName(key(orders, "o_orderkey", "orders", "lineitem")).unionByName(key(parts, "p_partkey", "part"))


#: Families of which :func:`unseen_rows` names rows.
UNSEEN = ("customer", "orders", "lineitem", "part")


def prepare_wide(spark: SparkSession, sf_dir: str, kind: str, cfg: Workload) -> list[Wide]:
    """The rows that all values come from, written once in wide form."""

    def make() -> list[Wide]:
        if cfg.flags:  # the other datasets are those of the repository without flags
            return [*prepare_wide(spark, sf_dir, kind, replace(cfg, flags=0)), wide_flags(spark, sf_dir, cfg.flags, words=kind != "numeric")]
        gone = cut(unseen_rows(spark, sf_dir, cfg.unseen), "workload-unseen") if cfg.unseen else None
        share = cfg.shift if kind == "numeric" else None
        return [wide_family(spark, sf_dir, f, share, gone if f.table in UNSEEN else None) for f in _FAMILIES[kind]]

    return _keep((_app(spark), sf_dir, kind, "wide", cfg.shift, cfg.flags, cfg.unseen), make)


def prepare(spark: SparkSession, sf_dir: str, kind: str, cfg: Workload) -> tuple[DataFrame, DataFrame]:
    """``cv`` (all values of all datasets), unpivoted in each pass over the written rows, and ``truth`` with roles, a
    written table."""

    def make() -> tuple[DataFrame, DataFrame]:
        wides = prepare_wide(spark, sf_dir, kind, cfg)
        cv, t = long_of(wides), cut(sizes_of(wides), "workload-sizes")
        roles = G.assign_roles(t, cfg.heldout, cfg.seed)
        if cfg.hold:
            roles = roles.withColumn("role", F.when(F.col("table_id").startswith(cfg.hold), "T").otherwise(F.col("role")))
        return cv, cut(t.join(roles, "table_id"), "workload-truth")

    return _keep((_app(spark), sf_dir, kind, cfg.shift, cfg.flags, cfg.heldout, cfg.hold, cfg.unseen, cfg.seed), make)


def encoder_of(kind: str, cfg: Workload):
    return {"numeric": lambda: NumericEncoder(cfg.form), "language": lambda: WordEncoder(None, cfg.word_width), "string": StringEncoder}[kind]()


def network_of(kind: str, cfg: Workload):
    if kind == "string":
        return CharBiLstm(cfg.units, cfg.width, 2, None, 16, cfg.use_g).init(cfg.seed)
    n_in = encoder_of(kind, cfg).width
    return SetNet(n_in, cfg.hidden, cfg.width, 3, cfg.use_g).init(cfg.seed)


def is_spare(cfg: Workload):
    """Whether a repository table is left out of training."""
    return priority(cfg.seed + 9, F.col("table_id")) < cfg.spare


def packed_values(spark: SparkSession, sf_dir: str, kind: str, cfg: Workload) -> DataFrame:
    """The sample of ``values`` values of every dataset, gathered in one pass for the fit and the two-sample tests."""

    def make() -> DataFrame:
        cv, truth = prepare(spark, sf_dir, kind, cfg)
        return cut(B.pack(cv, value_column(kind), cfg.values, sizes=truth), "workload-packed")

    return _keep((_app(spark), sf_dir, kind, "packed", cfg.values, cfg.shift, cfg.flags, cfg.heldout, cfg.hold, cfg.unseen, cfg.seed), make)


def packed_for_training(spark: SparkSession, sf_dir: str, kind: str, cfg: Workload) -> Packed:
    """The training role's datasets as arrays on the driver: at most ``train_datasets``, chosen by a seeded hash."""
    encode = encoder_of(kind, cfg)

    def make() -> Packed:
        _, truth = prepare(spark, sf_dir, kind, cfg)
        chosen = truth.filter("role = 'R'").filter(~is_spare(cfg)).orderBy(priority_bits(cfg.seed, F.col("dataset_id")), "dataset_id").limit(cfg.train_datasets)
        rows = packed_values(spark, sf_dir, kind, cfg).join(chosen, "dataset_id").orderBy("dataset_id").collect()
        inputs = [np.array(r["values"]) if kind == "numeric" else r["values"] if kind == "string" else encode(r["values"]).astype(np.float32) for r in rows]
        return Packed([r["dataset_id"] for r in rows], inputs, [r["variable"] for r in rows], [r["table_id"] for r in rows])

    # variants of one workload that differ in network or encoding of numbers have the same data; only the last is held
    key = (_app(spark), sf_dir, kind, cfg.values, cfg.train_datasets, cfg.word_width, cfg.spare, cfg.shift, cfg.flags, cfg.heldout, cfg.hold, cfg.unseen, cfg.seed)
    if _PACKED.get("key") != key:
        _PACKED.clear()
        _PACKED.update(key=key, packed=make())
    data = _PACKED["packed"]
    return data if kind != "numeric" else replace(data, inputs=[encode(x).astype(np.float32) for x in data.inputs])


def model_of(spark: SparkSession, sf_dir: str, kind: str, cfg: Workload):
    """The network trained for this kind, with its history."""

    def make():
        net = network_of(kind, cfg)
        return net, train(net, packed_for_training(spark, sf_dir, kind, cfg), cfg.strings if kind == "string" else cfg.train)

    return _keep((_app(spark), sf_dir, kind, "model", cfg), make)


def vectors_of(cv: DataFrame, kind: str, net, cfg: Workload) -> DataFrame:
    return vectors_of_histogram(histogram_of(cv, kind), kind, net, cfg)


def histogram_of(cv: DataFrame, kind: str) -> DataFrame:
    value = value_column(kind)
    return C.value_histogram(cv.filter(F.col(value).isNotNull()), value=value)


def vectors_of_histogram(hist: DataFrame, kind: str, net, cfg: Workload) -> DataFrame:
    return cut(embed_datasets(hist, net, encoder_of(kind, cfg), kind), "workload-vectors")


def vectors_of_wide(wides: list[Wide], kind: str, net, cfg: Workload) -> DataFrame:
    """Vectors of all datasets of wide rows, from sums over whole rows."""
    states = None
    for w in wides:
        one = column_states(w.df, list(w.columns), net, encoder_of(kind, cfg))
        states = one if states is None else states.unionByName(one)
    return cut(of_states(states, net, kind), "workload-vectors")


def score_pairs(vectors: DataFrame, pairs: DataFrame, method: str = "embedding", with_g: bool = True) -> DataFrame:
    side = lambda k: vectors.select(F.col("dataset_id").alias(f"id_{k}"), F.col("h").alias(f"h_{k}"), (F.col("g") if with_g else F.lit(0.0)).alias(f"g_{k}"))
    return pairs.select("id_a", "id_b").join(side("a"), "id_a").join(side("b"), "id_b").select("id_a", "id_b", F.lit(method).alias("method"), match_score(F.col("h_a"), F.col("h_b"), F.col("g_a"), F.col("g_b")).alias("d"))


def baseline_scores(cv: DataFrame, pairs: DataFrame, kind: str, cfg: Workload) -> DataFrame:
    return baselines_of(cut(B.pack(cv, value_column(kind), cfg.values), "workload-packed"), pairs, kind, cfg)


def baselines_of(packed: DataFrame, pairs: DataFrame, kind: str, cfg: Workload) -> DataFrame:
    """All baselines of the pairs on :func:`B.pack`'s samples."""
    if kind == "numeric":
        parts = [B.mean_sd_packed(packed, pairs), B.ks_packed(packed, pairs), B.mmd_linear(packed, pairs), B.smooth_cf_distance(packed, pairs)]
    else:
        moments = cut(B.text_moments(packed, WordEncoder(None, cfg.word_width).one), "workload-moments")
        # values meet once: a pair's two samples of long texts would be sent for every pair
        texts = cut(packed.select("dataset_id", F.explode("values").alias("value_str")).groupBy("dataset_id", "value_str").agg(F.count("*").alias("weight")), "workload-texts")
        parts = [B.jaccard_distance(texts, pairs, "value_str"), B.mean_word_vector_of_moments(moments, pairs), B.hotelling_of_moments(moments, pairs)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def eval_pairs(spark, sf_dir, kind, setting, cfg) -> tuple[DataFrame, DataFrame]:
    """Values and balanced labelled pairs of held-out datasets. ``split``: halves of one dataset against datasets of
    other variables; ``diff``: different tables' datasets of one variable against the same."""
    cv, truth = prepare(spark, sf_dir, kind, cfg)
    t = truth.filter("role = 'T'")
    own = cv.join(t.select("dataset_id"), "dataset_id", "left_semi")
    pairs = G.balanced_pairs(t.select("dataset_id", "variable", "table_id"), cfg.per_class, cfg.seed)
    if setting == "diff":
        return own, pairs
    halves = C.split_halves(own).withColumn("dataset_id", F.concat_ws("~", "dataset_id", F.col("half").cast("string"))).drop("half")
    unmatched = pairs.filter("y = 0").select(F.concat("id_a", F.lit("~0")).alias("id_a"), F.concat("id_b", F.lit("~1")).alias("id_b"), "y")
    both = t.filter("n_values >= 2").orderBy(priority_bits(cfg.seed, F.col("dataset_id")), "dataset_id").limit(cfg.per_class)
    matched = both.select(F.concat("dataset_id", F.lit("~0")).alias("id_a"), F.concat("dataset_id", F.lit("~1")).alias("id_b"), F.lit(1).alias("y"))
    return halves, matched.unionByName(unmatched)


# ------------------------------------------------------------------ classification


def run_pair_classification(spark, sf_dir, kind: str = "numeric", setting: str = "diff", cfg: Workload = Workload()) -> DataFrame:
    """``setting, kind, fraction, method, auc``."""
    net, _ = model_of(spark, sf_dir, kind, cfg)
    values, pairs = eval_pairs(spark, sf_dir, kind, setting, cfg)
    pairs, out = cut(pairs, "workload-pairs"), None
    for f in cfg.fractions:
        part = C.downsample_fraction(values, f, cfg.seed + 1) if f < 1 else values
        scored = score_pairs(vectors_of(part, kind, net, cfg), pairs).unionByName(baseline_scores(part, pairs, kind, cfg))
        auc = M.roc_auc(scored.join(pairs, ["id_a", "id_b"]), ["method"])
        one = auc.select(F.lit(setting).alias("setting"), F.lit(kind).alias("kind"), F.lit(f).alias("fraction"), "method", F.round("auc", 4).alias("auc"))
        out = one if out is None else out.unionByName(one)
    return out


def run_input_ablation(spark, sf_dir, cfg: Workload = Workload(), epochs: int = 8) -> DataFrame:
    """Inputs (raw, exponent and mantissa, bits) and bits without adjustment, on a repository rich in look-alikes and on
    one without: ``flags, variant, setting, auc``. Every variant trains ``epochs`` epochs; each result is one number and is
    computed at once, on pairs and histograms of values that are written once for all variants."""
    rows = []
    for flags in (0, 12):
        base = replace(cfg, flags=flags, train=replace(cfg.train, epochs=epochs))
        sides = {}
        for setting in ("split", "diff"):
            values, pairs = eval_pairs(spark, sf_dir, "numeric", setting, base)
            pairs = cut(pairs, "workload-pairs")
            used = pairs.select(F.explode(F.array("id_a", "id_b")).alias("dataset_id")).distinct()
            sides[setting] = cut(histogram_of(values.join(used, "dataset_id", "left_semi"), "numeric"), "workload-side"), pairs
        for variant, change in (("raw", {"form": "raw"}), ("exp_mantissa", {"form": "exp_mantissa"}), ("bits", {}), ("bits_no_g", {"use_g": False})):
            c = replace(base, **change)
            net, _ = model_of(spark, sf_dir, "numeric", c)
            for setting, (hist, pairs) in sides.items():
                auc = M.roc_auc(score_pairs(vectors_of_histogram(hist, "numeric", net, c), pairs).join(pairs, ["id_a", "id_b"])).first()["auc"]
                rows.append((flags, variant, setting, None if auc is None else round(float(auc), 4)))
    return spark.createDataFrame(rows, "flags int, variant string, setting string, auc double")


# ------------------------------------------------------------------ retrieval


def retrieval_sides(spark, sf_dir, kind, setting, cfg) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Values of the repository and of the queries, and ``query_id, dataset_id`` of the true matches.

    ``split``: half of the rows of a repository dataset is the query and the other half its only match; ``diff``: queries
    are held-out datasets whose variable the repository has.
    """
    cv, truth = prepare(spark, sf_dir, kind, cfg)
    r = truth.filter("role = 'R'")
    pick = lambda t: t.orderBy(priority_bits(cfg.seed + 2, F.col("dataset_id")), "dataset_id").limit(cfg.queries)
    if setting == "split":
        ids = pick(r.filter("n_values >= 4")).select("dataset_id")
        ids = cut(ids, "workload-ids")
        carved = G.carve_halves(cv.join(r.select("dataset_id"), "dataset_id", "left_semi"), ids, cfg.seed + 3)
        carved = cut(carved, "workload-carved")
        queries = carved.filter("role = 'S'")
        return carved.filter("role = 'R'").drop("role", "source_id"), queries.drop("role", "source_id"), queries.select(F.col("dataset_id").alias("query_id"), F.col("source_id").alias("dataset_id")).distinct()
    ids = cut(pick(truth.filter("role = 'T'").join(r.select("variable").distinct(), "variable", "left_semi")), "workload-ids")
    true = ids.select(F.col("dataset_id").alias("query_id"), "variable").join(r.select("dataset_id", "variable"), "variable").select("query_id", "dataset_id")
    return cv.join(r.select("dataset_id"), "dataset_id", "left_semi"), cv.join(F.broadcast(ids.select("dataset_id")), "dataset_id"), true


def _baseline_ranks(repo: DataFrame, queries: DataFrame, kind: str, cfg: Workload, k: int | None) -> DataFrame:
    """Scores of every query with every dataset by each baseline: exhaustive, as these methods have no index."""
    pairs = queries.select(F.col("dataset_id").alias("id_a")).distinct().crossJoin(repo.select(F.col("dataset_id").alias("id_b")).distinct())
    return _ranked(baseline_scores(repo.unionByName(queries), pairs.repartition(spark_slots(repo)), kind, cfg), k)


def _ranked(scores: DataFrame, k: int | None) -> DataFrame:
    s = scores.select("method", F.col("id_a").alias("query_id"), F.col("id_b").alias("dataset_id"), "d")
    if k is None:
        return s
    order = Window.partitionBy("method", "query_id").orderBy("d", "dataset_id")
    return s.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def spark_slots(df: DataFrame) -> int:
    return max(8, df.sparkSession.sparkContext.defaultParallelism)


def run_retrieval(spark, sf_dir, kind: str = "numeric", setting: str = "diff", cfg: Workload = Workload()) -> DataFrame:
    """``setting, kind, method, k, matches, hit_rate, queries``."""
    net, _ = model_of(spark, sf_dir, kind, cfg)
    repo, queries, true = retrieval_sides(spark, sf_dir, kind, setting, cfg)
    found = X.top_k_exact(query_vectors(vectors_of(queries, kind, net, cfg)), vectors_of(repo, kind, net, cfg), 10).withColumn("method", F.lit("embedding"))
    ranked = found.select("method", "query_id", "dataset_id", "d", "rank").unionByName(_baseline_ranks(repo, queries, kind, cfg, 10))
    m = M.matches_at_k(ranked, true, (1, 5, 10), ["method"])
    return m.select(F.lit(setting).alias("setting"), F.lit(kind).alias("kind"), "method", "k", F.round("matches", 4).alias("matches"), F.round("hit_rate", 4).alias("hit_rate"), "queries")


def run_calibrated_recall(spark, sf_dir, kind: str = "numeric", cfg: Workload = Workload(), absent: tuple[str, ...] = ("retailprice", "tax", "totalprice")) -> DataFrame:
    """Variables of ``absent`` are taken out of the repository; their datasets are the queries without a match."""
    net, _ = model_of(spark, sf_dir, kind, cfg)
    _, truth = prepare(spark, sf_dir, kind, cfg)
    r = truth.filter("role = 'R'").filter(~F.col("variable").isin(*absent))
    pick = lambda t: cut(t.orderBy(priority_bits(cfg.seed + 4, F.col("dataset_id")), "dataset_id").limit(cfg.queries).select("dataset_id", "variable"), "workload-ids")
    none, some = pick(truth.filter(F.col("variable").isin(*absent))), pick(truth.filter("role = 'T'").join(r.select("variable").distinct(), "variable", "left_semi"))
    ids = none.union(some).select(F.col("dataset_id").alias("id_a"))
    pairs = cut(ids.crossJoin(r.select(F.col("dataset_id").alias("id_b"))).repartition(spark_slots(truth)), "workload-pairs")
    used = pairs.select(F.explode(F.array("id_a", "id_b")).alias("dataset_id")).distinct()
    base = _ranked(baselines_of(packed_values(spark, sf_dir, kind, cfg).join(used, "dataset_id", "left_semi"), pairs, kind, cfg), None)
    emb = score_pairs(vectors_of_wide(prepare_wide(spark, sf_dir, kind, cfg), kind, net, cfg), pairs).select("method", F.col("id_a").alias("query_id"), F.col("id_b").alias("dataset_id"), "d")
    s = emb.unionByName(base).withColumn("p", -F.col("d"))  # any monotone map of d will do
    true = some.select(F.col("dataset_id").alias("query_id"), "variable").join(r.select("dataset_id", "variable"), "variable")
    out = M.calibrated_recall(s.join(true, ["query_id", "dataset_id"]), s.join(F.broadcast(none.select(F.col("dataset_id").alias("query_id"))), "query_id"), ["method"])
    return out.select(F.lit(kind).alias("kind"), "method", F.round("recall", 4).alias("recall"), "queries")


# ------------------------------------------------------------------ inspection


def run_embedding_map(spark, sf_dir, cfg: Workload = Workload(), points: int = 400) -> DataFrame:
    """``dataset_id, variable, x, y, purity`` of held-out numeric datasets (at most ``points``, drawn by hash)."""
    net, _ = model_of(spark, sf_dir, "numeric", cfg)
    cv, truth = prepare(spark, sf_dir, "numeric", cfg)
    t = truth.filter("role = 'T'").orderBy(priority_bits(cfg.seed, F.col("dataset_id")), "dataset_id").limit(points)
    rows = vectors_of(cv.join(F.broadcast(t.select("dataset_id")), "dataset_id"), "numeric", net, cfg).join(t, "dataset_id").orderBy("dataset_id").collect()
    if len(rows) < 3:
        return spark.createDataFrame([], "dataset_id string, variable string, x double, y double, purity double")
    h = np.array([r["h"] for r in rows])
    y = S.tsne(S.pca(h, min(20, *h.shape)), perplexity=15, steps=200)
    pts = spark.createDataFrame([(r["dataset_id"], r["variable"], float(a), float(b)) for r, (a, b) in zip(rows, y, strict=True)], "dataset_id string, variable string, x double, y double")
    return pts.join(M.neighbour_purity(pts), "dataset_id")


def run_lookalike_flags(spark, sf_dir, cfg: Workload = Workload(), flags: int = 12, kind: str = "numeric") -> DataFrame:
    """Adjustments and mistaken matches where unrelated flags (0 and 1, or the words true and false) abound.

    ``method, use_g, group, datasets, mean_g, mean_p_unmatched, mistaken`` for flags and others: ``mistaken`` is the share
    of unmatched pairs that are at most as far apart as the median matched pair of other variables, whatever the method's
    scale. The alternatives have neither adjustment nor probability.
    """
    out, group = None, F.when(F.col("variable").startswith("flag"), "flags").otherwise("others")
    for use_g in (True, False):
        c = replace(cfg, flags=flags, use_g=use_g, train=replace(cfg.train, epochs=12))
        net, _ = model_of(spark, sf_dir, kind, c)
        _, truth = prepare(spark, sf_dir, kind, c)
        if use_g:
            pairs = None
            for name, cond in (("flags", "variable LIKE 'flag%'"), ("others", "variable NOT LIKE 'flag%'")):
                one = G.balanced_pairs(truth.filter(cond).select("dataset_id", "variable", "table_id"), c.per_class, 5).withColumn("group", F.lit(name))
                pairs = one if pairs is None else pairs.unionByName(one)
            pairs = cut(pairs.filter("y = 0 OR group = 'others'"), "workload-pairs")
            used = pairs.select(F.explode(F.array("id_a", "id_b")).alias("dataset_id")).distinct()
            scored = baselines_of(packed_values(spark, sf_dir, kind, c).join(used, "dataset_id", "left_semi"), pairs, kind, c).withColumn("use_g", F.lit(None).cast("boolean"))
        v = vectors_of_wide(prepare_wide(spark, sf_dir, kind, c), kind, net, c)
        scored = scored.unionByName(score_pairs(v, pairs).withColumn("use_g", F.lit(use_g)))
        g = v.join(truth.select("dataset_id", group.alias("group")), "dataset_id").groupBy("group").agg(F.count("*").alias("datasets"), F.avg("g").alias("mean_g")).withColumn("use_g", F.lit(use_g))
        out = g if out is None else out.unionByName(g)
    scored = cut(scored.join(pairs, ["id_a", "id_b"]), "workload-scores")
    median = scored.filter("y = 1").groupBy("method", "use_g").agg(F.expr("percentile(d, 0.5)").alias("median")).withColumnsRenamed({"method": "m", "use_g": "u"})
    near = scored.filter("y = 0").join(median, (F.col("method") == F.col("m")) & F.col("use_g").eqNullSafe(F.col("u")))
    p = near.groupBy("method", "use_g", "group").agg(F.avg(match_probability(F.col("d"))).alias("mean_p"), F.avg((F.col("d") <= F.col("median")).cast("double")).alias("mistaken"))
    both = p.join(out.withColumnsRenamed({"use_g": "u", "group": "of"}), F.col("use_g").eqNullSafe(F.col("u")) & (F.col("group") == F.col("of")), "left")
    return both.select("method", "use_g", "group", "datasets", F.round("mean_g", 4).alias("mean_g"), F.when(F.col("use_g").isNotNull(), F.round("mean_p", 4)).alias("mean_p_unmatched"), F.round("mistaken", 4).alias("mistaken"))


def run_example_lookup(spark, sf_dir, cfg: Workload = Workload()) -> DataFrame:
    """The supplier balances look for their like: ``query_id, rank, dataset_id, table_id, d, p``. No supplier table is
    trained on."""
    cfg = replace(cfg, hold="supplier:")
    net, _ = model_of(spark, sf_dir, "numeric", cfg)
    cv, truth = prepare(spark, sf_dir, "numeric", cfg)
    q = cv.filter("variable = 'acctbal' AND table_id LIKE 'supplier:%'")
    r = cv.filter("table_id NOT LIKE 'supplier:%'")
    best = X.top_k_exact(query_vectors(vectors_of(q, "numeric", net, cfg)), vectors_of(r, "numeric", net, cfg), 3)
    return best.join(truth.select("dataset_id", "table_id"), "dataset_id").select("query_id", "rank", "dataset_id", "table_id", F.round("d", 4).alias("d"), F.round(match_probability(F.col("d")), 4).alias("p"))


# ------------------------------------------------------------------ schemas and unions


def state_tables(spark, sf_dir) -> DataFrame:
    """Wide rows of line items with their order, customer, part and region: one schema, one table per region."""
    t = lambda n, *c: load_table(spark, sf_dir, n, list(c))
    return (
        t("lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus")
        .join(t("orders", "o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderpriority"), F.col("l_orderkey") == F.col("o_orderkey"))
        .join(t("customer", "c_custkey", "c_nationkey", "c_acctbal", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey"))
        .join(t("part", "p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice"), F.col("l_partkey") == F.col("p_partkey"))
        .join(F.broadcast(t("nation", "n_nationkey", "n_regionkey")), F.col("c_nationkey") == F.col("n_nationkey"))
        .join(F.broadcast(t("region", "r_regionkey", "r_name")), F.col("n_regionkey") == F.col("r_regionkey"))
    )


SCHEMA = ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_partkey", "l_suppkey", "o_totalprice", "o_custkey", "c_acctbal", "p_size", "p_retailprice", "l_linenumber", "l_returnflag", "l_linestatus", "o_orderstatus", "o_orderpriority", "c_mktsegment", "p_name", "p_brand", "p_type")


def run_schema_matching(spark, sf_dir, cfg: Workload = Workload(), regions: int = 3) -> DataFrame:
    """Columns of three regions' tables aligned with names hidden: ``pair, method, precision, aligned``.

    The networks are trained on rows that none of these tables has: customers of other regions, their orders and items,
    and the odd parts, while the tables join the even ones."""
    cfg = replace(cfg, unseen=regions)
    wide = state_tables(spark, sf_dir).filter((F.col("r_regionkey") < regions) & (F.col("p_partkey") % 2 == 0))
    wide = cut(wide.select(F.col("r_name").alias("table_id"), *SCHEMA), "workload-schema")
    numbers = [c for c in SCHEMA if C.as_numeric(wide, c) is not None]
    of = {"numeric": Wide(wide, tuple(numbers), ()), "language": Wide(wide, tuple(c for c in SCHEMA if c not in numbers), ())}
    cv = C.columnize(wide, F.col("table_id"), list(SCHEMA))
    text = F.coalesce(F.col("value_str"), F.col("value_num").cast("string"))
    nets = {k: model_of(spark, sf_dir, k, cfg)[0] for k in ("numeric", "language")}
    vec = None
    for kind, w in of.items():
        one = vectors_of_wide([w], kind, nets[kind], cfg)
        vec = one if vec is None else vec.unionByName(one)
    # each distinct value of a dataset, in its own type, is made a text once
    hist = cut(cv.groupBy("dataset_id", "table_id", "column", "value_num", "value_str").agg(F.count("*").alias("weight")).withColumn("value_str", text), "workload-histograms")
    names = hist.select("dataset_id", "table_id", "column", F.when(F.col("value_num").isNotNull(), "numeric").otherwise("language").alias("kind")).distinct()
    side = lambda k: names.select(F.col("dataset_id").alias(f"id_{k}"), F.col("table_id").alias(f"t_{k}"), F.col("column").alias(f"c_{k}"), "kind")
    pairs = side("a").join(side("b"), "kind").filter("t_a < t_b").withColumn("pair", F.concat_ws("~", "t_a", "t_b"))
    pairs = cut(pairs, "workload-pairs")
    scored = score_pairs(vec, pairs).unionByName(B.likelihood_similarity(hist, pairs, "value_str")).unionByName(B.probability_vector_distance(hist, pairs, "value_str"))
    # exp(-d) is a probability for the embedder, and a monotone similarity for the others
    m = scored.join(pairs, ["id_a", "id_b"]).select(F.concat_ws("@", "method", "pair").alias("group_id"), F.col("id_a").alias("col_a"), F.col("id_b").alias("col_b"), F.exp(-F.col("d")).alias("p"))
    aligned = cut(A.align_schemas(m, "two_opt"), "workload-aligned")
    right = pairs.filter("c_a = c_b").select(F.col("id_a").alias("col_a"), F.col("id_b").alias("col_b"))
    out = M.alignment_precision(aligned, right.join(aligned.select("group_id", "col_a", "col_b"), ["col_a", "col_b"]), ["group_id"])
    return out.select(F.split("group_id", "@")[1].alias("pair"), F.split("group_id", "@")[0].alias("method"), F.round("precision", 4).alias("precision"), "aligned")


def run_union_search(spark, sf_dir, cfg: Workload = Workload(), ks: tuple[int, ...] = (1, 5, 10), n_queries: int = 12, background_share: float = 0.15) -> DataFrame:
    """Held-out tables (``n_queries`` of them, by hash) look for tables of their family: ``method, k, precision, recall``.

    The network is trained on half of the repository's tables, and the other half is searched. Tables are ranked by their
    best c-alignment against the alignments of random tables."""
    cfg = replace(cfg, spare=0.5)
    net, _ = model_of(spark, sf_dir, "numeric", cfg)
    cv, truth = prepare(spark, sf_dir, "numeric", cfg)
    # a seeded quarter of the columns of every table is dropped, so that tables are partly unionable
    part = truth.filter(priority(cfg.seed + 6, F.col("dataset_id")) >= 0.25).filter((F.col("role") == "T") | is_spare(cfg))
    q = part.filter("role = 'T'").select("table_id").distinct().orderBy(priority_bits(cfg.seed + 7, F.col("table_id")), "table_id").limit(n_queries)
    q = cut(q, "workload-queries")
    v = vectors_of(cv.join(part.select("dataset_id"), "dataset_id", "left_semi"), "numeric", net, cfg).join(part.select("dataset_id", "table_id", "role"), "dataset_id")
    v = cut(v, "workload-union")
    queries, repo = v.join(F.broadcast(q), "table_id"), v.filter("role = 'R'")
    near = X.top_k_exact(query_vectors(queries.drop("table_id", "role")), repo, 50)
    tables = near.join(v.select(F.col("dataset_id").alias("query_id"), F.col("table_id").alias("query_table")), "query_id").join(repo.select("dataset_id", "table_id"), "dataset_id")
    found = tables.select("query_table", "table_id").distinct()
    every = q.select(F.col("table_id").alias("query_table")).crossJoin(repo.select("table_id").distinct())
    # the background of both methods: query tables with tables drawn by a seeded hash
    drawn = every.filter(priority(cfg.seed + 8, F.col("query_table"), F.col("table_id")) < background_share)
    columns = lambda pairs: pairs.join(v.select(F.col("table_id").alias("query_table"), F.col("dataset_id").alias("id_a")), "query_table").join(v.select("table_id", F.col("dataset_id").alias("id_b")), "table_id")
    cols = cut(columns(every), "workload-columns")
    ids = cols.select("id_a", "id_b").distinct()
    emb = score_pairs(v, ids)
    packed = cut(B.pack(cv.join(part.select("dataset_id"), "dataset_id", "left_semi"), n=cfg.values), "workload-packed")
    some = ids.repartition(spark_slots(cv))
    base = [cut(f(packed, some), "workload-scores") for f in (B.jaccard_packed, B.ks_packed)]
    random_ids = cols.join(drawn, ["query_table", "table_id"], "left_semi").select("id_a", "id_b").distinct()
    ens = B.ensemble_similarity(base, [b.join(random_ids, ["id_a", "id_b"], "left_semi") for b in base])
    out, family = None, lambda c: F.split(c, ":")[0]
    want = q.select(F.col("table_id").alias("query_id")).crossJoin(part.filter("role = 'R'").select(F.col("table_id").alias("dataset_id")).distinct()).filter(family(F.col("query_id")) == family(F.col("dataset_id")))
    # the embedder ranks the tables that its search finds, the ensemble, which has no index, all of them
    for name, s, tables in (("embedding", emb, found), ("ensemble", ens, every)):
        p = cut(cols.join(s, ["id_a", "id_b"]).select("query_table", "table_id", F.col("id_a").alias("col_a"), F.col("id_b").alias("col_b"), F.exp(-F.col("d")).alias("p")), "workload-scored")
        of = lambda pairs, p=p: p.join(pairs, ["query_table", "table_id"], "left_semi")
        r = cut(A.union_search(of(tables), max(ks), background=of(drawn)), "workload-ranked").select(F.col("query_table").alias("query_id"), F.col("table_id").alias("dataset_id"), "rank")
        one = M.precision_recall_at_k(r, want, ks).select(F.lit(name).alias("method"), "k", F.round("precision", 4).alias("precision"), F.round("recall", 4).alias("recall"))
        out = one if out is None else out.unionByName(one)
    return out


# ------------------------------------------------------------------ repository, sampling, objectives, cost


def run_repository_summary(spark, sf_dir, cfg: Workload = Workload()) -> DataFrame:
    """Tables, datasets, sizes and matches per kind and role, over whole datasets."""
    out = None
    for kind, families in _FAMILIES.items():
        t = truth_of(repository_values(spark, sf_dir, families))
        catalog = t.join(G.assign_roles(t, cfg.heldout, cfg.seed), "table_id").withColumn("kind", F.lit(kind))
        # matches are counted from the sizes of the variables' groups; no pair is made
        n = catalog.groupBy("kind", "role", "variable").agg(F.count("*").alias("n")).groupBy("kind", "role").agg(F.sum(F.col("n") * (F.col("n") - 1) / 2).cast("long").alias("matches"))
        one = G.repository_summary(catalog).join(n, ["kind", "role"])
        out = one if out is None else out.unionByName(one)
    return out.withColumns({"mean_n": F.round("mean_n", 2), "sd_n": F.round("sd_n", 2)})


def run_deviation(spark, sf_dir, cfg: Workload = Workload()) -> DataFrame:
    """Sampled against whole distances of the label bags of unit vectors: ``n, eps, rate, bound, draws``."""
    e = load_table(spark, sf_dir, "embeddings").select(F.col("label").cast("string").alias("dataset_id"), F.col("vec_id").cast("string").alias("row_key"), F.col("embedding").cast("array<double>").alias("vec"))
    ids = e.select("dataset_id").distinct()
    pairs, out = ids.withColumnRenamed("dataset_id", "id_a").join(ids.withColumnRenamed("dataset_id", "id_b"), F.col("id_a") < F.col("id_b")), None
    for n in (10, 20, 40):
        one = M.empirical_deviation(e, pairs, n, 0.2, 40)
        out = one if out is None else out.unionByName(one)
    return out


def run_objectives(spark, sf_dir, cfg: Workload = Workload(), seeds: tuple[int, ...] = (1, 2)) -> DataFrame:
    """Other losses and samplers: ``objective, sampler, auc, auc_sd, seconds, gradient_sd``."""
    rows = []
    values, pairs = eval_pairs(spark, sf_dir, "numeric", "diff", cfg)
    pairs = cut(pairs, "workload-pairs")
    data = packed_for_training(spark, sf_dir, "numeric", cfg)
    for objective, sampler in (("xent", "uniform"), ("triplet", "semihard"), ("contrastive", "uniform"), ("margin", "distance_weighted"), ("xent", "semihard")):
        aucs, seconds, noise = [], 0.0, []
        for seed in seeds:
            net = network_of("numeric", replace(cfg, seed=seed))
            h = train(net, data, replace(cfg.train, objective=objective, sampler=sampler, seed=seed, epochs=6))
            seconds += h.seconds
            noise.append(np.std(h.gradient_norm) / (np.mean(h.gradient_norm) or 1))
            aucs.append(M.roc_auc(score_pairs(vectors_of(values, "numeric", net, cfg), pairs).join(pairs, ["id_a", "id_b"])).first()["auc"] or 0.5)
        rows.append((objective, sampler, round(float(np.mean(aucs)), 4), round(float(np.std(aucs)), 4), round(seconds / len(seeds), 2), round(float(np.mean(noise)), 4)))
    return spark.createDataFrame(rows, "objective string, sampler string, auc double, auc_sd double, seconds double, gradient_sd double")


def run_search_cost(spark, sf_dir, cfg: Workload = Workload(), k: int = 10) -> DataFrame:
    """Exhaustive, hashed and cell search on the given vectors, every vector whose id is divisible by 20 against all:
    ``index, size, recall, rows_scored, seconds``. ``size`` is the number of hash tables or of probed cells; the last row of
    the cells is the number that search chooses by itself."""
    e = load_table(spark, sf_dir, "embeddings", ["vec_id", "embedding"]).select(F.col("vec_id").cast("string").alias("dataset_id"), F.col("embedding").cast("array<double>").alias("s"))
    r = X.spread(e)
    q = cut(r.filter(F.col("dataset_id").cast("long") % 20 == 0).withColumnRenamed("dataset_id", "query_id"), "workload-queries")
    rows, n, m = [], r.count(), q.count()

    def timed(found: DataFrame) -> tuple[DataFrame, float]:
        began = time.time()
        return cut(found, "workload-found"), round(time.time() - began, 3)

    exact, took = timed(X.top_k_exact(q, r, k))
    rows.append(("exact", 0, 1.0, n * m, took))
    recall = lambda found: round(M.index_recall(found, exact, k).first()["recall"], 4)
    for tables in (1, 4, 10):
        found, took = timed(X.top_k_lsh(q, r, k, bucket_length=1.0, tables=tables))
        rows.append(("hashing", tables, recall(found), X.count_shared(*X.lsh_keys(q, r, 1.0, tables)), took))
    centroids = X.fit_cells(r)
    indexed = cut(X.assign_cells(r, centroids), "workload-cells")
    sizes = indexed.groupBy("cell").agg(F.count("*").alias("held"))
    for probes in (1, 4, 8, X.choose_probes(indexed, centroids, k)):
        found, took = timed(X.top_k_cells(q, indexed, centroids, k, probes))
        scored = X.assign_cells(q, centroids, probes).join(sizes, "cell").agg(F.sum("held").alias("n")).first()["n"]
        rows.append(("cells", probes, recall(found), scored, took))
    return spark.createDataFrame(rows, "index string, size int, recall double, rows_scored long, seconds double")


def run_scarcity(spark, sf_dir, cfg: Workload = Workload()) -> DataFrame:
    """With and without split augmentation, as annotated matches get scarce: ``augmentation, match_share, auc``."""
    values, pairs = eval_pairs(spark, sf_dir, "numeric", "diff", cfg)
    pairs, data, rows = cut(pairs, "workload-pairs"), packed_for_training(spark, sf_dir, "numeric", cfg), []
    rng = np.random.default_rng(cfg.seed)
    u = rng.random(len(data.ids))
    for share in (1.0, 0.1):
        known = Packed(data.ids, data.inputs, [v if x < share else None for v, x in zip(data.variable, u, strict=True)], data.table)
        for augment in (0.0, 0.5):
            net = network_of("numeric", cfg)
            train(net, known, replace(cfg.train, augment=augment, epochs=8))
            auc = M.roc_auc(score_pairs(vectors_of(values, "numeric", net, cfg), pairs).join(pairs, ["id_a", "id_b"])).first()["auc"]
            rows.append((augment, share, round(auc or 0.5, 4)))
    return spark.createDataFrame(rows, "augmentation double, match_share double, auc double")


# ------------------------------------------------------------------ registry

query("w01_embedding_map")(lambda s, d: run_embedding_map(s, d))
query("w02_split_numeric")(lambda s, d: run_pair_classification(s, d, "numeric", "split"))
query("w03_diff_numeric")(lambda s, d: run_pair_classification(s, d, "numeric", "diff"))
query("w04_input_ablation")(lambda s, d: run_input_ablation(s, d))
query("w05_split_language")(lambda s, d: run_pair_classification(s, d, "language", "split"))
query("w05_diff_language")(lambda s, d: run_pair_classification(s, d, "language", "diff"))
query("w06_split_string")(lambda s, d: run_pair_classification(s, d, "string", "split"))
query("w06_diff_string")(lambda s, d: run_pair_classification(s, d, "string", "diff"))
for _kind in ("numeric", "language", "string"):
    query(f"w07_split_retrieve_{_kind}")(lambda s, d, k=_kind: run_retrieval(s, d, k, "split"))
    query(f"w08_diff_retrieve_{_kind}")(lambda s, d, k=_kind: run_retrieval(s, d, k, "diff"))
query("w09_calibrated_recall")(lambda s, d: run_calibrated_recall(s, d))
query("w09_calibrated_recall_language")(lambda s, d: run_calibrated_recall(s, d, "language", absent=("type", "mktsegment")))
query("w09_calibrated_recall_string")(lambda s, d: run_calibrated_recall(s, d, "string", absent=("props", "brand")))
query("w10_lookalike_flags")(lambda s, d: run_lookalike_flags(s, d))
query("w10_lookalike_words")(lambda s, d: run_lookalike_flags(s, d, kind="language"))
query("w11_example_lookup")(lambda s, d: run_example_lookup(s, d))
query("w12_schema_matching")(lambda s, d: run_schema_matching(s, d))
query("w13_union_search")(lambda s, d: run_union_search(s, d))
_SIZES = " UNION ALL ".join(f"SELECT '{k}' AS kind, * FROM ({sizes_sql(f)})" for k, f in _FAMILIES.items())
query(
    "w14_repository_summary",
    f"WITH t AS (SELECT *, {role_sql(Workload().heldout, Workload().seed)} AS role FROM ({_SIZES})), m AS (SELECT kind, role, sum(n * (n - 1) / 2)::BIGINT AS matches FROM (SELECT kind, role, variable, count(*) AS n FROM t GROUP BY ALL) GROUP BY ALL) SELECT kind, role, count(DISTINCT table_id) AS tables, count(*) AS datasets, round(avg(n_values), 2) AS mean_n, round(coalesce(stddev_samp(n_values), 0), 2) AS sd_n, any_value(matches) AS matches FROM t JOIN m USING (kind, role) GROUP BY kind, role",
)(lambda s, d: run_repository_summary(s, d))
_DRAWN = priority_sql("draw::VARCHAR", "id", "k")
query(
    "w15_deviation",
    f"WITH e AS (SELECT label::VARCHAR AS id, vec_id::VARCHAR AS k, embedding::DOUBLE[] AS e FROM embeddings), b AS (SELECT max(list_sum(list_transform(e, lambda x: x * x))) AS b FROM e), x AS (SELECT id, k, unnest(range(0, len(e))) AS i, unnest(e) AS x FROM e), o AS (SELECT draw, id, k, row_number() OVER (PARTITION BY draw, id ORDER BY {_DRAWN}, k) AS r FROM e, range(1, 41) t(draw)), ns AS (SELECT unnest([10, 20, 40]) AS n), s AS (SELECT n, draw, id, i, avg(x) AS m FROM o JOIN x USING (id, k), ns WHERE r <= n GROUP BY ALL), w AS (SELECT id, i, avg(x) AS m FROM x GROUP BY ALL), dn AS (SELECT n, a.draw, a.id AS id_a, b.id AS id_b, sum(pow(a.m - b.m, 2)) AS d_n FROM s a JOIN s b USING (n, draw, i) WHERE a.id < b.id GROUP BY ALL), d AS (SELECT a.id AS id_a, b.id AS id_b, sum(pow(a.m - b.m, 2)) AS d FROM w a JOIN w b USING (i) WHERE a.id < b.id GROUP BY ALL) SELECT n::INTEGER AS n, 0.2::DOUBLE AS eps, round(avg((abs(d_n - d) > 0.2)::INTEGER), 6) AS rate, round(least(1.0, 4 * exp(-n * 0.2::DOUBLE * 0.2::DOUBLE / (32 * any_value(b) * any_value(b)))), 6) AS bound, count(*) AS draws FROM dn JOIN d USING (id_a, id_b), b GROUP BY n",
)(lambda s, d: run_deviation(s, d).withColumns({"rate": F.round("rate", 6), "bound": F.round("bound", 6)}))
query("w16_objectives")(lambda s, d: run_objectives(s, d))
query("w17_search_cost")(lambda s, d: run_search_cost(s, d))
query("w18_scarcity")(lambda s, d: run_scarcity(s, d))
