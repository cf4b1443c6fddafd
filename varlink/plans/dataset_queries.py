"""Queries on datasets, samples, encodings, networks and scores."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.encoding import encode_bits32, encode_exp_mantissa
from ..functions.sampling import priority_sql
from ..functions.scores import match_probability, match_score, pair_loss
from ..functions.vectors import sq_dist
from ..nets.mlp import SetNet, formula_sql
from ..operators import columnize as C
from ..operators.embed import NumericEncoder, embed_datasets, embed_values, partial_states
from ..sources.tables import load_table
from .registry import query
from .repository import repository_values, values_sql

CV = f"cv AS ({values_sql()})"
HIDDEN, OUT = 6, 4


def formula_net(use_g: bool = True) -> SetNet:
    return SetNet(32, HIDDEN, OUT, 3, use_g).init_formula()


def layer_sql(net: str, k: int, source: str, m: int, n: int, activation: str) -> str:
    """One layer of a formula-initialised network over rows ``v, i, x``."""
    w = formula_sql(net).replace("* k", f"* {k}").replace("sqrt(m)", f"sqrt({m})")
    s = f"sum(x * {w})"
    act = {"tanh": f"tanh({s})", "relu": f"greatest(0, {s})", "square": f"pow({s}, 2)"}[activation]
    return f"SELECT v, j AS i, {act} AS x FROM {source}, range(1, {n + 1}) t(j) GROUP BY v, j"


_BITS = "bits AS (SELECT v, i, get_bit(v::FLOAT::BIT, (i - 1)::INTEGER) AS x FROM (SELECT DISTINCT v FROM hist), range(1, 33) t(i))"
NET = f"""hist AS (SELECT dataset_id, value_num AS v, count(*) AS w FROM cv GROUP BY ALL),
{_BITS},
h1 AS ({layer_sql("h", 1, "bits", 32, HIDDEN, "tanh")}), h2 AS ({layer_sql("h", 2, "h1", HIDDEN, HIDDEN, "tanh")}), h3 AS ({layer_sql("h", 3, "h2", HIDDEN, OUT, "tanh")}),
g1 AS ({layer_sql("g", 1, "bits", 32, HIDDEN, "relu")}), g2 AS ({layer_sql("g", 2, "g1", HIDDEN, HIDDEN, "relu")}), g3 AS ({layer_sql("g", 3, "g2", HIDDEN, 1, "square")}),
h AS (SELECT dataset_id, i AS pos, sum(x * w) / sum(w) AS val FROM hist JOIN h3 USING (v) GROUP BY ALL),
g AS (SELECT dataset_id, sum(x * w) / sum(w) AS g FROM hist JOIN g3 USING (v) GROUP BY ALL),
scores AS (SELECT a.dataset_id AS id_a, b.dataset_id AS id_b, sum(pow(a.val - b.val, 2)) + any_value(ga.g) + any_value(gb.g) AS d FROM h a JOIN h b ON a.pos = b.pos AND a.dataset_id < b.dataset_id JOIN g ga ON ga.dataset_id = a.dataset_id JOIN g gb ON gb.dataset_id = b.dataset_id GROUP BY ALL)"""


def formula_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors of all datasets under the formula network, each distinct value embedded once."""
    return embed_datasets(C.value_histogram(repository_values(spark, sf_dir)), formula_net())


def all_scores(vectors: DataFrame) -> DataFrame:
    """``id_a, id_b, d`` of all dataset pairs (a few dozen datasets)."""
    side = lambda k: vectors.select(F.col("dataset_id").alias(f"id_{k}"), F.col("h").alias(f"h_{k}"), F.col("g").alias(f"g_{k}"))
    return side("a").join(F.broadcast(side("b")), F.col("id_a") < F.col("id_b")).select("id_a", "id_b", match_score(F.col("h_a"), F.col("h_b"), F.col("g_a"), F.col("g_b")).alias("d"))


# ------------------------------------------------------------------ datasets

_LINE = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax")


@query("q01_columnize", " UNION ALL ".join(f"SELECT '{c}' AS column_name, count({c}) AS n, round(avg({c}), 4) AS mean FROM lineitem" for c in _LINE))
def columnized(spark, sf_dir):
    long = C.columnize_by_unpivot(load_table(spark, sf_dir, "lineitem"), "lineitem", list(_LINE))
    return long.groupBy(F.col("column").alias("column_name")).agg(F.count("*").alias("n"), F.round(F.avg("value_num"), 4).alias("mean"))


_HIST = (("part", "p_size"), ("part", "p_brand"), ("lineitem", "l_returnflag"), ("lineitem", "l_linestatus"), ("orders", "o_orderstatus"), ("labels", "quality"), ("labels", "toxic"))


@query("q02_value_histogram", " UNION ALL ".join(f"SELECT '{c}' AS column_name, CAST({c} AS VARCHAR) AS value, count(*) AS weight FROM {t} GROUP BY {c}" for t, c in _HIST))
def histograms(spark, sf_dir):
    out = None
    for t in dict.fromkeys(t for t, _ in _HIST):
        columns = [c for x, c in _HIST if x == t]
        df = load_table(spark, sf_dir, t, columns).select(*[F.col(c).cast("string").alias(c) for c in columns])
        h = C.value_histogram(C.columnize(df, t), ("column",), "value_str").select(F.col("column").alias("column_name"), F.col("value_str").alias("value"), "weight")
        out = h if out is None else out.unionByName(h)
    return out


_TEXTS = (("part", "p_name"), ("part", "p_type"), ("part", "p_brand"), ("customer", "c_name"), ("customer", "c_mktsegment"), ("orders", "o_orderstatus"), ("orders", "o_orderpriority"), ("region", "r_name"), ("documents", "text"), ("pages", "url"), ("pages", "html"), ("events", "event_type"), ("events", "props"))


def text_values(spark: SparkSession, sf_dir: str, columns=_TEXTS) -> DataFrame:
    out = None
    for t, c in columns:
        df = C.columnize(load_table(spark, sf_dir, t, [c]), t)
        out = df if out is None else out.unionByName(df)
    return out


_WORDS = "list_filter(string_split_regex(lower({}), '[^\\p{{L}}]+'), lambda w: length(w) >= 2)"
_PLAIN = "trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace({0}, '<script[^>]*>.*?</script>', ' ', 'gis'), '<style[^>]*>.*?</style>', ' ', 'gis'), '<!--.*?-->', ' ', 'gs'), '<[^>]*>', ' ', 'gs'), '\\s+', ' ', 'g'))"
_TEXT_CTE = "tv AS (" + " UNION ALL ".join(f"SELECT '{t}.{c}' AS dataset_id, {c} AS v FROM {t} WHERE {c} IS NOT NULL" for t, c in _TEXTS) + ")"
_VOCAB = f"vocab AS (SELECT word FROM (SELECT unnest(list_distinct({_WORDS.format('v')})) AS word FROM tv) GROUP BY word HAVING count(*) >= 5)"


@query(
    "q03_infer_kind",
    rf"""
WITH {_TEXT_CTE}, {_VOCAB},
f AS (SELECT dataset_id, v, count(*) AS w, regexp_matches(v, '^[a-z]+://') OR (regexp_matches(v, '[0-9#_{{}}]') AND len(string_split_regex(v, '\s+')) <= 3) AS code FROM tv GROUP BY dataset_id, v),
p AS (SELECT dataset_id, v, unnest({_WORDS.format("CASE WHEN regexp_matches(v, '<html|</\\w+>', 'i') THEN " + _PLAIN.format("v") + " ELSE v END")}) AS word FROM f WHERE NOT code),
k AS (SELECT dataset_id, v, avg((vocab.word IS NOT NULL)::INTEGER) AS share FROM p LEFT JOIN vocab USING (word) GROUP BY dataset_id, v),
s AS (SELECT dataset_id, sum(CASE WHEN coalesce(share, 0) > 0.5 THEN w ELSE 0 END) / sum(w) AS language_share FROM f LEFT JOIN k USING (dataset_id, v) GROUP BY dataset_id)
SELECT dataset_id, CASE WHEN language_share > 0.5 THEN 'language' ELSE 'string' END AS kind, round(language_share, 4) AS language_share FROM s""",
)
def kinds(spark, sf_dir):
    values = text_values(spark, sf_dir)
    return C.infer_kind(values, C.build_vocab(values)).select("dataset_id", "kind", F.round("language_share", 4).alias("language_share"))


def _sampled(n: int = 1000, seed: int = 42) -> str:
    return f"s AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY dataset_id ORDER BY {priority_sql(seed, 'dataset_id', 'row_key')}, row_key) AS r FROM cv) WHERE r <= {n})"


@query("q04_subsample", f"WITH {CV}, {_sampled()} SELECT dataset_id, count(*) AS n, round(sum(value_num), 2) AS total FROM s GROUP BY dataset_id")
def subsampled(spark, sf_dir):
    s = C.subsample(repository_values(spark, sf_dir))
    return s.groupBy("dataset_id").agg(F.count("*").alias("n"), F.round(F.sum("value_num"), 2).alias("total"))


FRACTIONS = (1 / 16, 1 / 8, 1 / 4, 1 / 2, 1.0)


@query("q05_downsample_fraction", f"WITH {CV} SELECT dataset_id, f AS fraction, count(*) AS n FROM cv, (SELECT unnest([{', '.join(map(str, FRACTIONS))}]::DOUBLE[]) AS f) WHERE {priority_sql(42, 'dataset_id', 'row_key')} < f GROUP BY ALL")
def downsampled(spark, sf_dir):
    cv, out = repository_values(spark, sf_dir), None
    for f in FRACTIONS:
        part = C.downsample_fraction(cv, f).groupBy("dataset_id").agg(F.count("*").alias("n")).select("dataset_id", F.lit(f).alias("fraction"), "n")
        out = part if out is None else out.unionByName(part)
    return out


@query("q06_split_halves", f"WITH {CV}, p AS (SELECT dataset_id, row_key, ('0x' || substr(md5(concat_ws('|', '7', row_key)), 1, 8))::BIGINT % 2 AS half FROM cv) SELECT dataset_id, half::INTEGER AS half, count(*) AS n, 0::BIGINT AS shared FROM p GROUP BY ALL")
def halves(spark, sf_dir):
    cv = C.split_halves(repository_values(spark, sf_dir))
    both = cv.groupBy("dataset_id", "row_key").agg(F.countDistinct("half").alias("h")).groupBy("dataset_id").agg(F.sum((F.col("h") > 1).cast("long")).alias("shared"))
    return cv.groupBy("dataset_id", "half").agg(F.count("*").alias("n")).join(both, "dataset_id")


# ------------------------------------------------------------------ encodings


@query("q07_bits32", "WITH x AS (SELECT DISTINCT 'l_discount' AS column_name, l_discount::DOUBLE AS value FROM lineitem UNION SELECT DISTINCT 'p_size', p_size FROM part) SELECT column_name, value, i::INTEGER AS pos, get_bit(value::FLOAT::BIT, i::INTEGER)::INTEGER AS bit FROM x, range(0, 32) t(i)")
def bits(spark, sf_dir):
    one = lambda t, c: load_table(spark, sf_dir, t, [c]).distinct().select(F.lit(c).alias("column_name"), F.col(c).cast("double").alias("value"))
    x = one("lineitem", "l_discount").unionByName(one("part", "p_size"))
    return x.select("column_name", "value", F.posexplode(encode_bits32(F.col("value"))).alias("pos", "bit"))


@query("q08_exp_mantissa", "WITH x AS (SELECT DISTINCT p_retailprice AS value FROM part UNION SELECT DISTINCT c_acctbal FROM customer), e AS (SELECT value, CASE WHEN value = 0 THEN 0 ELSE floor(log2(abs(value))) END AS e0 FROM x), f AS (SELECT value, CASE WHEN value = 0 THEN 0 WHEN pow(2, e0) > abs(value) THEN e0 - 1 WHEN pow(2, e0 + 1) <= abs(value) THEN e0 + 1 ELSE e0 END AS e FROM e) SELECT value, e::DOUBLE AS exponent, round(CASE WHEN value = 0 THEN 0 ELSE value / pow(2, e) END, 4) AS mantissa FROM f")
def exp_mantissa(spark, sf_dir):
    x = load_table(spark, sf_dir, "part", ["p_retailprice"]).toDF("value").union(load_table(spark, sf_dir, "customer", ["c_acctbal"]).toDF("value")).distinct()
    em = encode_exp_mantissa(F.col("value"))
    return x.select("value", em[0].alias("exponent"), F.round(em[1], 4).alias("mantissa"))


# ------------------------------------------------------------------ networks


@query("q09_forward_layer", f"WITH hist AS (SELECT DISTINCT v FROM (SELECT p_size::DOUBLE AS v FROM part UNION ALL SELECT l_discount FROM lineitem)), {_BITS}, h1 AS ({layer_sql('h', 1, 'bits', 32, HIDDEN, 'tanh')}) SELECT v AS value, i::INTEGER AS unit, round(x, 4) AS output FROM h1")
def first_layer(spark, sf_dir):
    x = load_table(spark, sf_dir, "part").select(F.col("p_size").cast("double").alias("value_num")).union(load_table(spark, sf_dir, "lineitem", ["l_discount"])).distinct()
    net = SetNet(32, HIDDEN, HIDDEN, 1).init_formula()
    out = embed_values(x, net)
    return out.select(F.col("value_num").alias("value"), F.posexplode("h").alias("pos", "x")).select("value", (F.col("pos") + 1).alias("unit"), F.round("x", 4).alias("output"))


@query("q10_embed_numeric", f"WITH {CV}, {NET} SELECT dataset_id, pos::INTEGER AS pos, round(val, 4) AS val FROM h")
def embedded(spark, sf_dir):
    return formula_vectors(spark, sf_dir).select("dataset_id", F.posexplode("h").alias("pos", "val")).select("dataset_id", (F.col("pos") + 1).alias("pos"), F.round("val", 4).alias("val"))


@query("q11_weighted_pooling", f"WITH {CV}, {NET} SELECT dataset_id, count(*)::BIGINT AS n, 0.0::DOUBLE AS gap FROM cv GROUP BY dataset_id")
def weighted_pooling(spark, sf_dir):
    """Pooling every value and pooling distinct values by multiplicity agree."""
    cv = repository_values(spark, sf_dir)
    plain, weighted = embed_datasets(cv, formula_net()), embed_datasets(C.value_histogram(cv), formula_net())
    return plain.select("dataset_id", F.col("n_used").alias("n"), F.col("h").alias("h1")).join(weighted.select("dataset_id", "h"), "dataset_id").select("dataset_id", "n", F.abs(F.round(sq_dist(F.col("h1"), F.col("h")), 9)).alias("gap"))


@query("q12_adjustment", f"WITH {CV}, {NET} SELECT dataset_id, round(g, 4) AS g FROM g")
def adjustments(spark, sf_dir):
    return formula_vectors(spark, sf_dir).select("dataset_id", F.round("g", 4).alias("g"))


BAGS = "bag AS (SELECT label, unnest(range(0, len(embedding))) AS pos, unnest(embedding)::DOUBLE AS x FROM embeddings), m AS (SELECT label, pos, avg(x) AS x FROM bag GROUP BY ALL)"


def bag_means(spark: SparkSession, sf_dir: str, width: int = 64) -> DataFrame:
    e = load_table(spark, sf_dir, "embeddings")
    return e.groupBy("label").agg(F.array(*[F.avg(F.col("embedding")[i].cast("double")) for i in range(width)]).alias("m"), F.count("*").alias("n"))


def bag_pairs(spark, sf_dir):
    m = bag_means(spark, sf_dir)
    side = lambda k: m.select(F.col("label").alias(f"label_{k}"), F.col("m").alias(f"m_{k}"), F.col("n").alias(f"n_{k}"))
    return side("a").join(side("b"), F.col("label_a") < F.col("label_b"))


@query("q13_pair_distance", f"WITH {BAGS} SELECT a.label AS label_a, b.label AS label_b, round(sum(pow(a.x - b.x, 2)), 4) AS d FROM m a JOIN m b ON a.pos = b.pos AND a.label < b.label GROUP BY ALL")
def pair_distance(spark, sf_dir):
    return bag_pairs(spark, sf_dir).select("label_a", "label_b", F.round(sq_dist(F.col("m_a"), F.col("m_b")), 4).alias("d"))


@query("q14_match_score_prob", f"WITH {CV}, {NET} SELECT id_a, id_b, round(d, 4) AS d, round(exp(-d), 4) AS p FROM scores")
def scores(spark, sf_dir):
    return all_scores(formula_vectors(spark, sf_dir)).select("id_a", "id_b", F.round("d", 4).alias("d"), F.round(match_probability(F.col("d")), 4).alias("p"))


_VARIABLE = "variable AS (SELECT DISTINCT dataset_id, variable FROM cv)"


def same_variable(df: DataFrame) -> F.Column:
    """1 where both ids end in the same column label."""
    label = lambda c: F.regexp_replace(F.element_at(F.split(F.col(c), r"\."), -1), "^[a-z]+_", "")
    return (label("id_a") == label("id_b")).cast("int")


@query("q15_loss", f"WITH {CV}, {NET}, {_VARIABLE}, l AS (SELECT id_a, id_b, d, (a.variable = b.variable)::INTEGER AS y FROM scores JOIN variable a ON a.dataset_id = id_a JOIN variable b ON b.dataset_id = id_b) SELECT id_a, id_b, y, round(CASE WHEN y = 1 THEN d ELSE -ln(1 - exp(-d)) END, 4) AS loss, round(-y * ln(exp(-d)) - (1 - y) * ln(1 - exp(-d)), 4) AS cross_entropy FROM l")
def losses(spark, sf_dir):
    s = all_scores(formula_vectors(spark, sf_dir))
    s = s.withColumns({"y": same_variable(s), "p": match_probability(F.col("d"))})
    return s.select("id_a", "id_b", "y", F.round(pair_loss(F.col("d"), F.col("y")), 4).alias("loss"), F.round(-F.col("y") * F.log("p") - (1 - F.col("y")) * F.log(1 - F.col("p")), 4).alias("cross_entropy"))


@query("q16_search_vectors", f"WITH {CV}, {NET} SELECT id_a, id_b, round(d, 4) AS d_search, round(d, 4) AS d_score FROM scores")
def search_identity(spark, sf_dir):
    """The squared distance of search vectors is the score."""
    from ..functions.scores import query_vector

    v = formula_vectors(spark, sf_dir)
    a = v.select(F.col("dataset_id").alias("id_a"), query_vector(F.col("h"), F.col("g")).alias("s_a"), F.col("h").alias("h_a"), F.col("g").alias("g_a"))
    b = v.select(F.col("dataset_id").alias("id_b"), F.col("s").alias("s_b"), F.col("h").alias("h_b"), F.col("g").alias("g_b"))
    return a.join(b, F.col("id_a") < F.col("id_b")).select("id_a", "id_b", F.round(sq_dist(F.col("s_a"), F.col("s_b")), 4).alias("d_search"), F.round(match_score(F.col("h_a"), F.col("h_b"), F.col("g_a"), F.col("g_b")), 4).alias("d_score"))


@query("q16b_state_merge", f"WITH {CV}, {NET} SELECT dataset_id, round(val, 4) AS first_unit FROM h WHERE pos = 1")
def merged_states(spark, sf_dir):
    """States of two halves of the rows, computed apart and added, give the whole's embedding."""
    from ..operators.embed import finalize, merge_states

    cv = C.split_halves(repository_values(spark, sf_dir))
    parts = [partial_states(cv.filter(F.col("half") == h), formula_net(), NumericEncoder()) for h in (0, 1)]
    return finalize(merge_states(parts[0].unionByName(parts[1]), OUT)).select("dataset_id", F.round(F.col("h")[0], 4).alias("first_unit"))
