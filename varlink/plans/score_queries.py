"""Queries on search, baselines, truth and measures."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.sampling import priority_sql
from ..functions.scores import combine_scores, deviation_bound, match_probability, recalibrate_prior, recalibrate_pu
from ..functions.text import VAGUE_LABELS, jaro_winkler, plain_label
from ..functions.vectors import sq_dist
from ..operators import baselines as B
from ..operators import columnize as C
from ..operators import measures as M
from ..operators import search as X
from ..operators import truth as G
from ..sources.scratch import cut
from ..sources.tables import load_table
from .dataset_queries import BAGS, CV, NET, all_scores, bag_pairs, formula_vectors, same_variable
from .registry import query
from .repository import repository_values, role_sql, truth_of

# ------------------------------------------------------------------ search on the given vectors


def vectors(spark, sf_dir) -> DataFrame:
    return load_table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("string").alias("dataset_id"), F.col("embedding").cast("array<double>").alias("s"), "label")


def vector_queries(spark, sf_dir) -> DataFrame:
    """Every vector whose id is divisible by 20."""
    return vectors(spark, sf_dir).filter(F.col("dataset_id").cast("long") % 20 == 0).select(F.col("dataset_id").alias("query_id"), "s")


_TOP = """WITH q AS (SELECT vec_id::VARCHAR AS query_id, embedding::DOUBLE[] AS e FROM embeddings WHERE vec_id % 20 = 0),
d AS (SELECT query_id, vec_id::VARCHAR AS dataset_id, list_sum(list_transform(list_zip(q.e, x.embedding::DOUBLE[]), lambda p: (p[1] - p[2]) * (p[1] - p[2]))) AS d FROM q, embeddings x),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY d, dataset_id) AS rank FROM d)
SELECT query_id, dataset_id, rank::INTEGER AS rank, round(d, 4) AS d FROM r WHERE rank <= 5"""


def _top(df):
    return df.select("query_id", "dataset_id", F.col("rank").cast("int").alias("rank"), F.round("d", 4).alias("d"))


@query("q17_topk_exact", _TOP)
def exact_search(spark, sf_dir):
    return _top(X.top_k_exact(vector_queries(spark, sf_dir), vectors(spark, sf_dir), 5))


@query("q18_topk_lsh")
def hashed_search(spark, sf_dir):
    """Random-projection search with its recall against exact search in every row."""
    q, r = vector_queries(spark, sf_dir), X.spread(vectors(spark, sf_dir))
    found, exact = cut(X.top_k_lsh(q, r, 5, bucket_length=1.0, tables=10), "search-found"), X.top_k_exact(q, r, 5)
    return _top(found).crossJoin(F.broadcast(M.index_recall(found, exact, 5).select(F.round("recall", 4).alias("recall"))))


@query("q19_topk_ivf", _TOP)
def cell_search(spark, sf_dir):
    """With every cell probed, cell search is exact."""
    r = X.spread(vectors(spark, sf_dir))
    centroids = X.fit_cells(r, 16)
    return _top(X.top_k_cells(vector_queries(spark, sf_dir), X.assign_cells(r, centroids), centroids, 5, probes=len(centroids)))


@query("q19b_ivf_recall")
def cell_recall(spark, sf_dir):
    """Recall and scored rows by the number of probed cells."""
    r, q = X.spread(vectors(spark, sf_dir)), vector_queries(spark, sf_dir)
    centroids = X.fit_cells(r, 16)
    indexed, exact, out = cut(X.assign_cells(r, centroids), "search-cells"), cut(X.top_k_exact(q, r, 5), "search-exact"), None
    for probes in (1, 2, 4, 8, 16):
        one = M.index_recall(X.top_k_cells(q, indexed, centroids, 5, probes), exact, 5).select(F.lit(probes).alias("probes"), F.round("recall", 4).alias("recall"), "queries")
        out = one if out is None else out.unionByName(one)
    return out


# ------------------------------------------------------------------ baselines


def table_values(spark, sf_dir, table, shard, key, column):
    df = load_table(spark, sf_dir, table)
    return df.select(F.expr(shard).alias("dataset_id"), F.col(key).cast("string").alias("row_key"), F.col(column).cast("double").alias("value_num"))


def all_pairs(cv: DataFrame) -> DataFrame:
    """All pairs of datasets, for a few hundred datasets: the result itself grows with their square."""
    ids = cv.select("dataset_id").distinct()
    return ids.withColumnRenamed("dataset_id", "id_a").join(F.broadcast(ids.withColumnRenamed("dataset_id", "id_b")), F.col("id_a") < F.col("id_b"))


def _d(df: DataFrame, places: int = 4) -> DataFrame:
    return df.select("id_a", "id_b", F.round("d", places).alias("d"))


@query(
    "q20_mean_sd",
    "WITH cv AS (SELECT concat('events:', event_type) AS id, value AS v FROM events UNION ALL SELECT concat('nation:', c_nationkey::VARCHAR), c_acctbal FROM customer), s AS (SELECT id, avg(v) AS m, coalesce(stddev_samp(v), 0) AS sd FROM cv GROUP BY id) SELECT a.id AS id_a, b.id AS id_b, round(abs(a.m - b.m) + abs(a.sd - b.sd), 4) AS d FROM s a JOIN s b ON a.id < b.id",
)
def mean_sd(spark, sf_dir):
    cv = table_values(spark, sf_dir, "events", "concat('events:', event_type)", "event_id", "value").unionByName(table_values(spark, sf_dir, "customer", "concat('nation:', CAST(c_nationkey AS STRING))", "c_custkey", "c_acctbal"))
    return _d(B.mean_sd_distance(cv, all_pairs(cv)))


@query("q20b_approx_stats")
def approx_stats(spark, sf_dir):
    """Sketched counts and quartiles, and whether a dataset is pooled by distinct values."""
    a = C.approx_stats(repository_values(spark, sf_dir))
    return a.select("dataset_id", "n", "n_distinct", F.col("quartiles")[1].alias("median"), "by_distinct")


_KS_E = "(n1 * n2 / (n1 + n2))"
_LAM = f"((sqrt({_KS_E}) + 0.12 + 0.11 / sqrt({_KS_E})) * gap)"
_HIST = "hist AS (SELECT dataset_id, value_num AS v, count(*)::DOUBLE AS w FROM cv GROUP BY ALL), ids AS (SELECT DISTINCT dataset_id FROM hist), pairs AS (SELECT a.dataset_id AS id_a, b.dataset_id AS id_b FROM ids a JOIN ids b ON a.dataset_id < b.dataset_id)"
_MERGED = "m AS (SELECT id_a, id_b, v, sum(wa) AS wa, sum(wb) AS wb FROM (SELECT id_a, id_b, v, w AS wa, 0.0::DOUBLE AS wb FROM pairs JOIN hist ON dataset_id = id_a UNION ALL SELECT id_a, id_b, v, 0.0::DOUBLE, w FROM pairs JOIN hist ON dataset_id = id_b) GROUP BY ALL), t AS (SELECT *, sum(wa) OVER p AS na, sum(wb) OVER p AS nb, count(*) OVER p AS u FROM m WINDOW p AS (PARTITION BY id_a, id_b))"


def same_pairs(cv: DataFrame) -> DataFrame:
    """Pairs of datasets of one variable: the tests on all values cost a pair all its distinct values."""
    p = all_pairs(cv)
    return p.filter(same_variable(p) == 1)


_LABEL = "regexp_replace(string_split({}.dataset_id, '.')[-1], '^[a-z]+_', '')"
_SAME_HIST = f"{_HIST[:-1]} WHERE {_LABEL.format('a')} = {_LABEL.format('b')})"


@query(
    "q21_ks",
    f"WITH {CV}, {_SAME_HIST}, {_MERGED}, c AS (SELECT *, abs(sum(wa) OVER r / na - sum(wb) OVER r / nb) AS g FROM t WINDOW r AS (PARTITION BY id_a, id_b ORDER BY v)), k AS (SELECT id_a, id_b, max(g) AS gap, any_value(na) AS n1, any_value(nb) AS n2 FROM c GROUP BY ALL), l AS (SELECT *, {_LAM} AS lam FROM k) SELECT id_a, id_b, round(gap, 4) AS gap, round(CASE WHEN lam < 0.2 THEN 1.0 ELSE least(1.0, greatest(0.0, (SELECT sum(CASE WHEN j % 2 = 1 THEN 2.0 ELSE -2.0 END * exp(-2.0 * j * j * lam * lam)) FROM range(1, 101) t(j)))) END, 4) AS p FROM l",
)
def ks(spark, sf_dir):
    h = C.value_histogram(repository_values(spark, sf_dir))
    return B.ks_gap(h, same_pairs(h)).select("id_a", "id_b", F.round("gap", 4).alias("gap"), F.round("p", 4).alias("p"))


BANDWIDTH = 10.0
_K = lambda x, y: f"exp(-(({x}) - ({y})) * (({x}) - ({y})) / {2 * BANDWIDTH * BANDWIDTH})"


@query(
    "q22_mmd_linear",
    f"WITH cv0 AS (SELECT concat('quantity:', l_returnflag, l_linestatus) AS dataset_id, concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey) AS row_key, l_quantity AS v FROM lineitem UNION ALL SELECT concat('size:', (p_partkey % 3)::VARCHAR), p_partkey::VARCHAR, p_size::DOUBLE FROM part), o AS (SELECT dataset_id, v, row_number() OVER (PARTITION BY dataset_id ORDER BY {priority_sql(5, 'dataset_id', 'row_key')}, row_key, v) - 1 AS n FROM cv0), f AS (SELECT dataset_id, n // 2 AS i, max(CASE WHEN n % 2 = 0 THEN v END) AS x, max(CASE WHEN n % 2 = 1 THEN v END) AS y FROM o GROUP BY ALL HAVING x IS NOT NULL AND y IS NOT NULL) SELECT a.dataset_id AS id_a, b.dataset_id AS id_b, round(avg({_K('a.x', 'a.y')} + {_K('b.x', 'b.y')} - {_K('a.x', 'b.y')} - {_K('a.y', 'b.x')}), 4) AS d FROM f a JOIN f b ON a.i = b.i AND a.dataset_id < b.dataset_id GROUP BY ALL",
)
def mmd_linear(spark, sf_dir):
    q = load_table(spark, sf_dir, "lineitem").select(F.concat(F.lit("quantity:"), "l_returnflag", "l_linestatus").alias("dataset_id"), F.concat_ws("|", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").alias("row_key"), F.col("l_quantity").alias("value_num"))
    cv = q.unionByName(table_values(spark, sf_dir, "part", "concat('size:', CAST(p_partkey % 3 AS STRING))", "p_partkey", "p_size"))
    return _d(B.mmd_linear_sql(cv, all_pairs(cv), BANDWIDTH))


_EVEN = "cv AS (SELECT 'quantity' AS dataset_id, l_quantity AS value_num FROM lineitem UNION ALL SELECT 'size', p_size FROM part UNION ALL SELECT 'discount', l_discount FROM lineitem UNION ALL SELECT 'tax', l_tax FROM lineitem)"


def even_values(spark, sf_dir):
    """Whole columns in two look-alike pairs."""
    li = load_table(spark, sf_dir, "lineitem")
    one = lambda df, c, n: df.select(F.lit(n).alias("dataset_id"), F.col(c).cast("double").alias("value_num"))
    return one(li, "l_quantity", "quantity").unionByName(one(load_table(spark, sf_dir, "part"), "p_size", "size")).unionByName(one(li, "l_discount", "discount")).unionByName(one(li, "l_tax", "tax"))


@query(
    "q23_mmd_quadratic",
    f"WITH {_EVEN}, p AS (SELECT dataset_id, value_num AS x, count(*) / sum(count(*)) OVER (PARTITION BY dataset_id) AS w FROM cv GROUP BY dataset_id, value_num), k AS (SELECT a.dataset_id AS i, b.dataset_id AS j, sum(a.w * b.w * {_K('a.x', 'b.x')}) AS k FROM p a, p b GROUP BY ALL) SELECT c.i AS id_a, c.j AS id_b, round(a.k + b.k - 2 * c.k, 4) AS d FROM k c JOIN k a ON a.i = c.i AND a.j = c.i JOIN k b ON b.i = c.j AND b.j = c.j WHERE c.i < c.j",
)
def mmd_quadratic(spark, sf_dir):
    h = C.value_histogram(even_values(spark, sf_dir))
    return _d(B.mmd_quadratic_sql(h, all_pairs(h), BANDWIDTH))


FREQS = (-1.5, -1.0, -0.6, -0.3, -0.1, 0.2, 0.4, 0.8, 1.2, 2.0)


@query(
    "q24_scf_moments",
    f"WITH {_EVEN}, z AS (SELECT dataset_id, (value_num - 20.0) / 15.0 AS z FROM cv), f AS (SELECT unnest([{', '.join(map(str, FREQS))}]::DOUBLE[]) AS f, unnest(range(0, {len(FREQS)})) AS j) SELECT dataset_id, j::INTEGER AS j, round(avg(exp(-(z * z) / 2) * sin(z * f)), 4) AS mean_sin, round(avg(exp(-(z * z) / 2) * cos(z * f)), 4) AS mean_cos FROM z, f GROUP BY ALL",
)
def cf_moments(spark, sf_dir):
    m = B.cf_moments(even_values(spark, sf_dir), list(FREQS), 20.0, 15.0)
    return m.select("dataset_id", "j", F.round("mean_sin", 4).alias("mean_sin"), F.round("mean_cos", 4).alias("mean_cos"))


@query("q24b_smooth_cf")
def smooth_cf(spark, sf_dir):
    """The whole test on all values of the pairs of one variable, from moments that merge."""
    hist = C.value_histogram(repository_values(spark, sf_dir))
    return _d(B.smooth_cf_of_histograms(hist, same_pairs(hist)))


@query("q25_jaccard", f"WITH {CV}, v AS (SELECT DISTINCT dataset_id, value_num FROM cv), n AS (SELECT dataset_id, count(*) AS u FROM v GROUP BY ALL), s AS (SELECT a.dataset_id AS id_a, b.dataset_id AS id_b, count(*) AS shared FROM v a JOIN v b USING (value_num) WHERE a.dataset_id < b.dataset_id GROUP BY ALL) SELECT a.dataset_id AS id_a, b.dataset_id AS id_b, round(1 - coalesce(shared, 0)::DOUBLE / (a.u + b.u - coalesce(shared, 0)), 4) AS d FROM n a JOIN n b ON a.dataset_id < b.dataset_id LEFT JOIN s ON s.id_a = a.dataset_id AND s.id_b = b.dataset_id")
def jaccard(spark, sf_dir):
    h = C.value_histogram(repository_values(spark, sf_dir))
    return _d(B.jaccard_distance(h, all_pairs(h)))


@query("q25b_jaccard_minhash")
def jaccard_sketch(spark, sf_dir):
    cv = repository_values(spark, sf_dir)
    return _d(B.jaccard_minhash(cv, all_pairs(cv)))


@query("q26_mean_wordvec", f"WITH {BAGS} SELECT a.label AS label_a, b.label AS label_b, round(sqrt(sum(pow(a.x - b.x, 2))), 4) AS d FROM m a JOIN m b ON a.pos = b.pos AND a.label < b.label GROUP BY ALL")
def mean_wordvec(spark, sf_dir):
    return bag_pairs(spark, sf_dir).select("label_a", "label_b", F.round(F.sqrt(sq_dist(F.col("m_a"), F.col("m_b"))), 4).alias("d"))


@query(
    "q27_hotelling_diag",
    "WITH bag AS (SELECT label, unnest(range(0, len(embedding))) AS pos, unnest(embedding)::DOUBLE AS x FROM embeddings), s AS (SELECT label, pos, avg(x) AS m, var_pop(x) * count(*) AS ss, count(*) AS n FROM bag GROUP BY ALL) SELECT a.label AS label_a, b.label AS label_b, round(sum((a.n * b.n)::DOUBLE / (a.n + b.n) * pow(a.m - b.m, 2) / ((a.ss + b.ss) / (a.n + b.n - 2) + 1e-6)), 4) AS t2 FROM s a JOIN s b ON a.pos = b.pos AND a.label < b.label GROUP BY ALL",
)
def hotelling_diag(spark, sf_dir):
    """Diagonal two-sample statistic from per-dimension moments, which merge."""
    e = load_table(spark, sf_dir, "embeddings").select("label", F.posexplode("embedding").alias("pos", "x"))
    x = F.col("x").cast("double")
    s = e.groupBy("label", "pos").agg(F.avg(x).alias("m"), (F.var_pop(x) * F.count("*")).alias("ss"), F.count("*").alias("n"))
    side = lambda k: s.select("pos", *[F.col(c).alias(f"{c}_{k}") for c in ("label", "m", "ss", "n")])
    p = side("a").join(side("b"), "pos").filter("label_a < label_b")
    term = F.col("n_a") * F.col("n_b") / (F.col("n_a") + F.col("n_b")) * (F.col("m_a") - F.col("m_b")) ** 2 / ((F.col("ss_a") + F.col("ss_b")) / (F.col("n_a") + F.col("n_b") - 2) + 1e-6)
    return p.groupBy("label_a", "label_b").agg(F.round(F.sum(term), 4).alias("t2"))


_WIDTH = 64


@query(
    "q27b_hotelling_full",
    # each step takes the first unknown out of the bordered covariance matrix; the corner ends as minus the quadratic form
    f"""WITH RECURSIVE bag AS (SELECT label::VARCHAR AS id, vec_id, unnest(range(0, {_WIDTH})) AS pos, unnest(embedding)::DOUBLE AS x FROM embeddings),
m AS (SELECT id, pos, avg(x) AS m, count(*)::DOUBLE AS n FROM bag GROUP BY ALL), z AS (SELECT id, vec_id, pos, x - m AS x FROM bag JOIN m USING (id, pos)),
c AS (SELECT a.id, a.pos AS i, b.pos AS j, sum(a.x * b.x) AS s FROM z a JOIN z b USING (id, vec_id) GROUP BY ALL),
n AS (SELECT DISTINCT id, n FROM m), pairs AS (SELECT a.id AS id_a, b.id AS id_b, a.n AS na, b.n AS nb FROM n a JOIN n b ON a.id < b.id),
s AS (SELECT id_a, id_b, na, nb, i, j, (a.s + b.s) / greatest(1, na + nb - 2) AS v FROM pairs JOIN c a ON a.id = id_a JOIN c b USING (i, j) WHERE b.id = id_b),
t AS (SELECT id_a, id_b, sum(v) / {_WIDTH} AS scale FROM s WHERE i = j GROUP BY ALL),
e AS (SELECT 0 AS k, id_a, id_b, i, j, v + CASE WHEN i = j THEN CASE WHEN na + nb > {_WIDTH + 1} THEN 1e-6 ELSE 0.1 END * scale ELSE 0 END AS v FROM s JOIN t USING (id_a, id_b)
  UNION ALL SELECT 0, id_a, id_b, CASE WHEN side = 0 THEN a.pos ELSE {_WIDTH} END, CASE WHEN side = 0 THEN {_WIDTH} ELSE a.pos END, a.m - b.m FROM pairs JOIN m a ON a.id = id_a JOIN m b ON b.id = id_b AND a.pos = b.pos, range(0, 2) q(side)
  UNION ALL SELECT 0, id_a, id_b, {_WIDTH}, {_WIDTH}, 0.0 FROM pairs),
r AS (SELECT * FROM e UNION ALL SELECT k + 1, id_a, id_b, i, j, v - down * across / corner FROM (SELECT *, first_value(v) OVER (PARTITION BY id_a, id_b, i ORDER BY j) AS down, first_value(v) OVER (PARTITION BY id_a, id_b, j ORDER BY i) AS across, first_value(v) OVER (PARTITION BY id_a, id_b ORDER BY i, j) AS corner FROM r) WHERE i > k AND j > k AND k < {_WIDTH})
SELECT id_a, id_b, round(-v * na * nb / (na + nb), 2) AS t2 FROM r JOIN pairs USING (id_a, id_b) WHERE k = {_WIDTH}""",
)
def hotelling_full(spark, sf_dir):
    """The full-covariance statistic of all given vectors as fields, from moments that merge."""
    e = load_table(spark, sf_dir, "embeddings").select(F.col("label").cast("string").alias("dataset_id"), F.col("vec_id").cast("string").alias("row_key"), F.col("embedding").cast("array<double>").alias("vec"))
    return B.hotelling_of_moments(B.vector_moments(e), all_pairs(e), output="t2").select("id_a", "id_b", F.round("d", 2).alias("t2"))


EDGES = (0.0, 0.02, 0.05, 0.08, 1.0, 5.0, 10.0, 20.0, 30.0, 40.0, 50.0, 1000.0, 5000.0)
_BIN = " + ".join(f"(value_num >= {e})::INTEGER" for e in EDGES)


@query("q28_histogram_distance", f"WITH cv0 AS (SELECT * FROM ({CV[len('cv AS ('):-1]})), cv AS (SELECT dataset_id, ({_BIN})::DOUBLE AS value_num FROM cv0), {_HIST}, {_MERGED} SELECT id_a, id_b, round(sqrt(sum(pow(wa / na - wb / nb, 2))), 4) AS d FROM t GROUP BY ALL")
def histogram_distance(spark, sf_dir):
    cv = repository_values(spark, sf_dir)
    return _d(B.histogram_distance(cv, all_pairs(cv), list(EDGES)))


@query("q28b_probability_vector", f"WITH {CV}, {_HIST}, {_MERGED} SELECT id_a, id_b, round(sqrt(sum(pow(wa / na - wb / nb, 2))), 4) AS d FROM t GROUP BY ALL")
def probability_vectors(spark, sf_dir):
    h = C.value_histogram(repository_values(spark, sf_dir))
    return _d(B.probability_vector_distance(h, all_pairs(h)))


@query("q28c_likelihood", f"WITH {CV}, {_HIST}, {_MERGED} SELECT id_a, id_b, round(-(sum(wa / na * ln((wb + 1) / (nb + u))) + sum(wb / nb * ln((wa + 1) / (na + u)))) / 2, 4) AS d FROM t GROUP BY ALL")
def likelihoods(spark, sf_dir):
    h = C.value_histogram(repository_values(spark, sf_dir))
    return _d(B.likelihood_similarity(h, all_pairs(h)))


# ------------------------------------------------------------------ truth

#: Columns whose distinct values are the labels: names, kinds, segments and codes of the given tables.
LABELS = (("part", "p_name"), ("part", "p_type"), ("customer", "c_mktsegment"), ("events", "event_type"), ("documents", "source"), ("documents", "lang"))
_LABELS_SQL = "l AS (SELECT DISTINCT regexp_replace(name, '^[a-z]+_', '') AS label FROM (" + " UNION ALL ".join(f"SELECT {c} AS name FROM {t}" for t, c in LABELS) + ") WHERE name IS NOT NULL)"
_W = 8
_COMP = "((('0x' || substr(md5(concat(word, '|', i::VARCHAR)), 1, 8))::BIGINT % 2001) - 1000) / 1000.0"


def labels(spark, sf_dir) -> DataFrame:
    """The distinct labels of :data:`LABELS`; each column is made distinct before they meet."""
    parts = [load_table(spark, sf_dir, t, [c]).select(F.col(c).alias("name")).filter("name IS NOT NULL").distinct() for t, c in LABELS]
    return reduce(DataFrame.unionByName, parts).select(plain_label(F.col("name")).alias("label")).distinct()


def digest_vectors(words: DataFrame, width: int = _W) -> DataFrame:
    """A vector per word from digests of the word and the place: any engine can make it."""
    part = lambda i: ((F.conv(F.substring(F.md5(F.concat(F.col("word"), F.lit(f"|{i}")).cast("binary")), 1, 8), 16, 10).cast("long") % 2001) - 1000) / 1000.0
    return words.select("word", F.array(*[part(i) for i in range(width)]).alias("vec"))


@query(
    "q29_label_cosine",
    f"WITH {_LABELS_SQL}, w AS (SELECT label, unnest(list_filter(string_split_regex(lower(label), '[^a-z]+'), lambda x: length(x) > 0)) AS word FROM l), v AS (SELECT label, i, avg({_COMP}) AS x FROM w, range(0, {_W}) t(i) GROUP BY ALL) SELECT a.label AS label_a, b.label AS label_b, round(sum(a.x * b.x) / sqrt(sum(a.x * a.x) * sum(b.x * b.x)), 4) AS cosine FROM v a JOIN v b ON a.i = b.i AND a.label < b.label GROUP BY ALL HAVING sum(a.x * b.x) / sqrt(sum(a.x * a.x) * sum(b.x * b.x)) > 0.5",
)
def label_cosine(spark, sf_dir):
    from ..functions.text import tokenize_label

    l = labels(spark, sf_dir)
    words = l.select(F.explode(tokenize_label(F.col("label"))).alias("word")).distinct()
    v = G.label_vectors(l, digest_vectors(words), _W)
    side = lambda k: v.select(F.col("label").alias(f"label_{k}"), F.col("vec").alias(f"v_{k}"))
    p = side("a").join(side("b"), F.col("label_a") < F.col("label_b")).withColumn("cosine", G.cosine(F.col("v_a"), F.col("v_b")))
    return p.filter("cosine > 0.5").select("label_a", "label_b", F.round("cosine", 4).alias("cosine"))


@query("q30_jaro_winkler", f"WITH {_LABELS_SQL} SELECT a.label AS label_a, b.label AS label_b, round(jaro_winkler_similarity(a.label, b.label), 4) AS similarity FROM l a JOIN l b ON a.label < b.label WHERE jaro_winkler_similarity(a.label, b.label) > 0.6")
def label_jaro(spark, sf_dir):
    l = labels(spark, sf_dir)
    p = l.withColumnRenamed("label", "label_a").join(l.withColumnRenamed("label", "label_b"), F.col("label_a") < F.col("label_b"))
    return p.withColumn("similarity", jaro_winkler("label_a", "label_b")).filter("similarity > 0.6").select("label_a", "label_b", F.round("similarity", 4).alias("similarity"))


@query("q31_drop_vague", f"WITH {_LABELS_SQL} SELECT label FROM l WHERE length(label) >= 3 AND lower(label) NOT IN ({', '.join(repr(x) for x in VAGUE_LABELS)})")
def vague(spark, sf_dir):
    return G.drop_vague(labels(spark, sf_dir))


_TRUTH = "truth AS (SELECT dataset_id, table_id, variable, count(*) AS n_values FROM cv GROUP BY ALL)"


@query("q32_roles", f"WITH {CV}, {_TRUTH}, r AS (SELECT *, {role_sql()} AS role FROM truth), m AS (SELECT a.role, count(*) AS matches FROM r a JOIN r b ON a.variable = b.variable AND a.dataset_id < b.dataset_id GROUP BY a.role) SELECT 'numeric' AS kind, r.role, count(DISTINCT table_id) AS tables, count(*) AS datasets, round(avg(n_values), 4) AS mean_n, round(coalesce(stddev_samp(n_values), 0), 4) AS sd_n, any_value(coalesce(m.matches, 0)) AS matches FROM r LEFT JOIN m ON m.role = r.role GROUP BY r.role")
def roles(spark, sf_dir):
    t = truth_of(repository_values(spark, sf_dir))
    catalog = t.join(G.assign_roles(t), "table_id").withColumn("kind", F.lit("numeric"))
    same = t.select(F.col("dataset_id").alias("dataset_a"), "variable").join(t.select(F.col("dataset_id").alias("dataset_b"), "variable"), "variable").filter("dataset_a < dataset_b")
    s = G.repository_summary(catalog, same)
    return s.select("kind", "role", "tables", "datasets", F.round("mean_n", 4).alias("mean_n"), F.round("sd_n", 4).alias("sd_n"), "matches")


_BITS = lambda seed, *k: f"('0x' || substr(md5(concat_ws('|', '{seed}', {', '.join(f'({x})::VARCHAR' for x in k)})), 1, 8))::BIGINT"


@query(
    "q33_triplets",
    f"WITH {CV}, {_TRUTH}, mt AS (SELECT a.dataset_id AS anchor, b.dataset_id AS positive FROM truth a JOIN truth b ON a.variable = b.variable AND a.dataset_id <> b.dataset_id), cat AS (SELECT dataset_id, row_number() OVER (ORDER BY {_BITS(9, 'dataset_id')}, dataset_id) AS i, count(*) OVER () AS n FROM (SELECT DISTINCT dataset_id FROM truth)), d AS (SELECT anchor, positive, t AS try, (i + {_BITS(10, 'anchor', 'positive', 't')} % (n - 1)) % n + 1 AS i FROM mt JOIN cat ON dataset_id = anchor, range(0, 8) r(t)), c AS (SELECT anchor, positive, try, dataset_id AS negative FROM d JOIN cat USING (i) WHERE dataset_id <> anchor AND NOT EXISTS (SELECT 1 FROM mt WHERE mt.anchor = d.anchor AND mt.positive = dataset_id)) SELECT anchor, positive, arg_min(negative, try) AS negative FROM c GROUP BY ALL",
)
def triplets(spark, sf_dir):
    t = truth_of(repository_values(spark, sf_dir))
    same = t.select(F.col("dataset_id").alias("dataset_a"), "variable").join(t.select(F.col("dataset_id").alias("dataset_b"), "variable"), "variable").filter("dataset_a < dataset_b").select("dataset_a", "dataset_b")
    return G.sample_triplets(t, same)


# ------------------------------------------------------------------ measures

_STATS = "st AS (SELECT dataset_id, any_value(table_id) AS table_id, any_value(variable) AS variable, avg(value_num) AS m, coalesce(stddev_samp(value_num), 0) AS sd FROM cv GROUP BY dataset_id)"
_AUC = "SELECT method, round(sum(pos * (tot - cum + neg / 2)) / (sum(pos) * sum(neg)), 4) AS auc FROM (SELECT *, sum(neg) OVER (PARTITION BY method) AS tot, sum(neg) OVER (PARTITION BY method ORDER BY d) AS cum FROM (SELECT method, d, sum(y)::DOUBLE AS pos, sum(1 - y)::DOUBLE AS neg FROM sc GROUP BY ALL)) GROUP BY method"


@query(
    "q34_auc",
    f"WITH {CV}, {NET}, {_STATS}, tb AS (SELECT a.dataset_id AS id_a, b.dataset_id AS id_b, (a.variable = b.variable)::INTEGER AS y, abs(a.m - b.m) + abs(a.sd - b.sd) AS ms FROM st a JOIN st b ON a.dataset_id < b.dataset_id AND a.table_id <> b.table_id), sc AS (SELECT 'mean_sd' AS method, round(ms, 6) AS d, y FROM tb UNION ALL SELECT 'embedding', round(s.d, 6), y FROM tb JOIN scores s USING (id_a, id_b)) {_AUC}",
)
def auc(spark, sf_dir):
    """Pairs of datasets of different tables, scored by moments and by the formula network."""
    cv = repository_values(spark, sf_dir)
    tables = F.split("id_a", r"\.")[0] != F.split("id_b", r"\.")[0]
    pairs = all_pairs(cv).filter(tables)
    ms = B.mean_sd_distance(cv, pairs)
    emb = all_scores(formula_vectors(spark, sf_dir)).join(pairs, ["id_a", "id_b"]).select("id_a", "id_b", F.lit("embedding").alias("method"), "d")
    scored = ms.unionByName(emb)
    scored = scored.select("method", F.round("d", 6).alias("d"), same_variable(scored).alias("y"))
    return M.roc_auc(scored, ["method"]).select("method", F.round("auc", 4).alias("auc"))


_RANKED = f"{_STATS}, rl AS (SELECT DISTINCT table_id, {role_sql(0.4)} AS role FROM cv), q AS (SELECT st.*, role FROM st JOIN rl USING (table_id)), rk AS (SELECT a.dataset_id AS query_id, b.dataset_id, a.variable AS qv, b.variable AS rv, row_number() OVER (PARTITION BY a.dataset_id ORDER BY round(abs(a.m - b.m) + abs(a.sd - b.sd), 6), b.dataset_id) AS rank FROM q a JOIN q b ON a.role = 'T' AND b.role = 'R')"


@query(
    "q35_matches_at_k",
    f"WITH {CV}, {_RANKED}, pk AS (SELECT k, query_id, sum((qv = rv)::INTEGER) AS n FROM rk, (SELECT unnest([1, 5, 10]) AS k) WHERE rank <= k GROUP BY ALL) SELECT k::INTEGER AS k, round(avg(n), 4) AS matches, round(avg((n > 0)::INTEGER), 4) AS hit_rate, count(*) AS queries FROM pk GROUP BY k",
)
def matches(spark, sf_dir):
    """Datasets of held-out tables look for their variable among the others by mean and deviation."""
    cv = repository_values(spark, sf_dir)
    t = truth_of(cv).join(G.assign_roles(truth_of(cv), 0.4), "table_id")
    stats = C.dataset_stats(cv).join(t.select("dataset_id", "role"), "dataset_id")
    side = lambda r, k: stats.filter(F.col("role") == r).select(F.col("dataset_id").alias(k), F.col("mean").alias(f"m_{r}"), F.col("sd").alias(f"s_{r}"))
    scored = side("R", "dataset_id").crossJoin(F.broadcast(side("T", "query_id"))).select("query_id", "dataset_id", F.round(F.abs(F.col("m_T") - F.col("m_R")) + F.abs(F.col("s_T") - F.col("s_R")), 6).alias("d"))
    truth = t.filter("role = 'T'").select(F.col("dataset_id").alias("query_id"), "variable").join(t.filter("role = 'R'").select("dataset_id", "variable"), "variable")
    return M.matches_at_k(X.merge_top_k(scored, 10), truth).select("k", F.round("matches", 4).alias("matches"), F.round("hit_rate", 4).alias("hit_rate"), "queries")


@query(
    "q36_calibrated_recall",
    f"WITH {CV}, {NET}, vr AS (SELECT DISTINCT dataset_id, variable FROM cv), sc AS (SELECT a.variable AS va, b.variable AS vb, id_a, round(exp(-d), 6) AS p FROM scores JOIN vr a ON a.dataset_id = id_a JOIN vr b ON b.dataset_id = id_b), best AS (SELECT id_a, max(p) AS p FROM sc WHERE va <> vb GROUP BY id_a), mt AS (SELECT p FROM sc WHERE va = vb) SELECT round(avg(share), 4) AS recall, count(*) AS queries FROM (SELECT best.id_a, avg((mt.p > best.p)::INTEGER) AS share FROM best, mt GROUP BY best.id_a)",
)
def recall(spark, sf_dir):
    """Every dataset as a query without match (its own variable left out) sets a threshold."""
    s = all_scores(formula_vectors(spark, sf_dir))
    s = s.withColumns({"y": same_variable(s), "p": F.round(match_probability(F.col("d")), 6)})
    r = M.calibrated_recall(s.filter("y = 1"), s.filter("y = 0").select(F.col("id_a").alias("query_id"), "p"))
    return r.select(F.round("recall", 4).alias("recall"), "queries")


@query("q37_recalibrate", f"WITH {CV}, {NET}, vr AS (SELECT DISTINCT dataset_id, variable FROM cv), s AS (SELECT id_a, id_b, exp(-d) AS p, avg((a.variable = b.variable)::INTEGER) OVER () AS rate FROM scores JOIN vr a ON a.dataset_id = id_a JOIN vr b ON b.dataset_id = id_b) SELECT id_a, id_b, round(p / (1 - p) * rate / (1 - rate) / (1 + p / (1 - p) * rate / (1 - rate)), 4) AS p_prior, round(least(1.0, p / 0.8), 4) AS p_pu FROM s")
def recalibrated(spark, sf_dir):
    s = all_scores(formula_vectors(spark, sf_dir))
    s = s.withColumns({"p": match_probability(F.col("d")), "y": same_variable(s)})
    rate = s.agg(F.avg("y").alias("rate"))
    return s.crossJoin(F.broadcast(rate)).select("id_a", "id_b", F.round(recalibrate_prior(F.col("p"), F.col("rate")), 4).alias("p_prior"), F.round(recalibrate_pu(F.col("p"), 0.8), 4).alias("p_pu"))


@query(
    "q38_bound",
    "WITH e AS (SELECT label, count(*) AS n, round(max(list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x))), 6) AS b FROM embeddings GROUP BY label), x AS (SELECT label, n, eps, b FROM e, (SELECT unnest([0.1, 0.2, 0.5]) AS eps)) SELECT label, n::BIGINT AS n, eps::DOUBLE AS eps, b::DOUBLE AS b, round(4 * exp(-n * eps::DOUBLE * eps / (32 * b::DOUBLE * b)), 6) AS bound, ceil(32 * b::DOUBLE * b / (eps::DOUBLE * eps) * ln(4 / 0.05))::BIGINT AS needed FROM x",
)
def bounds(spark, sf_dir):
    """The bound for each label's bag of vectors: its size, its largest squared norm, and the values it would need."""
    e = load_table(spark, sf_dir, "embeddings", ["label", "embedding"]).withColumn("v", F.col("embedding").cast("array<double>"))
    bags = e.groupBy("label").agg(F.count("*").alias("n"), F.round(F.max(F.aggregate("v", F.lit(0.0), lambda t, x: t + x * x)), 6).alias("b"))
    grid = bags.select("label", "n", F.explode(F.array(*[F.lit(e) for e in (0.1, 0.2, 0.5)])).alias("eps"), "b")
    needed = F.ceil(32 * F.col("b") * F.col("b") / (F.col("eps") * F.col("eps")) * F.log(F.lit(4 / 0.05)))
    return grid.select("label", "n", "eps", "b", F.round(deviation_bound(F.col("n"), F.col("eps"), F.col("b")), 6).alias("bound"), needed.cast("long").alias("needed"))


@query("q39_top_adjustment", f"WITH {CV}, {NET}, tp AS (SELECT dataset_id, g FROM g ORDER BY g DESC, dataset_id LIMIT 10), b AS (SELECT dataset_id, v, w, sum(w) OVER (PARTITION BY dataset_id) AS n, row_number() OVER (PARTITION BY dataset_id ORDER BY w DESC, v) AS r FROM hist) SELECT dataset_id, round(g, 4) AS g, v AS top_value, round(w / n, 4) AS top_share FROM tp JOIN b USING (dataset_id) WHERE r = 1")
def adjusted(spark, sf_dir):
    h = C.value_histogram(repository_values(spark, sf_dir))
    t = M.top_adjustment(formula_vectors(spark, sf_dir), h, 10)
    return t.select("dataset_id", F.round("g", 4).alias("g"), "top_value", F.round("top_share", 4).alias("top_share"))


@query("q46_label_combo", f"WITH {CV}, {NET}, lb AS (SELECT id_a, id_b, exp(-d) AS p, jaro_winkler_similarity(string_split(id_a, '.')[-1], string_split(id_b, '.')[-1]) AS s FROM scores), o AS (SELECT *, least(greatest(p, 1e-6), 1 - 1e-6) AS pv, least(greatest(s, 1e-6), 1 - 1e-6) AS pl FROM lb) SELECT id_a, id_b, round(1 / (1 + exp(-(0.5 * ln(pv / (1 - pv)) + 0.5 * ln(pl / (1 - pl))))), 4) AS p FROM o")
def label_combo(spark, sf_dir):
    s = all_scores(formula_vectors(spark, sf_dir))
    last = lambda c: F.element_at(F.split(F.col(c), r"\."), -1)
    named = s.withColumns({"la": last("id_a"), "lb": last("id_b")})
    return named.select("id_a", "id_b", F.round(combine_scores(match_probability(F.col("d")), jaro_winkler("la", "lb")), 4).alias("p"))
