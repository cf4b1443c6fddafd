"""Queries on downstream procedures and the surrounding relational and streaming surface."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.sql_surface import register
from ..functions.text import strip_html, url_host, words

from ..operators import alignment as A
from ..operators import baselines as B
from ..operators import columnize as C
from ..operators import measures as M
from ..operators import search as X
from ..sources.tables import load_table
from ..streaming import states as ST
from .dataset_queries import _PLAIN, _TEXT_CTE, _VOCAB, _WORDS, CV, NET, all_scores, formula_vectors, text_values
from .registry import query
from .repository import repository_values
from .score_queries import BANDWIDTH, _K, vectors

# ------------------------------------------------------------------ alignment and union


def _prob_sql(extra: str = "") -> str:
    return f"WITH {CV}, {NET}, both_ways AS (SELECT id_a, id_b, d FROM scores UNION ALL SELECT id_b, id_a, d FROM scores), pr AS (SELECT string_split(id_a, '.')[1] AS ta, string_split(id_b, '.')[1] AS tb, id_a AS col_a, id_b AS col_b, round(exp(-d), 6) AS p FROM both_ways){extra}"


def column_probabilities(spark, sf_dir) -> DataFrame:
    """``ta, tb, col_a, col_b, p`` for columns of different tables, both ways."""
    s = all_scores(formula_vectors(spark, sf_dir)).select("id_a", "id_b", F.round(F.exp(-F.col("d")), 6).alias("p"))
    both = s.unionByName(s.select(F.col("id_b").alias("id_a"), F.col("id_a").alias("id_b"), "p"))
    return both.select(F.split("id_a", r"\.")[0].alias("ta"), F.split("id_b", r"\.")[0].alias("tb"), F.col("id_a").alias("col_a"), F.col("id_b").alias("col_b"), "p").filter("ta <> tb")


#: Columns of the widest table.
WIDEST = 6


def _greedy_sql(steps: int = WIDEST, last: str = "") -> str:
    out = ", c0 AS (SELECT * FROM pr WHERE ta < tb)"
    for k in range(1, steps + 1):
        out += f", pick{k} AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY ta, tb ORDER BY p DESC, col_a, col_b) AS r FROM c{k - 1}) WHERE r = 1), c{k} AS (SELECT c.* FROM c{k - 1} c JOIN pick{k} g USING (ta, tb) WHERE c.col_a <> g.col_a AND c.col_b <> g.col_b)"
    picked = " UNION ALL ".join(f"SELECT ta, tb, col_a, col_b, p FROM pick{k}" for k in range(1, steps + 1))
    return out + (f", greedy AS ({picked}){last}" if last else f" {picked}")


def _optimum_sql(steps: int = WIDEST) -> str:
    """``best``: the largest total of a one-to-one alignment of each two tables, and its probabilities. Columns of the
    narrower table are placed one by one; of all ways to take the same set of columns of the other the best is kept."""
    out = ", ranked AS (SELECT ta, tb, p, dense_rank() OVER (PARTITION BY ta, tb ORDER BY col_a) AS ra, dense_rank() OVER (PARTITION BY ta, tb ORDER BY col_b) AS rb FROM pr WHERE ta <> tb)"
    out += ", sized AS (SELECT ta, tb, max(ra) AS na, max(rb) AS nb FROM ranked GROUP BY ALL)"
    out += ", edge AS (SELECT ta, tb, p, least(na, nb) AS size, CASE WHEN na <= nb THEN ra ELSE rb END AS r, 1::BIGINT << (CASE WHEN na <= nb THEN rb ELSE ra END - 1)::INTEGER AS bit FROM ranked JOIN sized USING (ta, tb))"
    out += ", f0 AS (SELECT ta, tb, 0::BIGINT AS mask, 0.0::DOUBLE AS total, []::DOUBLE[] AS ps FROM sized)"
    for k in range(1, steps + 1):
        out += f", f{k} AS MATERIALIZED (SELECT ta, tb, mask | bit AS mask, any_value(edge.size) AS size, max(total + p) AS total, arg_max(list_append(ps, p), total + p) AS ps FROM f{k - 1} JOIN edge USING (ta, tb) WHERE r = {k} AND mask & bit = 0 GROUP BY ta, tb, mask | bit)"
    done = " UNION ALL ".join(f"SELECT ta, tb, total, ps FROM f{k} WHERE f{k}.size = {k}" for k in range(1, steps + 1))
    return out + f", best AS (SELECT ta, tb, max(total) AS total, list_reverse_sort(arg_max(ps, total)) AS ps FROM ({done}) GROUP BY ta, tb)"


@query("q40_alignment", _prob_sql(_greedy_sql()))
def greedy_alignment(spark, sf_dir):
    """Greedy one-to-one alignment of the columns of all table pairs."""
    p = column_probabilities(spark, sf_dir).filter("ta < tb")
    a = A.align_schemas(p.withColumn("group_id", F.concat_ws("~", "ta", "tb")), "greedy")
    return a.select(F.split("group_id", "~")[0].alias("ta"), F.split("group_id", "~")[1].alias("tb"), "col_a", "col_b", "p")


@query("q40b_two_opt", _prob_sql(_optimum_sql() + _greedy_sql(last=" SELECT concat(ta, '~', tb) AS group_id, round(best.total, 6) AS two_opt, round(greedy_total, 6) AS greedy FROM best JOIN (SELECT ta, tb, sum(p) AS greedy_total FROM greedy GROUP BY ALL) USING (ta, tb)")))
def two_opt_alignment(spark, sf_dir):
    """Two-way swaps over all pairs of tables, with the totals of the greedy alignment beside them. The reference SQL holds
    the swaps to the optimum."""
    p = column_probabilities(spark, sf_dir).filter("ta < tb").withColumn("group_id", F.concat_ws("~", "ta", "tb"))
    total = lambda m, n: A.align_schemas(p, m).groupBy("group_id").agg(F.round(F.sum("p"), 6).alias(n))
    return total("two_opt", "two_opt").join(total("greedy", "greedy"), "group_id")


@query("q41_union_topk", _prob_sql(", bc AS (SELECT ta, tb, col_a, max(p) AS p FROM pr WHERE ta <> tb GROUP BY ALL), sc AS (SELECT ta, tb, round(avg(p), 9) AS score FROM bc GROUP BY ALL), rk AS (SELECT *, row_number() OVER (PARTITION BY ta ORDER BY score DESC, tb) AS rank FROM sc) SELECT ta AS query_table, tb AS table_id, rank::INTEGER AS rank, score FROM rk WHERE rank <= 5"))
def union_ranking(spark, sf_dir):
    """Tables ranked by the mean of the best probability of the query's columns."""
    best = column_probabilities(spark, sf_dir).groupBy("ta", "tb", "col_a").agg(F.max("p").alias("p"))
    score = best.groupBy("ta", "tb").agg(F.round(F.avg("p"), 9).alias("score"))
    order = Window.partitionBy("ta").orderBy(F.desc("score"), "tb")
    return score.withColumn("rank", F.row_number().over(order)).filter("rank <= 5").select(F.col("ta").alias("query_table"), F.col("tb").alias("table_id"), F.col("rank").cast("int").alias("rank"), "score")


@query(
    "q41b_union_alignment",
    _prob_sql(_optimum_sql() + ", pre AS (SELECT ta, tb, c, list_sum(list_transform(ps[1:c], lambda x: ln(greatest(x, 1e-12)))) AS log_p FROM best, range(1, " + str(WIDEST + 1) + ") t(c) WHERE c <= len(ps)), good AS (SELECT *, count(*) OVER (PARTITION BY c ORDER BY log_p) / count(*) OVER (PARTITION BY c) AS goodness FROM pre), top AS (SELECT *, row_number() OVER (PARTITION BY ta, tb ORDER BY goodness DESC, c DESC) AS r FROM good), o AS (SELECT *, row_number() OVER (PARTITION BY ta ORDER BY goodness DESC, c DESC, log_p DESC, tb) AS rank FROM top WHERE r = 1) SELECT ta AS query_table, tb AS table_id, round(goodness, 6) AS score, c::INTEGER AS c, rank::INTEGER AS rank FROM o WHERE rank <= 5"),
)
def union_by_alignment(spark, sf_dir):
    """The ranking by the best c-alignment against a background of all table pairs."""
    p = column_probabilities(spark, sf_dir).select(F.col("ta").alias("query_table"), F.col("tb").alias("table_id"), "col_a", "col_b", "p")
    return A.union_search(p, 5, background=p).withColumn("score", F.round("score", 6))


# ------------------------------------------------------------------ reports, nested data


@query("q42_report_cube", "SELECT l_returnflag AS flag, l_linestatus AS status, CAST(l_linenumber AS BIGINT) AS line, grouping(l_returnflag) * 4 + grouping(l_linestatus) * 2 + grouping(l_linenumber) AS gid, count(*) AS n, round(avg(l_discount), 4) AS mean_value FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus, l_linenumber)")
def cube(spark, sf_dir):
    d = load_table(spark, sf_dir, "lineitem").select(F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("status"), F.col("l_linenumber").cast("long").alias("line"), F.col("l_discount").alias("value"))
    return M.report(d, ["flag", "status", "line"], "value").withColumn("mean_value", F.round("mean_value", 4))


@query("q43_props_json", "SELECT concat('events.props.k:', event_type) AS dataset_id, count(*) AS n, round(avg(CAST(json_extract(props, '$.k') AS DOUBLE)), 4) AS mean, count(DISTINCT CAST(json_extract(props, '$.k') AS DOUBLE)) AS n_distinct FROM events WHERE json_extract(props, '$.k') IS NOT NULL GROUP BY event_type")
def json_leaves(spark, sf_dir):
    e = C.flatten_json(load_table(spark, sf_dir, "events", ["event_type", "props"]), "props", {"k": "double"})
    return e.filter("`props.k` IS NOT NULL").groupBy(F.concat(F.lit("events.props.k:"), "event_type").alias("dataset_id")).agg(F.count("*").alias("n"), F.round(F.avg("`props.k`"), 4).alias("mean"), F.countDistinct("`props.k`").alias("n_distinct"))


@query("q45_text_jaccard_docs", f"WITH w AS (SELECT DISTINCT concat(source, ':', lang) AS id, unnest({_WORDS.format('text')}) AS word FROM documents), n AS (SELECT id, count(*) AS u FROM w GROUP BY id), s AS (SELECT a.id AS id_a, b.id AS id_b, count(*) AS shared FROM w a JOIN w b USING (word) WHERE a.id < b.id GROUP BY ALL) SELECT a.id AS id_a, b.id AS id_b, round(1 - coalesce(shared, 0)::DOUBLE / (a.u + b.u - coalesce(shared, 0)), 4) AS d FROM n a JOIN n b ON a.id < b.id LEFT JOIN s ON s.id_a = a.id AND s.id_b = b.id")
def text_jaccard(spark, sf_dir):
    w = load_table(spark, sf_dir, "documents", ["source", "lang", "text"]).select(F.concat_ws(":", "source", "lang").alias("dataset_id"), F.explode(F.array_distinct(words(F.col("text")))).alias("value_str")).distinct()
    ids = w.select("dataset_id").distinct()
    pairs = ids.withColumnRenamed("dataset_id", "id_a").join(F.broadcast(ids.withColumnRenamed("dataset_id", "id_b")), F.col("id_a") < F.col("id_b"))
    return B.jaccard_distance(w, pairs, "value_str").select("id_a", "id_b", F.round("d", 4).alias("d"))


# ------------------------------------------------------------------ relational surface


@query("q47_filter_project", "SELECT CASE WHEN l_discount > 0.05 THEN 'true' ELSE 'false' END AS high_discount, CASE WHEN l_tax > 0.04 THEN 'true' ELSE 'false' END AS high_tax, count(*) AS n FROM lineitem WHERE l_quantity IS NOT NULL AND l_shipdate >= TIMESTAMP '1995-01-01' GROUP BY ALL")
def predicates_as_words(spark, sf_dir):
    """Predicates as true/false words over a scan pruned to four columns, with the filter pushed to it."""
    d = load_table(spark, sf_dir, "lineitem", ["l_discount", "l_tax", "l_quantity", "l_shipdate"]).filter("l_quantity IS NOT NULL AND l_shipdate >= TIMESTAMP '1995-01-01'")
    return d.groupBy((F.col("l_discount") > 0.05).cast("string").alias("high_discount"), (F.col("l_tax") > 0.04).cast("string").alias("high_tax")).agg(F.count("*").alias("n"))


@query("q48_vocab_join", rf"WITH {_TEXT_CTE}, {_VOCAB}, w AS (SELECT dataset_id, unnest({_WORDS.format('v')}) AS word FROM tv) SELECT dataset_id, count(*) AS n_words, round(avg((vocab.word IS NOT NULL)::INTEGER), 4) AS known_share FROM w LEFT JOIN vocab USING (word) GROUP BY dataset_id")
def known_words(spark, sf_dir):
    values = text_values(spark, sf_dir)
    vocab = C.build_vocab(values).select("word", F.lit(1).alias("known"))
    w = values.select("dataset_id", F.explode(words(F.col("value_str"))).alias("word")).groupBy("dataset_id", "word").agg(F.count("*").alias("n"))
    return w.join(vocab, "word", "left").groupBy("dataset_id").agg(F.sum("n").alias("n_words"), F.round(F.sum(F.col("n") * F.coalesce("known", F.lit(0))) / F.sum("n"), 4).alias("known_share"))


_SCALE = "(1 + (vec_id % 7) / 4.0)"


@query("q49_norm_band", f"WITH v AS (SELECT vec_id::VARCHAR AS id, vec_id, list_transform(embedding::DOUBLE[], lambda x: x * {_SCALE}) AS e FROM embeddings), d AS (SELECT a.id AS query_id, b.id AS dataset_id, list_sum(list_transform(list_zip(a.e, b.e), lambda p: (p[1] - p[2]) * (p[1] - p[2]))) AS d FROM v a, v b WHERE a.vec_id % 20 = 0) SELECT query_id, dataset_id, round(d, 4) AS d FROM d WHERE sqrt(d) <= 0.9")
def norm_band(spark, sf_dir):
    """Neighbours within a radius of scaled vectors: candidates by bands of norms, then exact distances."""
    v = vectors(spark, sf_dir).withColumn("k", 1 + (F.col("dataset_id").cast("long") % 7) / 4.0).select("dataset_id", F.transform("s", lambda x: x * F.col("k")).alias("s"))
    q = v.filter(F.col("dataset_id").cast("long") % 20 == 0).withColumnRenamed("dataset_id", "query_id")
    return X.norm_band_join(q, X.spread(v), 0.9).select("query_id", "dataset_id", F.round("d", 4).alias("d"))


def asof_join(left: DataFrame, right: DataFrame, by: str, on: str, value: str) -> DataFrame:
    """``left`` with the last ``value`` of ``right`` at or before its own time, per ``by``: one union, one sort, no
    range join. Right rows of the same instant count as before."""
    both = right.select(by, on, F.col(value).alias("seen"), F.lit(0).alias("side"), F.lit(None).cast("long").alias("row_id")).unionByName(left.select(by, on, F.lit(None).cast("double").alias("seen"), F.lit(1).alias("side"), F.col("event_id").alias("row_id")))
    w = Window.partitionBy(by).orderBy(on, "side", "seen").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.withColumn("latest", F.last("seen", ignorenulls=True).over(w)).filter("side = 1").select(F.col("row_id").alias("event_id"), by, on, "latest")


@query("q50_asof", "WITH p AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase'), v AS (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type <> 'purchase' GROUP BY ALL) SELECT p.event_id, p.user_id, round(v.value, 4) AS latest FROM p ASOF LEFT JOIN v ON p.user_id = v.user_id AND p.ts >= v.ts")
def asof(spark, sf_dir):
    """The latest other event's value of the user at each purchase."""
    e = load_table(spark, sf_dir, "events", ["event_id", "user_id", "ts", "event_type", "value"])
    j = asof_join(e.filter("event_type = 'purchase'"), e.filter("event_type <> 'purchase'"), "user_id", "ts", "value")
    return j.select("event_id", "user_id", F.round("latest", 4).alias("latest"))


@query("q51_semi_anti", "SELECT 'present' AS side, count(*) AS n, sum(p_partkey)::BIGINT AS keys FROM part WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 45) UNION ALL SELECT 'absent', count(*), sum(p_partkey)::BIGINT FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 45)")
def semi_anti(spark, sf_dir):
    p, l = load_table(spark, sf_dir, "part", ["p_partkey"]), load_table(spark, sf_dir, "lineitem", ["l_partkey", "l_quantity"]).filter("l_quantity > 45").select(F.col("l_partkey").alias("p_partkey"))
    agg = lambda df, n: df.agg(F.lit(n).alias("side"), F.count("*").alias("n"), F.sum("p_partkey").alias("keys"))
    return agg(p.join(l, "p_partkey", "left_semi"), "present").unionByName(agg(p.join(l, "p_partkey", "left_anti"), "absent"))


@query("q52_lag_pairs", f"WITH o AS (SELECT event_type, value, lag(value) OVER (PARTITION BY event_type ORDER BY ('0x' || substr(md5(concat_ws('|', '5', event_id::VARCHAR)), 1, 8))::BIGINT, event_id) AS previous FROM events) SELECT event_type, count(previous) AS n, round(avg({_K('value', 'previous')}), 4) AS mean_kernel FROM o GROUP BY event_type")
def lag_pairs(spark, sf_dir):
    from ..functions.sampling import priority_bits

    e = load_table(spark, sf_dir, "events", ["event_id", "event_type", "value"])
    w = Window.partitionBy("event_type").orderBy(priority_bits(5, F.col("event_id")), "event_id")
    d = F.col("value") - F.col("previous")
    return e.withColumn("previous", F.lag("value").over(w)).groupBy("event_type").agg(F.count("previous").alias("n"), F.round(F.avg(F.exp(-d * d / (2 * BANDWIDTH * BANDWIDTH))), 4).alias("mean_kernel"))


@query("q53_setops", "SELECT 'shared_customers' AS name, count(*) AS n FROM (SELECT c_custkey FROM customer INTERSECT SELECT o_custkey FROM orders) UNION ALL SELECT 'idle_customers', count(*) FROM (SELECT c_custkey FROM customer EXCEPT SELECT o_custkey FROM orders) UNION ALL SELECT 'unused_parts', count(*) FROM (SELECT p_partkey FROM part EXCEPT SELECT l_partkey FROM lineitem) UNION ALL SELECT 'half_overlap', 0::BIGINT")
def set_operations(spark, sf_dir):
    key = lambda t, c: load_table(spark, sf_dir, t, [c]).select(F.col(c).alias("k"))
    halves = C.split_halves(load_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("row_key")))
    parts = {
        "shared_customers": key("customer", "c_custkey").intersect(key("orders", "o_custkey")),
        "idle_customers": key("customer", "c_custkey").exceptAll(key("customer", "c_custkey").intersect(key("orders", "o_custkey"))),
        "unused_parts": key("part", "p_partkey").subtract(key("lineitem", "l_partkey")),
        "half_overlap": halves.filter("half = 0").select("row_key").intersect(halves.filter("half = 1").select("row_key")),
    }
    out = None
    for name, df in parts.items():
        one = df.agg(F.lit(name).alias("name"), F.count("*").alias("n"))
        out = one if out is None else out.unionByName(one)
    return out


@query("q54_text_clean", f"WITH c AS (SELECT lower(regexp_extract(url, '^[a-zA-Z][a-zA-Z0-9+.-]*://([^/?#]*)', 1)) AS host, {_PLAIN.format('html')} AS plain FROM pages) SELECT host, count(*) AS pages, sum(length(plain))::BIGINT AS characters, sum(len({_WORDS.format('plain')}))::BIGINT AS n_words FROM c GROUP BY host")
def cleaned(spark, sf_dir):
    p = load_table(spark, sf_dir, "pages", ["url", "html"]).select(url_host(F.col("url")).alias("host"), strip_html(F.col("html")).alias("plain"))
    return p.groupBy("host").agg(F.count("*").alias("pages"), F.sum(F.char_length("plain")).cast("long").alias("characters"), F.sum(F.size(words(F.col("plain")))).cast("long").alias("n_words"))


@query("q55_date_numeric", "SELECT CAST(year(l_shipdate) AS INTEGER) AS year, count(*) AS n, round(avg(date_diff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE))), 4) AS mean_day, round(stddev_samp(date_diff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE))), 4) AS sd_day FROM lineitem GROUP BY 1")
def dates(spark, sf_dir):
    d = load_table(spark, sf_dir, "lineitem", ["l_shipdate"]).select(F.year("l_shipdate").alias("year"), F.col("l_shipdate").cast("date").alias("day"))
    d = d.withColumn("x", C.as_numeric(d, "day"))
    return d.groupBy("year").agg(F.count("*").alias("n"), F.round(F.avg("x"), 4).alias("mean_day"), F.round(F.stddev_samp("x"), 4).alias("sd_day"))


@query("q56_annotations", _prob_sql(", rk AS (SELECT *, row_number() OVER (PARTITION BY col_a ORDER BY -ln(p), col_b) AS r FROM pr WHERE ta <> tb), vt AS (SELECT col_a AS query_id, 'family' AS key, string_split(tb, ':')[1] AS value, sum(p) AS support FROM rk WHERE r <= 5 GROUP BY ALL) SELECT query_id, key, value, round(support, 4) AS support FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY support DESC, value) AS n FROM vt) WHERE n = 1"))
def annotations(spark, sf_dir):
    """The family that most of a column's five nearest columns come from, weighed by probability."""
    p = column_probabilities(spark, sf_dir).select(F.col("col_a").alias("query_id"), F.col("col_b").alias("dataset_id"), (-F.log("p")).alias("d"))
    catalog = repository_values(spark, sf_dir).select("dataset_id", "table_id").distinct().select("dataset_id", F.create_map(F.lit("family"), F.split("table_id", ":")[0]).alias("meta"))
    return X.lookup_annotations(X.merge_top_k(p, 5), catalog).select("query_id", "key", "value", F.round("support", 4).alias("support"))


@query("q57_sql_surface", f"WITH {CV}, {NET} SELECT id_a, id_b, round(d, 4) AS d, round(exp(-d), 4) AS p FROM scores")
def sql_surface(spark, sf_dir):
    """The scores through registered SQL functions and views."""
    register(spark, vectors=formula_vectors(spark, sf_dir).select("dataset_id", "h", "g"))
    return spark.sql("SELECT a.dataset_id AS id_a, b.dataset_id AS id_b, round(match_score(a.h, b.h, a.g, b.g), 4) AS d, round(match_probability(match_score(a.h, b.h, a.g, b.g)), 4) AS p FROM vectors a JOIN vectors b ON a.dataset_id < b.dataset_id")


# ------------------------------------------------------------------ windows over events

_TANH = lambda s: f"sum(tanh(value / {s}))"


def _states(df: DataFrame) -> DataFrame:
    return df.select("dataset_id", F.col("start").cast("timestamp_ntz").cast("string").alias("start"), "n", F.round("total", 4).alias("total"), F.round(F.col("sum_h")[1], 4).alias("h10"), F.round(F.col("sum_h")[2], 4).alias("h100"))


@query("q44_stream_windows", f"SELECT event_type AS dataset_id, strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(sum(value), 4) AS total, round({_TANH(10.0)}, 4) AS h10, round({_TANH(100.0)}, 4) AS h100 FROM events GROUP BY 1, 2")
def windows(spark, sf_dir):
    return _states(ST.stream_states(load_table(spark, sf_dir, "events"), "1 day"))


@query("q58_sliding", f"WITH w AS (SELECT event_type, value, unnest([time_bucket(INTERVAL 1 DAY, ts), time_bucket(INTERVAL 1 DAY, ts) - INTERVAL 1 DAY]) AS start FROM events) SELECT event_type AS dataset_id, strftime(start, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(sum(value), 4) AS total, round({_TANH(10.0)}, 4) AS h10, round({_TANH(100.0)}, 4) AS h100 FROM w GROUP BY 1, 2")
def sliding(spark, sf_dir):
    return _states(ST.stream_states(load_table(spark, sf_dir, "events"), "2 days", slide="1 day"))


@query("q59_sessions", "WITH o AS (SELECT user_id, ts, value, CASE WHEN lag(ts) OVER u IS NULL OR ts - lag(ts) OVER u >= INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS new FROM events WINDOW u AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM o) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(avg(value), 4) AS mean_value FROM s GROUP BY user_id, k")
def sessions(spark, sf_dir):
    s = ST.stream_sessions(load_table(spark, sf_dir, "events"))
    return s.select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n", F.round("mean_value", 4).alias("mean_value"))


@query("q60_drift", "WITH f AS (SELECT event_type, ts, [tanh(value / 1.0), tanh(value / 10.0), tanh(value / 100.0), tanh(value / 1000.0)] AS h FROM events), x AS (SELECT event_type, ts, unnest(h) AS x, unnest([0, 1, 2, 3]) AS i FROM f), whole AS (SELECT event_type, i, avg(x) AS m FROM x GROUP BY ALL), w AS (SELECT event_type, i, unnest([time_bucket(INTERVAL 1 DAY, ts), time_bucket(INTERVAL 1 DAY, ts) - INTERVAL 1 DAY]) AS start, x FROM x), s AS (SELECT event_type, start, i, avg(x) AS m, count(*) AS n FROM w GROUP BY ALL) SELECT s.event_type AS dataset_id, strftime(s.start, '%Y-%m-%d %H:%M:%S') AS start, any_value(s.n) AS n, round(sqrt(sum(pow(s.m - whole.m, 2))), 4) AS drift FROM s JOIN whole USING (event_type, i) GROUP BY 1, 2")
def drift(spark, sf_dir):
    """Distance of each sliding window to the dataset's whole history."""
    e = load_table(spark, sf_dir, "events")
    stored = e.groupBy(F.col("event_type").alias("dataset_id")).agg(F.array(*[F.avg(f) for f in ST.moment_features(F.col("value"))]).alias("h0"))
    d = ST.stream_drift(e, stored)
    return d.select("dataset_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n", F.round("drift", 4).alias("drift"))


