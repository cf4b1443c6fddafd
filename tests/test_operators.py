import math
import random
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from varlink.nets.bilstm import CharBiLstm
from varlink.nets.mlp import SetNet
from varlink.operators import alignment as A
from varlink.operators import baselines as B
from varlink.operators import columnize as C
from varlink.operators import measures as M
from varlink.operators import search as X
from varlink.operators import statistics as S
from varlink.operators import truth as G
from varlink.operators.embed import NumericEncoder, StringEncoder, WordEncoder, embed_datasets, embed_values, query_vectors
from varlink.plans.repository import COARSE, repository_values
from varlink.sources import tables


def cv_of(spark, sets):
    return spark.createDataFrame([(k, str(i), float(v)) for k, vs in sets.items() for i, v in enumerate(vs)], "dataset_id string, row_key string, value_num double")


def pairs_of(spark, *ids):
    return spark.createDataFrame(list(ids), "id_a string, id_b string")


def d_of(df):
    return {(r["id_a"], r["id_b"]): r["d"] for r in df.collect()}


# ------------------------------------------------------------------ datasets


def test_columnize(spark):
    df = spark.sql("SELECT * FROM VALUES (1, 2.5D, 'a', true, date'1970-01-03', timestamp'1970-01-01 00:01:00', array(1), struct(7 AS z)), (NULL, double('NaN'), NULL, NULL, NULL, NULL, NULL, NULL) AS t(i, d, s, b, day, ts, xs, st)")
    flat = C.flatten_nested(df)
    got = {(r["dataset_id"], r["value_num"], r["value_str"]) for r in C.columnize(flat, "t").collect()}
    assert got == {("t.i", 1.0, None), ("t.d", 2.5, None), ("t.s", None, "a"), ("t.b", None, "true"), ("t.day", 2.0, None), ("t.ts", 60.0, None), ("t.st.z", 7.0, None)}
    assert C.columnize(df.limit(0), "t").count() == 0


def test_columnize_plan_is_one_pruned_scan(spark, sf_dir):
    plan = C.columnize_by_unpivot(tables.load_table(spark, sf_dir, "lineitem"), "lineitem", ["l_tax", "l_discount"]).groupBy("column").count()._jdf.queryExecution().executedPlan().toString()
    assert plan.count("FileScan") == 1 and "Expand" in plan and "l_comment" not in plan and "l_quantity" not in plan.split("ReadSchema")[1]


def test_filter_reaches_scan(spark, sf_dir):
    df = tables.load_table(spark, sf_dir, "lineitem", ["l_tax", "l_quantity"]).filter("l_quantity > 45")
    assert "GreaterThan(l_quantity,45" in df._jdf.queryExecution().executedPlan().toString()


def test_subsample(spark):
    cv = cv_of(spark, {"big": range(3000), "small": range(5)})
    a = C.subsample(cv, 100)
    assert {r["dataset_id"]: r["count"] for r in a.groupBy("dataset_id").count().collect()} == {"big": 100, "small": 5}
    b = C.subsample(cv.repartition(7), 100, slack=1000.0)  # without thinning: the same rows
    assert sorted(map(tuple, a.select("dataset_id", "row_key").collect())) == sorted(map(tuple, b.select("dataset_id", "row_key").collect()))


def test_split_augment(spark):
    cv = cv_of(spark, {"a": range(200)})
    parts = C.split_augment(cv, 3)
    per = parts.groupBy("pair_id", "row_key").count()
    assert per.count() == 600 and per.filter("count > 1").count() == 0
    shares = [r["s"] for r in parts.groupBy("pair_id").agg(F.avg("side").alias("s")).collect()]
    assert len(set(shares)) == 3 and all(0.02 < s < 0.98 for s in shares)


def test_kinds(spark):
    texts = [("t.words", w) for w in ["red apple", "green apple", "red pear", "green pear", "red", "green", "apple", "pear"] * 3] + [("t.codes", f"AB#{i}") for i in range(9)] + [("t.urls", "http://red.apple/green")]
    cv = spark.createDataFrame([(d, None, v) for d, v in texts] + [("t.n", 1.0, None)], "dataset_id string, value_num double, value_str string")
    got = {r["dataset_id"]: r["kind"] for r in C.infer_kind(cv, C.build_vocab(cv)).collect()}
    assert got == {"t.words": "language", "t.codes": "string", "t.urls": "string", "t.n": "numeric"}
    some = C.infer_kind(cv, C.build_vocab(cv), rule="any").filter("dataset_id = 't.words'").first()
    assert some["language_share"] == 1.0


# ------------------------------------------------------------------ pooling


def test_pooling_paths_agree(spark):
    cv = cv_of(spark, {"a": [1, 1, 2, 3], "b": [5, 1e6, -2.5]}).repartition(3)
    net = SetNet(32, 8, 5).init(2)
    plain = embed_values(cv, net).collect()
    want = {k: (np.mean([r["h"] for r in plain if r["dataset_id"] == k], axis=0), np.mean([r["g"] for r in plain if r["dataset_id"] == k])) for k in "ab"}
    for made in (embed_datasets(cv, net), embed_datasets(C.value_histogram(cv), net)):
        for r in made.collect():
            assert np.allclose(r["h"], want[r["dataset_id"]][0]) and r["g"] == pytest.approx(want[r["dataset_id"]][1])
            assert r["s"][-2] == pytest.approx(math.sqrt(r["g"])) and r["s"][-1] == 0
    wide = SetNet(32, 8, 20).init(2)  # the other merge
    assert embed_datasets(cv, wide).count() == 2


def test_text_and_string_pooling(spark):
    cv = spark.createDataFrame([("a", "red apple"), ("a", "pear"), ("b", "zz9"), ("b", "")], "dataset_id string, value_str string")
    rows = {r["dataset_id"]: r for r in embed_datasets(cv, SetNet(16, 6, 4).init(1), WordEncoder(None, 16), "language").collect()}
    assert rows["a"]["kind"] == "language" and len(rows["a"]["h"]) == 4
    net = CharBiLstm(units=3, n_out=4, char_dim=3).init(1)
    got = {r["dataset_id"]: r["h"] for r in embed_datasets(cv, net, StringEncoder(), "string").collect()}
    from varlink.nets.bilstm import encode_bytes

    assert np.allclose(got["b"], net.forward(*encode_bytes(["zz9", ""]))[0].mean(axis=0))
    assert (WordEncoder(None, 8).one("42 !") == 0).all() and (WordEncoder({"red": np.ones(3)}).one("red car") == 1).all()
    assert embed_datasets(cv.limit(0), net, StringEncoder()).count() == 0


def test_unbiased_distance(spark):
    """The biased distance of samples of one distribution exceeds the unbiased one, which is near 0."""
    from varlink.functions.scores import embedding_distance

    rng = np.random.default_rng(0)
    cv = cv_of(spark, {f"{s}{i}": rng.normal(size=8) for s in "ab" for i in range(40)})
    v = embed_datasets(cv, SetNet(1, 4, 3).init(1), NumericEncoder("raw")).cache()
    a = v.filter("dataset_id LIKE 'a%'").select(F.substring("dataset_id", 2, 9).alias("i"), F.col("h").alias("ha"), F.col("spread").alias("sa"))
    b = v.filter("dataset_id LIKE 'b%'").select(F.substring("dataset_id", 2, 9).alias("i"), F.col("h").alias("hb"), F.col("spread").alias("sb"))
    m = a.join(b, "i").agg(F.avg(embedding_distance(F.col("ha"), F.col("hb"))).alias("v"), F.avg(embedding_distance(F.col("ha"), F.col("hb"), "u", F.col("sa"), F.col("sb"))).alias("u")).first()
    assert m["v"] > 3 * abs(m["u"])


# ------------------------------------------------------------------ baselines


def test_simple_baselines(spark):
    cv = cv_of(spark, {"a": [0, 2], "b": [1, 3], "c": [1, 2], "d": [3, 4]})
    ms = d_of(B.mean_sd_distance(cv, pairs_of(spark, ("a", "b"))))
    assert ms["a", "b"] == pytest.approx(1.0)
    h = C.value_histogram(cv)
    gap = {(r["id_a"], r["id_b"]): r["gap"] for r in B.ks_gap(h, pairs_of(spark, ("c", "d"), ("c", "c"))).collect()}
    assert gap == {("c", "d"): 1.0, ("c", "c"): 0.0}
    s = spark.createDataFrame([("x", v) for v in "abc"] + [("y", v) for v in "bcd"], "dataset_id string, value_str string")
    assert d_of(B.jaccard_distance(C.value_histogram(s, value="value_str"), pairs_of(spark, ("x", "y")), "value_str"))["x", "y"] == 0.5
    est = d_of(B.jaccard_minhash(cv_of(spark, {"p": range(300), "q": range(100, 400)}), pairs_of(spark, ("p", "q"))))["p", "q"]
    assert abs(est - 0.5) < 0.15


def test_two_sample_forms_agree(spark):
    rng = np.random.default_rng(4)
    sets = {"a": rng.normal(size=60), "b": rng.normal(0.7, 1.5, size=80), "c": rng.normal(size=60)}
    cv, pairs = cv_of(spark, sets), pairs_of(spark, ("a", "b"), ("a", "c"))
    packed = B.pack(cv)
    for x, y in (("a", "b"), ("a", "c")):
        quad = S.mmd_quadratic(sets[x], sets[y], 1.0)
        assert d_of(B.mmd_quadratic(packed, pairs, 1.0))[x, y] == pytest.approx(quad)
        assert d_of(B.mmd_quadratic_sql(C.value_histogram(cv), pairs, 1.0))[x, y] == pytest.approx(quad)
        assert d_of(B.ks_packed(packed, pairs))[x, y] == pytest.approx(d_of(B.ks_distance(C.value_histogram(cv), pairs))[x, y], abs=1e-9)
        assert d_of(B.mmd_linear_sql(cv, pairs, 1.0, seed=5))[x, y] == pytest.approx(d_of(B.mmd_linear(packed, pairs, 1.0))[x, y])
        assert d_of(B.mean_sd_packed(packed, pairs))[x, y] == pytest.approx(d_of(B.two_sample("mean_sd", cv, pairs))[x, y])
    for m in ("ks", "mmd_quadratic", "smooth_cf"):
        d = d_of(B.two_sample(m, cv, pairs))
        assert d["a", "b"] > d["a", "c"]


def test_statistics():
    assert S.chi2_survival_even(3.84, 2) == pytest.approx(math.exp(-1.92)) and S.chi2_survival(3.84, 1) == pytest.approx(0.05, abs=1e-3)
    assert S.chi2_survival(7.0, 6) == pytest.approx(S.chi2_survival_even(7.0, 6))
    assert S.f_survival(4.0, 2, 20) == pytest.approx((1 + 2 * 4.0 / 20) ** -10)  # closed form for two degrees
    assert S.ks_survival(0.0, 9, 9) == 1 and S.ks_survival(1.0, 50, 50) < 1e-9
    rng = np.random.default_rng(2)
    x, y = rng.normal(size=(40, 3)), rng.normal(size=(50, 3))
    t2, p = S.hotelling(x, y, ridge=0.0)
    cov = (np.cov(x.T) * 39 + np.cov(y.T) * 49) / 88
    diff = x.mean(axis=0) - y.mean(axis=0)
    assert t2 == pytest.approx(40 * 50 / 90 * diff @ np.linalg.inv(cov) @ diff) and 0.001 < p < 1
    assert S.hotelling(x, y + 2)[1] < 1e-6 and 0 <= S.hotelling(x[:2], y[:1])[1] <= 1
    ps = [S.hotelling(rng.normal(size=(20, 2)), rng.normal(size=(20, 2)))[1] for _ in range(200)]
    assert 0.4 < np.mean(ps) < 0.6  # uniform under the null
    c = np.full(10, 3.0)
    assert S.smooth_cf(c, c, B.test_frequencies()) == pytest.approx(0) and S.mmd_linear(c, c, S.median_bandwidth(c, c)) == 0


def test_vector_baselines(spark):
    texts = {"a": ["red apple", "green apple"] * 5, "b": ["red pear", "green apple"] * 5, "c": ["quartz rock", "slate stone"] * 5}
    cv = spark.createDataFrame([(k, str(i), v) for k, vs in texts.items() for i, v in enumerate(vs)], "dataset_id string, row_key string, value_str string")
    packed, pairs, enc = B.pack(cv, "value_str"), pairs_of(spark, ("a", "b"), ("a", "c")), WordEncoder(None, 8).one
    for d in (d_of(B.mean_word_vector_distance(packed, pairs, enc)), d_of(B.hotelling_distance(packed, pairs, enc, diag=True, output="stat"))):
        assert d["a", "b"] < d["a", "c"]


def test_histogram_forms(spark):
    cv, pairs = cv_of(spark, {"a": [0.5, 1.5, 1.6], "b": [0.2, 0.3, 1.5]}), pairs_of(spark, ("a", "b"))
    assert d_of(B.histogram_distance(cv, pairs, [0.0, 1.0, 2.0]))["a", "b"] == pytest.approx(math.sqrt(2) / 3)
    feats = [(F.col("value_num") < 1), (F.col("value_num") >= 1)]
    assert d_of(B.mean_feature_distance(cv, pairs, feats))["a", "b"] == pytest.approx(math.sqrt(2) / 3)
    bins = spark.createDataFrame([(0, 0.0, 1.0), (1, 1.0, 2.0)], "bin int, low double, high double")
    assert B.bin_join(cv, bins).groupBy("bin").count().count() == 2
    assert d_of(B.likelihood_similarity(C.value_histogram(cv), pairs_of(spark, ("a", "a"), ("a", "b"))))["a", "a"] < d_of(B.likelihood_similarity(C.value_histogram(cv), pairs))["a", "b"]


def test_ensemble(spark):
    s1 = spark.createDataFrame([("a", "b", "x", 1.0), ("a", "c", "x", 5.0)], "id_a string, id_b string, method string, d double")
    d = d_of(B.ensemble_similarity([s1], [s1]))
    assert d["a", "b"] == 0.5 and d["a", "c"] == 1.0


# ------------------------------------------------------------------ measures


def test_measures(spark):
    scored = spark.createDataFrame([(1.0, 1), (2.0, 1), (2.0, 0), (3.0, 0)], "d double, y int")
    assert M.roc_auc(scored).first()["auc"] == 0.875
    ranked = spark.createDataFrame([("q", "a", 1), ("q", "b", 2), ("q", "c", 3)], "query_id string, dataset_id string, rank int")
    truth = spark.createDataFrame([("q", "a"), ("q", "c")], "query_id string, dataset_id string")
    assert {r["k"]: r["matches"] for r in M.matches_at_k(ranked, truth, (1, 2, 3)).collect()} == {1: 1, 2: 1, 3: 2}
    assert {r["k"]: r["hit_rate"] for r in M.hit_rate_at_k(ranked, truth, (1,)).collect()} == {1: 1.0}
    m = spark.createDataFrame([(p,) for p in (0.4, 0.5, 0.6, 0.9)], "p double")
    none = spark.createDataFrame([("z", 0.5), ("z", 0.1)], "query_id string, p double")
    assert M.calibrated_recall(m, none).first()["recall"] == 0.5
    pr = {r["k"]: (r["precision"], r["recall"]) for r in M.precision_recall_at_k(ranked, truth, (1, 2)).collect()}
    assert pr == {1: (1.0, 0.5), 2: (0.5, 0.5)}
    al = spark.createDataFrame([("x", "x"), ("y", "z")], "col_a string, col_b string")
    assert M.alignment_precision(al, spark.createDataFrame([("x", "x"), ("y", "y")], "col_a string, col_b string")).first()["precision"] == 0.5
    rows, seconds = M.observe_cost(scored, "t", lambda df: df.collect())
    assert rows == 4 and seconds > 0


def test_auc_random(spark):
    rng = random.Random(1)
    data = [(float(rng.randrange(8)), rng.randrange(2)) for _ in range(80)]
    pos, neg = [d for d, y in data if y], [d for d, y in data if not y]
    want = sum((a < b) + 0.5 * (a == b) for a in pos for b in neg) / len(pos) / len(neg)
    assert M.roc_auc(spark.createDataFrame(data, "d double, y int")).first()["auc"] == pytest.approx(want)


def test_deviation_below_bound(spark):
    rng = np.random.default_rng(0)
    bags = spark.createDataFrame([(k, str(i), v.tolist()) for k in "ab" for i, v in enumerate(rng.normal(size=(60, 3)) / 3)], "dataset_id string, row_key string, vec array<double>")
    r = M.empirical_deviation(bags, pairs_of(spark, ("a", "b")), 30, 0.5, 20, width=3).first()
    assert r["rate"] <= r["bound"] and r["draws"] == 20


# ------------------------------------------------------------------ search


@pytest.fixture(scope="module")
def cloud(spark):
    rng = np.random.default_rng(8)
    x = rng.normal(size=(400, 6))
    x[13] = x[12]  # a tie
    df = spark.createDataFrame([(f"{i:03d}", v.tolist()) for i, v in enumerate(x)], "dataset_id string, s array<double>").repartition(5).cache()
    q = df.filter("CAST(dataset_id AS INT) % 20 = 0 OR dataset_id = '012'").withColumnRenamed("dataset_id", "query_id").cache()
    return x, df, q


def brute(x, i, k):
    d = ((x - x[i]) ** 2).sum(axis=1)
    return [f"{j:03d}" for j in sorted(range(len(x)), key=lambda j: (d[j], j))[:k]]


def test_exact_search(cloud):
    x, df, q = cloud
    for block in (3, 1000):
        got = {}
        for r in X.top_k_exact(q, df, 4, block).orderBy("rank").collect():
            got.setdefault(r["query_id"], []).append(r["dataset_id"])
        assert got == {i: brute(x, int(i), 4) for i in got} and len(got) == q.count()
    assert X.top_k_exact(q, df, 1000).count() == q.count() * 400  # k beyond the repository
    assert X.top_k_exact(q.limit(0), df, 3).count() == 0


def test_many_ties(spark):
    df = spark.createDataFrame([(f"{i:03d}", [float(i // 40), 0.0]) for i in range(200)], "dataset_id string, s array<double>").repartition(3)
    q = spark.createDataFrame([("q", [0.0, 0.0])], "query_id string, s array<double>")
    assert [r["dataset_id"] for r in X.top_k_exact(q, df, 3).orderBy("rank").collect()] == ["000", "001", "002"]


def test_indexes(cloud):
    x, df, q = cloud
    exact = X.top_k_exact(q, df, 5).cache()
    centroids = X.fit_cells(df, 12)
    indexed = X.assign_cells(df, centroids).cache()
    recall = [M.index_recall(X.top_k_cells(q, indexed, centroids, 5, p), exact, 5).first()["recall"] for p in (1, 4, 12)]
    assert recall[0] <= recall[1] <= recall[2] == 1.0 and recall[1] > 0.7
    assert M.index_recall(X.top_k_lsh(q, df, 5, 2.0, 12), exact, 5).first()["recall"] >= 0.9
    radii = {r["cell"]: r["radius"] for r in X.cell_radii(indexed, centroids).collect()}
    kth = {r["query_id"]: math.sqrt(r["d"]) for r in exact.filter("rank = 5").collect()}
    cell = {r["dataset_id"]: r["cell"] for r in indexed.collect()}
    for r in exact.collect():  # no cell that holds a neighbour may be pruned
        c = cell[r["dataset_id"]]
        assert np.linalg.norm(x[int(r["query_id"])] - centroids[c]) - radii[c] <= kth[r["query_id"]] + 1e-9


def test_norm_band(cloud, spark):
    x, df, q = cloud
    got = {(r["query_id"], r["dataset_id"]) for r in X.norm_band_join(q, df, 1.2).collect()}
    want = {(i, f"{j:03d}") for i in (r["query_id"] for r in q.collect()) for j in range(400) if np.linalg.norm(x[int(i)] - x[j]) <= 1.2}
    assert got == want


def test_decisions(spark):
    r = spark.createDataFrame([("q", "a", 0.1), ("q", "b", 0.2), ("z", "a", 3.0)], "query_id string, dataset_id string, d double")
    assert {x["query_id"]: x["dataset_id"] for x in X.match_or_none(r, 0.5).collect()} == {"q": "a", "z": None}
    cat = spark.createDataFrame([("a", {"use": "money"}), ("b", {"use": "age"})], "dataset_id string, meta map<string,string>")
    assert {x["query_id"]: x["value"] for x in X.lookup_annotations(r, cat).collect()} == {"q": "money", "z": "money"}
    assert X.g_limit(0.5, 0.1) == pytest.approx(math.log(2) - 0.1)


def test_repository_storage(spark, tmp_path):
    v = embed_datasets(cv_of(spark, {"a": [1, 2], "b": [3]}), SetNet(32, 4, 3).init(1), model_id="m1")
    path = f"{tmp_path}/repo"
    tables.write_repository(v, path)
    more = embed_datasets(cv_of(spark, {"c": [9]}), SetNet(32, 4, 3).init(1), model_id="m1")
    tables.append_repository(more, path)
    assert tables.read_repository(spark, path, "numeric").count() == 3 and tables.read_repository(spark, path, "string").count() == 0
    with pytest.raises(ValueError):
        tables.append_repository(more.withColumn("model_id", F.lit("m2")), path)
    plan = tables.read_repository(spark, path, "numeric", [0], 0.5)._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(kind" in plan and "LessThanOrEqual(g,0.5)" in plan
    top = X.top_k_exact(query_vectors(tables.read_repository(spark, path)), tables.read_repository(spark, path), 3)
    own = {r["query_id"]: r["d"] for r in top.filter("query_id = dataset_id").collect()}
    g = {r["dataset_id"]: r["g"] for r in tables.read_repository(spark, path).collect()}
    assert all(own[k] == pytest.approx(2 * g[k]) for k in g)  # a dataset scores 2g with itself


def test_sources(spark, tmp_path):
    df = spark.createDataFrame([(1, "a"), (2, "b")], "x int, y string")
    for fmt in ("csv", "json", "orc", "parquet"):
        df.write.format(fmt).option("header", "true").save(f"{tmp_path}/{fmt}")
        assert sorted(map(tuple, tables.load_any(spark, f"{tmp_path}/{fmt}", fmt).select("x", "y").collect())) == [(1, "a"), (2, "b")]


# ------------------------------------------------------------------ truth


def test_labels(spark):
    t = spark.createDataFrame([("d1", "c_acctbal"), ("d2", "s_acctbal"), ("d3", "shipdate"), ("d4", "shipdates"), ("d5", "x")], "dataset_id string, label string")
    lp = {(r["label_a"], r["label_b"]): r["rule"] for r in G.label_pairs(t).collect()}
    assert lp["acctbal", "acctbal"] == "equal" and lp["shipdate", "shipdates"] == "jaro_winkler" and ("acctbal", "shipdate") not in lp
    vec = spark.createDataFrame([("ship", [1.0, 0.0]), ("send", [0.99, 0.05])], "word string, vec array<double>")
    t2 = spark.createDataFrame([("d1", "ship"), ("d2", "send")], "dataset_id string, label string")
    assert {r["rule"] for r in G.label_pairs(t2, vec, 2).filter("label_a <> label_b").collect()} == {"cosine"}
    m = {tuple(r) for r in G.dataset_matches(t, G.label_pairs(t)).collect()}
    assert m == {("d1", "d2"), ("d3", "d4")}
    assert {r["label"] for r in G.drop_vague(t.select("label")).collect()} == {"c_acctbal", "s_acctbal", "shipdate", "shipdates"}
    with pytest.raises(ValueError):
        G.assert_no_labels(t)


def test_roles_and_pairs(spark, sf_dir):
    cv = repository_values(spark, sf_dir, COARSE)
    t = cv.select("dataset_id", "table_id", "variable").distinct().cache()
    roles = G.assign_roles(t, 0.4)
    assert roles.groupBy("table_id").count().filter("count > 1").count() == 0
    p = G.balanced_pairs(t, 30).cache()
    var = {r["dataset_id"]: (r["variable"], r["table_id"]) for r in t.collect()}
    for r in p.collect():
        (va, ta), (vb, tb) = var[r["id_a"]], var[r["id_b"]]
        assert ta != tb and (va == vb) == bool(r["y"])
    assert p.filter("y = 1").count() > 5 and G.cross_table_pairs(p, t).count() == p.count()
    same = t.alias("a").join(t.alias("b"), F.expr("a.variable = b.variable AND a.dataset_id < b.dataset_id")).select(F.col("a.dataset_id").alias("dataset_a"), F.col("b.dataset_id").alias("dataset_b"))
    for r in G.sample_triplets(t, same).collect():
        assert var[r["anchor"]][0] == var[r["positive"]][0] != var[r["negative"]][0]


def test_carve(spark):
    cv = cv_of(spark, {"a": range(50), "b": range(50)})
    c = G.carve_halves(cv, spark.createDataFrame([("a",)], "dataset_id string"))
    n = {r["dataset_id"]: r["count"] for r in c.groupBy("dataset_id").count().collect()}
    assert n["b"] == 50 and n["a"] + n["a~S"] == 50 and 10 < n["a"] < 40


# ------------------------------------------------------------------ alignment


def test_two_opt_swaps():
    p = np.array([[0.9, 0.8], [0.8, 0.1]])
    assert A.align_greedy(p) == [(0, 0), (1, 1)] and A.align_two_opt(p) == [(0, 1), (1, 0)] == A.align_exact(p)


def test_two_opt_against_brute_force():
    rng = np.random.default_rng(3)
    for shape in ((4, 4), (3, 6), (6, 3), (5, 5)) * 5:
        p = rng.random(shape)
        total = lambda a: sum(p[i, j] for i, j in a)  # noqa: E731, B023
        two, best = A.align_two_opt(p, 10), A.align_exact(p)
        assert len(two) == min(shape) and len({j for _, j in two}) == len(two)
        assert total(A.align_greedy(p)) - 1e-9 <= total(two) <= total(best) + 1e-9 and total(two) >= 0.97 * total(best)


def test_union_search(spark):
    rows = []
    for t, good in (("t1", 3), ("t2", 1), ("t3", 0)):
        for i, j in ((i, j) for i in range(3) for j in range(3)):
            rows.append(("q", t, f"q.{i}", f"{t}.{j}", 0.9 if i == j and i < good else 0.05))
    cp = spark.createDataFrame(rows, "query_table string, table_id string, col_a string, col_b string, p double")
    for background in (None, cp):
        assert [r["table_id"] for r in A.union_search(cp, 3, background).orderBy("rank").collect()] == ["t1", "t2", "t3"]
    al = A.align_schemas(A.similarity_matrix(spark.createDataFrame([("g", "a", "x", 0.1), ("g", "a", "y", 2.0), ("g", "b", "x", 0.2), ("g", "b", "y", 0.3)], "group_id string, id_a string, id_b string, d double")))
    assert {(r["col_a"], r["col_b"]) for r in al.collect()} == {("a", "x"), ("b", "y")}
    n = spark.createDataFrame([("g", 2), ("none", 2)], "group_id string, n_columns int")
    assert {r["group_id"]: r["unionable"] for r in A.is_unionable(al, n).collect()} == {"g": True, "none": False}


def test_union_tables(spark):
    a, b = spark.createDataFrame([(1, "x")], "a int, n string"), spark.createDataFrame([(2, 3.0, "z")], "b int, c double, n string")
    u = A.union_tables(a, b, [("a", "b")])
    assert u.columns == ["a", "n", "c", "n_b"] and sorted(map(tuple, u.collect())) == [(1, "x", None, None), (2, None, 3.0, "z")]


def test_maps():
    rng = np.random.default_rng(0)
    x = np.concatenate([rng.normal(0, 0.1, (15, 5)), rng.normal(3, 0.1, (15, 5))])
    y = S.tsne(x, 5, 150)
    d = lambda i, j: np.linalg.norm(y[i] - y[j])
    near = np.mean([d(i, j) for i, j in combinations(range(15), 2)])
    assert near < np.mean([d(i, j) for i in range(15) for j in range(15, 30)])
    assert S.pca(x, 2).shape == (30, 2)


def test_word_vectors(spark, sf_dir):
    from varlink.operators import words as WV

    t = tables.load_table(spark, sf_dir, "documents").select(F.lit("d").alias("dataset_id"), F.col("text").alias("value_str"))
    v = WV.fit_word_vectors(t, 8).cache()
    d = WV.vector_dictionary(v)
    assert len(d) > 100 and all(len(x) == 8 for x in d.values())
    with pytest.raises(ValueError):
        WV.vector_dictionary(v, 3)
    some = sorted(d)[:2]
    f = spark.createDataFrame([("a", " ".join(some) + " qqqqqq"), ("a", "42")], "dataset_id string, value_str string")
    got = sorted(([r["vec"] for r in WV.field_word_vectors(f, v, 8).collect()]), key=lambda x: sum(abs(y) for y in x))
    assert got[0] == [0.0] * 8 and np.allclose(got[1], (d[some[0]] + d[some[1]]) / 2) and np.allclose(WordEncoder(d).one(" ".join(some) + " qqqqqq"), got[1])


def test_approx_stats(spark):
    r = {x["dataset_id"]: x for x in C.approx_stats(cv_of(spark, {"a": [1, 1, 2, 3] * 50, "b": range(3000)})).collect()}
    assert r["a"]["by_distinct"] and not r["b"]["by_distinct"] and r["a"]["n"] == 200 and abs(r["b"]["quartiles"][1] - 1500) < 60


def test_tests_from_moments(spark):
    """Hotelling's and the smoothed characteristic-function test from merged moments, against the tests on whole samples."""
    rng = np.random.default_rng(2)
    bags = {"a": rng.normal(size=(1500, 4)), "b": rng.normal(0.1, 1, size=(40, 4)), "c": rng.normal(size=(3, 4))}
    df = spark.createDataFrame([(k, x.tolist()) for k, v in bags.items() for x in v], "dataset_id string, vec array<double>").repartition(5)
    pairs = spark.createDataFrame([("a", "b"), ("a", "c"), ("b", "c")], "id_a string, id_b string")
    got = {(r["id_a"], r["id_b"]): r["d"] for r in B.hotelling_of_moments(B.vector_moments(df), pairs, output="t2").collect()}
    for a, b in got:
        assert np.isclose(got[a, b], S.hotelling(bags[a], bags[b])[0])
    values = {"a": np.round(rng.normal(size=900), 1), "b": np.round(rng.normal(0.3, 2, size=50), 1), "c": np.array([1.0])}
    hist = spark.createDataFrame([(k, float(x), int((v == x).sum())) for k, v in values.items() for x in np.unique(v)], "dataset_id string, value_num double, weight long").repartition(4)
    got = {(r["id_a"], r["id_b"]): r["d"] for r in B.smooth_cf_of_histograms(hist, pairs).collect()}
    assert len(got) == 3
    for a, b in got:
        assert np.isclose(got[a, b], S.smooth_cf(values[a], values[b], B.test_frequencies()), rtol=1e-6)


def test_strings_differ_late(spark):
    """Strings that differ only after their first hundred characters have other embeddings, alone and in batches."""
    from varlink.nets.bilstm import CharBiLstm
    from varlink.operators import embed

    net = CharBiLstm(4, 3, 2, None, 5).init(1)
    texts = ["x" * 120 + end for end in ("a", "b")] + ["", "é" * 300, "short"] * 3
    h, _ = embed.run_network(net, texts)
    assert not np.allclose(h[0], h[1]) and np.allclose(h[2], h[5])
    whole, embed.BATCH_CHARS = embed.BATCH_CHARS, 300
    try:
        assert np.allclose(embed.run_network(net, texts)[0], h)
    finally:
        embed.BATCH_CHARS = whole


def test_probes_reach_their_recall(spark):
    """The default number of probed cells gives the recall asked for, and fewer cells than all where cells are clear."""
    rng = np.random.default_rng(4)
    x = np.concatenate([rng.normal(8 * i, 1, size=(120, 3)) for i in range(6)])
    repo = spark.createDataFrame([(f"d{i}", v.tolist()) for i, v in enumerate(x)], "dataset_id string, s array<double>")
    centroids = X.fit_cells(repo, 6)
    indexed = X.assign_cells(repo, centroids)
    probes = X.choose_probes(indexed, centroids, 5)
    queries = repo.limit(60).withColumnRenamed("dataset_id", "query_id")
    recall = M.index_recall(X.top_k_cells(queries, indexed, centroids, 5), X.top_k_exact(queries, repo, 5), 5).first()["recall"]
    assert probes < 6 and recall >= 0.85


def test_numbered(spark):
    rows = [(f"d{i}", random.Random(i).randrange(50)) for i in range(300)]
    df = spark.createDataFrame(rows, "dataset_id string, p long").repartition(7)
    got = {r["dataset_id"]: r for r in G.numbered(df, "p", "dataset_id").collect()}
    assert [got[d]["i"] for d, _ in sorted(rows, key=lambda r: (r[1], r[0]))] == list(range(1, 301)) and {r["n"] for r in got.values()} == {300}
    assert G.numbered(df.limit(0), "p", "dataset_id").count() == 0
