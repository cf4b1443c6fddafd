import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from varlink.functions import encoding as E
from varlink.functions import scores as SC
from varlink.functions import text as TX
from varlink.functions import vectors as V


def one(spark, column):
    return spark.range(1).select(column.alias("x")).first()["x"]


def arr(*x):
    return F.array(*[F.lit(float(v)) for v in x])


def test_vectors(spark):
    assert one(spark, V.sq_dist(arr(1, 2), arr(4, 6))) == 25
    assert one(spark, V.dot(arr(1, 2), arr(3, 4))) == 11 and one(spark, V.norm(arr(3, 4))) == 5
    assert one(spark, V.vec_add(arr(1, 2), arr(3, 4))) == [4, 6] and one(spark, V.vec_scale(arr(1, 2), 2)) == [2, 4]


def test_score_is_no_metric_but_its_root_is(spark):
    g = F.lit(0.0)
    d = lambda a, b: one(spark, SC.match_score(arr(a), arr(b), g, g))
    assert (d(0, 1), d(1, 2), d(0, 2)) == (1, 1, 4)  # D breaks the triangle inequality
    assert math.sqrt(d(0, 2)) <= math.sqrt(d(0, 1)) + math.sqrt(d(1, 2))
    assert one(spark, SC.match_score(arr(1), arr(1), F.lit(0.3), F.lit(0.3))) == pytest.approx(0.6)
    assert one(spark, SC.match_probability(F.lit(0.6))) == pytest.approx(math.exp(-0.6))
    rng = np.random.default_rng(0)
    for _ in range(2000):
        h, q = rng.normal(size=(3, 2)), rng.random(3)
        r = lambda i, j: math.sqrt(((h[i] - h[j]) ** 2).sum() + q[i] + q[j])  # noqa: E731, B023
        assert r(0, 2) <= r(0, 1) + r(1, 2) + 1e-12


def test_search_vectors(spark):
    a, b = SC.query_vector(arr(1, 0), F.lit(0.25)), SC.repository_vector(arr(0, 0), F.lit(0.09))
    assert one(spark, V.sq_dist(a, b)) == pytest.approx(1.34)
    assert one(spark, SC.match_score(arr(1, 0), arr(0, 0), F.lit(0.25), F.lit(0.09))) == pytest.approx(1.34)


def test_losses(spark):
    loss = lambda d, y: one(spark, SC.pair_loss(F.lit(d), F.lit(y)))
    assert loss(2.0, 1) == 2 and loss(2.0, 0) == pytest.approx(0.1454, abs=1e-4)
    assert math.isfinite(loss(0.0, 0))
    assert one(spark, SC.loss_gradient(F.lit(2.0), F.lit(0))) == pytest.approx(-1 / (math.e**2 - 1))
    assert abs(one(spark, SC.loss_gradient(F.lit(0.01), F.lit(0)))) > 50  # separation outweighs attraction near zero


def test_recalibration(spark):
    assert one(spark, SC.recalibrate_prior(F.lit(0.8), 0.1)) == pytest.approx(0.3077, abs=1e-4)
    assert one(spark, SC.recalibrate_pu(F.lit(0.5), 0.4)) == 1.0
    assert one(spark, SC.combine_scores(F.lit(0.5), F.lit(0.5))) == pytest.approx(0.5)
    assert 0.6 < one(spark, SC.combine_scores(F.lit(0.5), F.lit(0.9))) < 0.9


def test_bound(spark):
    b = lambda n, e: one(spark, SC.deviation_bound(F.lit(n), F.lit(e), F.lit(1.0)))
    assert b(2000, 0.5) == pytest.approx(6.5e-7, rel=0.02) and b(10, 0.2) > 1
    n = SC.samples_needed(0.5, 0.05, 1.0)
    assert b(n, 0.5) <= 0.05 < b(n - 1, 0.5)
    assert one(spark, SC.adjustment_bound(F.lit(100), F.lit(0.5), F.lit(1.0))) < 1e-9


@pytest.mark.parametrize(("x", "n"), [(1.5, 1069547520), (-2.0, -1073741824), (0.1, 1036831949)])
def test_float_bits(spark, x, n):
    assert one(spark, E.float_bits(F.lit(x))) == n


EDGES = [0.0, -0.0, 1.0, -1.5, 0.1, 16777217.0, 1e-40, 3.4e38, float("inf"), -7.25, 2.0**20, 1e-7]


def test_bit_encodings_agree(spark):
    df = spark.createDataFrame([(i, x) for i, x in enumerate(EDGES)], "i int, x double")
    got = np.array([r["b"] for r in df.select("i", E.encode_bits32(F.col("x")).alias("b")).orderBy("i").collect()])
    assert (got == E.np_bits32(np.array(EDGES))).all()
    small = [x for x in EDGES if abs(x) < 1e6]
    df = spark.createDataFrame([(i, x) for i, x in enumerate(small)], "i int, x double")
    got = np.array([r["b"] for r in df.select("i", E.encode_bits32(F.col("x"), "fixed32").alias("b")).orderBy("i").collect()])
    assert (got == E.np_bits32(np.array(small), "fixed32")).all()


def test_exponent_mantissa(spark):
    xs = [x for x in EDGES if math.isfinite(x)]
    df = spark.createDataFrame([(i, x) for i, x in enumerate(xs)], "i int, x double")
    got = np.array([r["b"] for r in df.select("i", E.encode_exp_mantissa(F.col("x")).alias("b")).orderBy("i").collect()])
    assert np.allclose(got, E.np_exp_mantissa(np.array(xs)))
    assert all(m * 2.0**e == x for (e, m), x in zip(got, xs, strict=True))


def test_text(spark):
    assert TX.jaro_winkler_text("martha", "marhta") == pytest.approx(0.9611, abs=1e-4)
    assert TX.jaro_winkler_text("", "a") == 0 and TX.jaro_winkler_text(None, "a") is None and TX.jaro_winkler_text("a", "a") == 1
    assert one(spark, TX.words(F.lit("An é élan, of X 42 straße"))) == ["an", "élan", "of", "straße"]
    assert one(spark, TX.strip_html(F.lit("<p>a<script>x</p></script><!-- y > -->b<STYLE>z</STYLE></p>"))) == "a b"
    assert one(spark, TX.url_host(F.lit("https://A.b/c?d"))) == "a.b"
    assert one(spark, TX.tokenize_label(F.lit("shipDate_2 x"))) == ["ship", "date", "x"]
    assert one(spark, TX.plain_label(F.lit("l_extendedprice"))) == "extendedprice"
    a, b, c = (TX.hashed_word_vector(w) for w in ("shipping", "shipped", "quartz"))
    cos = lambda x, y: x @ y / np.sqrt((x @ x) * (y @ y))
    assert cos(a, b) > cos(a, c) + 0.2
