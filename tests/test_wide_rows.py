"""Values that are read from wide rows give what their long form gives."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from varlink.operators import baselines as B
from varlink.operators import embed as E
from varlink.operators.columnize import columnize
from varlink.plans import repository as R
from varlink.plans import workloads

from .test_workload_reuse import SF, SMALL

PLAIN = {"numeric": R.FINE, "language": R.LANGUAGE}


def plain_values(spark, kind, flags):
    cv = R.repository_values(spark, SF, PLAIN[kind])
    cv = R.apply_unit_shift(cv, share=SMALL.shift) if kind == "numeric" else cv
    return cv.unionByName(R.flag_datasets(spark, SF, flags, words=kind != "numeric"))


@pytest.mark.parametrize("kind", ["numeric", "language"])
def test_prepared_values(spark, kind, monkeypatch):
    """The long form and the sizes are those of the tables, and what is written has no row for every value."""
    written, cut = [], workloads.cut
    for module in (workloads, R):
        monkeypatch.setattr(module, "cut", lambda df, name: written.append(cut(df, name)) or written[-1])
    cv, truth = workloads.prepare(spark, SF, kind, replace(SMALL, seed=91, shift=0.4000001, flags=2))
    plain = plain_values(spark, kind, 2)
    columns = ["dataset_id", "table_id", "variable", "row_key", "value_num", "value_str"]
    assert cv.select(*columns).exceptAll(plain.select(*columns)).count() == 0 and cv.count() == plain.count()
    want = {tuple(r) for r in R.truth_of(plain).collect()}
    assert {tuple(r) for r in truth.select("dataset_id", "table_id", "variable", "n_values").collect()} == want
    tables = {f.table for f in PLAIN[kind]}
    rows = sum(spark.read.parquet(f"{SF}/{t}.parquet").count() for t in [*tables, "orders"])
    assert sum(t.count() for t in written) <= rows + 2 * len(want) < cv.count()


def test_column_states(spark, monkeypatch):
    """Sums over wide rows, gathered in parts of any size, with missing values, tables without a name and repeated values."""
    rng = np.random.default_rng(3)
    rows = [(f"t{i % 3}" if i % 7 else None, float(rng.integers(0, 9)) if i % 5 else None, float("nan") if i % 4 else float(i), f"word{i % 6} blue" if i % 3 else None, None) for i in range(300)]
    wide = spark.createDataFrame(rows, "table_id string, a double, b double, c string, d string").repartition(3)
    long = columnize(wide, F.col("table_id"), ["a", "b", "c", "d"])
    for encoder, columns, missing in ((E.NumericEncoder(), ["a", "b"], "value_num IS NOT NULL"), (E.WordEncoder(None, 8), ["c", "d"], "value_str IS NOT NULL")):
        net = workloads.SetNet(encoder.width, 6, 4, 3, True).init(1)
        want = {r["dataset_id"]: r for r in E.embed_datasets(long.filter(missing), net, encoder).collect()}
        for gathered in (4, 1 << 22):
            monkeypatch.setattr(E, "GATHERED", gathered)
            monkeypatch.setattr(E, "BATCH", 16 if gathered == 4 else 2048)
            got = {r["dataset_id"]: r for r in E.of_states(E.column_states(wide, columns, net, encoder), net).collect()}
            assert got.keys() == want.keys() and len(got) >= 3
            for k, r in want.items():
                assert got[k]["n_used"] == r["n_used"] and got[k]["h"] == pytest.approx(r["h"]) and got[k]["g"] == pytest.approx(r["g"]) and got[k]["spread"] == pytest.approx(r["spread"], abs=1e-12)


def test_pack_by_sizes(spark):
    """Thinning by known sizes leaves the packed values as they are, for the named datasets."""
    cv = spark.range(6000).select(F.when(F.col("id") < 5000, "long").when(F.col("id") < 5990, "short").otherwise("other").alias("dataset_id"), F.col("id").cast("string").alias("row_key"), F.col("id").cast("double").alias("value_num"))
    sizes = cv.filter("dataset_id <> 'other'").groupBy("dataset_id").agg(F.count("*").alias("n_values"))
    for n in (1, 50, 1000):
        want = {r["dataset_id"]: r["values"] for r in B.pack(cv, n=n).collect() if r["dataset_id"] != "other"}
        assert {r["dataset_id"]: r["values"] for r in B.pack(cv, n=n, sizes=sizes).collect()} == want
