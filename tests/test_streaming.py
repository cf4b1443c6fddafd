import datetime as dt

import pytest
from pyspark.sql import functions as F

from varlink.sources.tables import load_table, stream_table
from varlink.streaming import states as ST


@pytest.fixture(scope="module")
def event_files(spark, sf_dir, tmp_path_factory):
    """The events, a file per day, in order of time."""
    path = str(tmp_path_factory.mktemp("events"))
    e = load_table(spark, sf_dir, "events")
    for i, day in enumerate(sorted(r[0] for r in e.select(F.to_date("ts")).distinct().collect())[:6]):
        e.filter(F.to_date("ts") == F.lit(day)).coalesce(1).write.mode("append").parquet(f"{path}/day={i}")
    return path, e.schema


def drain(df, tmp, mode="append", sink=None):
    w = df.writeStream.option("checkpointLocation", f"{tmp}/ck").outputMode(mode).trigger(availableNow=True)
    q = (w.foreachBatch(sink) if sink else w.format("memory").queryName("t_" + tmp.name.replace("-", "_"))).start()
    q.awaitTermination(120)
    return None if sink else df.sparkSession.table("t_" + tmp.name.replace("-", "_"))


def batch(spark, event_files):
    return spark.read.parquet(event_files[0]).drop("day")


def stream(spark, event_files):
    return stream_table(spark, f"{event_files[0]}/*", event_files[1], per_trigger=1)


def test_windows(spark, event_files, tmp_path):
    got = drain(ST.stream_states(stream(spark, event_files), "1 day", "1 hour"), tmp_path, "complete")
    want = ST.stream_states(batch(spark, event_files), "1 day")
    key = lambda df: {(r["dataset_id"], r["start"]): r["n"] for r in df.collect()}
    assert key(got) == key(want)


def test_upsert_counts_once(spark, event_files, tmp_path):
    out = f"file://{tmp_path}/states"
    states = stream(spark, event_files).select(F.col("event_type").alias("dataset_id"), F.lit(1).cast("long").alias("n"), F.array(*ST.moment_features(F.col("value"))).alias("sum_h"), F.col("value").alias("total"))
    sink = ST.merge_states_sink(out)
    drain(states, tmp_path, sink=sink)
    last = max(int(p.name.split("=")[1]) for p in (tmp_path / "states").iterdir())
    want = {r["event_type"]: r["count"] for r in batch(spark, event_files).groupBy("event_type").count().collect()}
    got = lambda: {r["dataset_id"]: r["n"] for r in spark.read.parquet(f"{out}/batch={last}").collect()}
    assert got() == want
    one = batch(spark, event_files).limit(3).select(F.col("event_type").alias("dataset_id"), F.lit(1).cast("long").alias("n"), F.array(*ST.moment_features(F.col("value"))).alias("sum_h"), F.col("value").alias("total"))
    sink(one, last)  # run again after a failure: nothing is added
    assert got() == want


def test_sample_state(spark, event_files, tmp_path):
    got = drain(ST.stream_sample_state(stream(spark, event_files), keep=5), tmp_path, "update")
    last = {}
    for r in got.collect():
        if r["n"] >= last.get(r["dataset_id"], (0,))[0]:
            last[r["dataset_id"]] = (r["n"], r["sample"])
    from varlink.functions.sampling import priority_bits

    rows = batch(spark, event_files).select("event_type", priority_bits(42, F.col("event_id")).alias("p"), "value").collect()
    for t, (n, sample) in last.items():
        own = sorted((r["p"], r["value"]) for r in rows if r["event_type"] == t)
        assert n == len(own) and sample == [v for _, v in own[:5]]


def test_late_and_repeated_rows(spark, tmp_path):
    t = lambda h: dt.datetime(2024, 1, 1) + dt.timedelta(hours=h)
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double"
    path = f"{tmp_path}/in"
    for rows in ([(1, t(0), 1, "a", 1.0), (1, t(0), 1, "a", 1.0), (2, t(10), 1, "a", 1.0)], [(3, t(30), 1, "a", 1.0)], [(4, t(1), 1, "a", 9.0), (5, t(31), 1, "a", 1.0)]):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(path)
    s = stream_table(spark, path, schema, per_trigger=1)
    got = drain(ST.stream_states(ST.dedup(s, "2 hours"), "1 day", None), tmp_path, "update")
    n = {}
    for r in got.collect():
        n[r["start"]] = max(n.get(r["start"], 0), r["n"])
    assert n[t(0)] == 2  # the repeat is dropped, and the row that came a day late
    assert ST.dedup(spark.createDataFrame([(1, t(0))] * 2, "event_id long, ts timestamp")).count() == 1


def test_joins(spark, event_files, tmp_path):
    e = batch(spark, event_files)
    views, buys = e.filter("event_type = 'view'"), e.filter("event_type = 'purchase'")
    want = ST.stream_interval_join(views, buys, "12 hours").count()
    s = stream(spark, event_files)
    got = drain(ST.stream_interval_join(s.filter("event_type = 'view'"), s.filter("event_type = 'purchase'"), "12 hours", "1 day"), tmp_path)
    assert got.count() == want > 0
    h = e.groupBy(F.col("event_type").alias("dataset_id")).agg(F.array(*[F.avg(f) for f in ST.moment_features(F.col("value"))]).alias("h")).withColumn("g", F.lit(0.0))
    assert ST.stream_match(ST.stream_states(e, "1 day"), h, 0.9).count() > 0


def test_states_add(spark, event_files):
    e = batch(spark, event_files).cache()
    whole = ST.stream_states(e, "100 days")
    parts = [ST.stream_states(e.filter(f"event_id % 2 = {i}"), "100 days") for i in (0, 1)]
    a = {r["dataset_id"]: r for r in ST.add_states(*parts).collect()}
    for r in ST.add_states(whole, whole.limit(0)).collect():
        assert a[r["dataset_id"]]["n"] == r["n"] and a[r["dataset_id"]]["sum_h"] == pytest.approx(r["sum_h"])
