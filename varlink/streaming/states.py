"""Streaming dataset states.

The state of a dataset is a sum, so windows of a stream keep only ``n`` and the sums of the embedding's elements. The
same functions run on a batch DataFrame, which is how they are tested against SQL.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..functions.vectors import sq_dist


def moment_features(value: Column) -> list[Column]:
    """A small fixed feature map inside Catalyst: squashed value at several scales."""
    return [F.tanh(value / s) for s in (1.0, 10.0, 100.0, 1000.0)]


def watermarked(events: DataFrame, delay: str, ts: str = "ts") -> DataFrame:
    """``events`` with a watermark; times without zone are taken in the session's zone, as watermarks need instants."""
    return events.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay)


def stream_states(events: DataFrame, window: str = "1 day", delay: str | None = None, key: str = "event_type", value: str = "value", ts: str = "ts", slide: str | None = None) -> DataFrame:
    """``dataset_id, start, n, sum_h``: the state of every (key, window) dataset. With ``delay``, a watermark drops rows
    later than that."""
    if delay and events.isStreaming:
        events = watermarked(events, delay, ts)
    w = F.window(ts, window, slide) if slide else F.window(ts, window)
    g = events.filter(F.col(value).isNotNull()).groupBy(w.alias("w"), F.col(key).alias("dataset_id")).agg(F.count("*").alias("n"), F.array(*[F.sum(f) for f in moment_features(F.col(value))]).alias("sum_h"), F.sum(value).alias("total"))
    return g.select("dataset_id", F.col("w.start").alias("start"), "n", "sum_h", "total")


def add_states(a: DataFrame, b: DataFrame, by: tuple[str, ...] = ("dataset_id",), width: int = 4) -> DataFrame:
    """Merge two sets of states."""
    both = a.select(*by, "n", "sum_h", "total").unionByName(b.select(*by, "n", "sum_h", "total"))
    return both.groupBy(*by).agg(F.sum("n").alias("n"), F.array(*[F.sum(F.col("sum_h")[i]) for i in range(width)]).alias("sum_h"), F.sum("total").alias("total"))


def mean_of_state(df: DataFrame) -> DataFrame:
    return df.withColumn("h", F.transform("sum_h", lambda x: x / F.col("n")))


def stream_drift(events: DataFrame, stored: DataFrame, size: str = "2 days", slide: str = "1 day", delay: str | None = None) -> DataFrame:
    """Root distance of each sliding window's mean features to the stored vector of its dataset (``dataset_id, h0``)."""
    now = mean_of_state(stream_states(events, size, delay, slide=slide))
    return now.join(stored, "dataset_id").select("dataset_id", "start", "n", F.sqrt(sq_dist(F.col("h"), F.col("h0"))).alias("drift"))


def stream_sessions(events: DataFrame, gap: str = "30 minutes", delay: str | None = None) -> DataFrame:
    """Sessions of a user as datasets: ``user_id, start, n, mean_value``."""
    if delay and events.isStreaming:
        events = watermarked(events, delay)
    g = events.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n"), F.avg("value").alias("mean_value"))
    return g.select("user_id", F.col("s.start").alias("start"), "n", "mean_value")


def dedup(events: DataFrame, delay: str = "1 hour", key: str = "event_id", ts: str = "ts") -> DataFrame:
    """Repeats of a key dropped: within the watermark on streams, over all rows on batches."""
    return watermarked(events, delay, ts).dropDuplicatesWithinWatermark([key]) if events.isStreaming else events.dropDuplicates([key])


def stream_match(states: DataFrame, repository: DataFrame, tau: float = 0.5, max_rows: int = 100_000) -> DataFrame:
    """New states against a slice of the repository (``dataset_id, h, g``) that is sent to all tasks: at most ``max_rows``
    datasets, which is checked; a larger one is matched cell by cell (``search.assign_cells``)."""
    n = repository.limit(max_rows + 1).count()
    if n > max_rows:
        raise ValueError(f"more than {max_rows} datasets to match: pass one cell of the repository at a time")
    r = repository.select(F.col("dataset_id").alias("match_id"), F.col("h").alias("rh"), F.col("g").alias("rg"))
    scored = mean_of_state(states).join(F.broadcast(r), F.lit(True)).withColumn("p", F.exp(-(sq_dist(F.col("h"), F.col("rh")) + F.col("rg"))))
    return scored.filter(F.col("p") >= tau).select("dataset_id", "start", "match_id", "p")


def stream_interval_join(left: DataFrame, right: DataFrame, within: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    """Each row of ``left`` with rows of ``right`` of the same user up to ``within`` later; both sides watermarked."""
    if left.isStreaming:
        left, right = watermarked(left, delay), watermarked(right, delay)
    a = left.select("user_id", F.col("event_id").alias("left_id"), F.col("ts").alias("left_ts"))
    b = right.select(F.col("user_id").alias("right_user"), F.col("event_id").alias("right_id"), F.col("ts").alias("right_ts"), "value")
    on = (F.col("user_id") == F.col("right_user")) & (F.col("right_ts") >= F.col("left_ts")) & (F.col("right_ts") <= F.col("left_ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, on).drop("right_user")


# ------------------------------------------------------------------ sinks and state


def merge_states_sink(path: str, width: int = 4):
    """A function for ``foreachBatch`` that adds each micro-batch to the states kept at ``path``.

    States are kept as one folder per batch id; a batch that is run again finds its folder and is skipped, so every row
    counts once. The previous folder is the input of the next.
    """

    def sink(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
        at = lambda i: jvm.org.apache.hadoop.fs.Path(f"{path}/batch={i}")
        fs = at(0).getFileSystem(conf)
        done = lambda i: fs.exists(jvm.org.apache.hadoop.fs.Path(f"{path}/batch={i}/_SUCCESS"))
        if done(batch_id):
            return
        fresh = batch.select("dataset_id", "n", "sum_h", "total")
        merged = add_states(spark.read.parquet(f"{path}/batch={batch_id - 1}"), fresh, width=width) if batch_id and done(batch_id - 1) else add_states(fresh, fresh.limit(0), width=width)
        merged.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")
        if batch_id > 1:
            fs.delete(at(batch_id - 2), True)

    return sink


SAMPLE_SCHEMA = "dataset_id string, n long, total double, sample array<double>"
_STATE_SCHEMA = "n long, total double, priorities array<long>, values array<double>"


def stream_sample_state(events: DataFrame, keep: int = 1000, key: str = "event_type", value: str = "value", row_key: str = "event_id", seed: int = 42) -> DataFrame:
    """Per dataset the ``keep`` values of lowest seeded priority seen so far, with count and sum.

    A bottom-k sample of priorities merges and does not depend on arrival order, unlike a reservoir; the state holds at
    most ``keep`` values a key.
    """
    from ..functions.sampling import priority_bits

    source = events.filter(F.col(value).isNotNull()).select(F.col(key).cast("string").alias("dataset_id"), priority_bits(seed, F.col(row_key)).alias("p"), F.col(value).cast("double").alias("v"))

    def update(group: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, total, ps, vs = state.get if state.exists else (0, 0.0, [], [])
        pairs = list(zip(ps, vs, strict=True))
        for f in frames:
            n, total = n + len(f), total + float(f["v"].sum())
            pairs = sorted(pairs + list(zip(f["p"].tolist(), f["v"].tolist(), strict=True)))[:keep]
        state.update((n, total, [p for p, _ in pairs], [v for _, v in pairs]))
        yield pd.DataFrame({"dataset_id": [group[0]], "n": [n], "total": [total], "sample": [[v for _, v in pairs]]})

    return source.groupBy("dataset_id").applyInPandasWithState(update, SAMPLE_SCHEMA, _STATE_SCHEMA, "update", GroupStateTimeout.NoTimeout)
