"""Session profiles."""

from __future__ import annotations

from pyspark.sql import SparkSession

#: Settings that hold at any size; the rest is up to the cluster.
COMMON = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.session.timeZone": "UTC",
    "spark.sql.execution.arrow.pyspark.enabled": "true",
    "spark.sql.execution.arrow.maxRecordsPerBatch": "10000",
}


def build_session(app: str = "varlink", cores: int | None = None, memory: str = "8g") -> SparkSession:
    """A local session for tests and benchmarks (``cores`` threads), or with ``cores=None`` the cluster's own."""
    builder = SparkSession.builder.appName(app).config(map=COMMON)
    if cores:
        builder = builder.master(f"local[{cores}]").config("spark.driver.memory", memory).config("spark.sql.shuffle.partitions", str(max(cores, 8))).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
    return builder.getOrCreate()
