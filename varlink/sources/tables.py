"""Tables in, repository out."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def load_any(spark: SparkSession, path: str, fmt: str = "parquet", schema: T.StructType | str | None = None, **options) -> DataFrame:
    """A user's data table: any Spark format, or ``fmt="table"`` for a catalogue name. CSV and JSON without a schema cost
    one more pass to infer it."""
    if fmt == "table":
        return spark.table(path)
    reader = spark.read.format(fmt)
    if schema is not None:
        reader = reader.schema(schema)
    elif fmt == "csv":
        options = {"header": "true", "inferSchema": "true"} | options
    return reader.options(**options).load(path)


def stream_table(spark: SparkSession, path: str, schema: T.StructType | str, fmt: str = "parquet", per_trigger: int | None = None) -> DataFrame:
    """New files of a folder as a stream."""
    reader = spark.readStream.format(fmt).schema(schema)
    if per_trigger:
        reader = reader.option("maxFilesPerTrigger", per_trigger)
    return reader.load(path)


# ------------------------------------------------------------------ repository of vectors


def write_repository(vectors: DataFrame, path: str, mode: str = "overwrite") -> None:
    """Vectors partitioned by kind and cell, sorted by g inside a file, so row groups are skipped by its minimum.

    ``vectors``: dataset_id, kind, h, g, s, n_used, model_id and optionally cell.
    """
    if "cell" not in vectors.columns:
        vectors = vectors.withColumn("cell", F.lit(0))
    vectors.repartition("kind", "cell").sortWithinPartitions("kind", "cell", "g").write.mode(mode).partitionBy("kind", "cell").parquet(path)


def append_repository(vectors: DataFrame, path: str) -> None:
    """Add datasets; those of another model are refused, since scores across models mean nothing."""
    spark = vectors.sparkSession
    have = [r[0] for r in spark.read.parquet(path).select("model_id").distinct().limit(2).collect()]
    new = [r[0] for r in vectors.select("model_id").distinct().limit(2).collect()]
    if new and have and new != have:
        raise ValueError(f"the repository holds vectors of model {have}, not {new}")
    write_repository(vectors, path, "append")


def read_repository(spark: SparkSession, path: str, kind: str | None = None, cells: list[int] | None = None, g_at_most: float | None = None) -> DataFrame:
    """The repository, or the part of it that a search needs; all three conditions reach the scan."""
    df = spark.read.parquet(path)
    if kind is not None:
        df = df.filter(F.col("kind") == kind)
    if cells is not None:
        df = df.filter(F.col("cell").isin(cells))
    if g_at_most is not None:
        df = df.filter(F.col("g") <= g_at_most)
    return df
