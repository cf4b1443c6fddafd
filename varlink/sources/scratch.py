"""Working tables in the shared folder: lineage is cut by writing a table, which any executor can read again."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_ROOTS: dict[str, str] = {}


def shared_root(spark: SparkSession) -> str:
    """Folder of this application below ``spark.checkpoint.dir``; removed when the driver ends.

    Where the setting is absent, a local session (tests) gets a temporary folder, and any other session a folder below
    the warehouse, which all executors share.
    """
    app = spark.sparkContext.applicationId
    if app not in _ROOTS:
        base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
        if not base:
            local = spark.sparkContext.master == "local" or spark.sparkContext.master.startswith("local[")
            base = "file://" + tempfile.mkdtemp(prefix="varlink-") if local else spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_work"
        _ROOTS[app] = f"{base.rstrip('/')}/work-{app}-{uuid.uuid4().hex[:8]}"
        atexit.register(remove, spark, _ROOTS[app])
    return _ROOTS[app]


def remove(spark: SparkSession, path: str) -> None:
    """Delete ``path`` through Hadoop, whatever store it is in; nothing happens when the session has ended."""
    jsc = spark.sparkContext._jsc
    if jsc is None or jsc.sc().isStopped():
        return
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(jsc.hadoopConfiguration()).delete(where, True)


def new_path(spark: SparkSession, name: str) -> str:
    """An unused path for a working table of the given name."""
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex[:10]}"


def cut(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as a table in the shared folder and read it back: the lineage ends there.

    Lost executors then cost only the tasks that read the table, and later passes read just the columns they need.
    """
    path = new_path(df.sparkSession, name)
    df.write.option("compression", "zstd").parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._work_path = path
    return out


def drop_cut(df: DataFrame) -> None:
    """Remove a table made by :func:`cut` that nothing will read again."""
    remove(df.sparkSession, df._work_path)
