"""The given tables as a repository: virtual tables (shards) and their columns as datasets.

A family's expressions are plain SQL that Spark and DuckDB read alike, so the same text makes both sides of a comparison.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.sampling import priority_bits, priority_sql
from ..functions.text import plain_label
from ..operators.columnize import as_numeric, columnize, not_missing
from ..sources.scratch import cut
from ..sources.tables import load_table


@dataclass(frozen=True)
class Family:
    """Shards of one table: ``shard`` names the virtual table of a row, ``key`` tells rows apart."""

    table: str
    shard: str
    key: tuple[str, ...]
    columns: tuple[str, ...]


_LINE_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "CAST(round(l_extendedprice * 100) AS BIGINT)")
#: A few large shards per table, for the registry's queries.
COARSE = (
    Family("lineitem", "concat('lineitem:', l_returnflag, l_linestatus)", _LINE_KEY, ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_partkey", "l_suppkey")),
    Family("orders", "concat('orders:', o_orderstatus)", ("o_orderkey",), ("o_totalprice", "o_custkey")),
    Family("customer", "concat('customer:', c_mktsegment)", ("c_custkey",), ("c_acctbal", "c_custkey", "c_nationkey")),
    Family("supplier", "concat('supplier:', CAST(s_nationkey % 2 AS STRING))", ("s_suppkey",), ("s_acctbal", "s_suppkey", "s_nationkey")),
    Family("part", "concat('part:', CAST(p_size % 4 AS STRING))", ("p_partkey",), ("p_size", "p_retailprice", "p_partkey")),
    Family("events", "concat('events:', event_type)", ("event_id",), ("value", "user_id")),
)
#: Many small shards, for training and retrieval.
FINE = (
    Family("lineitem", "concat('lineitem:', CAST(l_linenumber AS STRING), l_returnflag, l_linestatus, CAST(year(l_shipdate) AS STRING))", _LINE_KEY, ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_partkey", "l_suppkey", "l_orderkey")),
    Family("orders", "concat('orders:', substr(o_orderpriority, 1, 1), CAST(year(o_orderdate) AS STRING))", ("o_orderkey",), ("o_totalprice", "o_custkey", "o_orderkey")),
    Family("customer", "concat('customer:', CAST(c_nationkey AS STRING))", ("c_custkey",), ("c_acctbal", "c_custkey")),
    Family("supplier", "concat('supplier:', CAST(s_suppkey % 4 AS STRING))", ("s_suppkey",), ("s_acctbal", "s_suppkey", "s_nationkey")),
    Family("part", "concat('part:', p_brand)", ("p_partkey",), ("p_size", "p_retailprice", "p_partkey")),
    Family("events", "concat('events:', event_type, CAST(day(ts) AS STRING))", ("event_id",), ("value", "user_id")),
)
#: String-valued datasets; ``language`` and ``string`` are the kinds the rules give them.
LANGUAGE = (
    Family("documents", "concat('documents:', source, lang)", ("doc_id",), ("text",)),
    Family("conversations", "concat('conversations:', role, CAST(turn AS STRING))", ("conv_id", "turn"), ("text",)),
    Family("benchmark", "concat('benchmark:', CAST(item_id % 2 AS STRING))", ("item_id",), ("text",)),
    Family("part", "concat('part:', p_brand)", ("p_partkey",), ("p_name", "p_type")),
    Family("customer", "concat('customer:', CAST(c_nationkey AS STRING))", ("c_custkey",), ("c_mktsegment",)),
    Family("events", "concat('events:', CAST(day(ts) AS STRING))", ("event_id",), ("event_type",)),
)
STRINGS = (
    Family("pages", "concat('pages:', CAST(page_id % 8 AS STRING))", ("page_id",), ("url",)),
    Family("customer", "concat('customer:', CAST(c_nationkey AS STRING))", ("c_custkey",), ("c_name",)),
    Family("supplier", "concat('supplier:', CAST(s_suppkey % 4 AS STRING))", ("s_suppkey",), ("s_name",)),
    Family("part", "concat('part:', CAST(p_size AS STRING))", ("p_partkey",), ("p_brand",)),
    Family("orders", "concat('orders:', o_orderstatus, CAST(year(o_orderdate) AS STRING))", ("o_orderkey",), ("o_orderpriority",)),
    Family("events", "concat('events:', event_type, CAST(day(ts) AS STRING))", ("event_id",), ("props",)),
)


def family_values(spark: SparkSession, sf_dir: str, family: Family, dealt: bool = False) -> DataFrame:
    """``dataset_id, table_id, variable, row_key, value_num, value_str``; one scan, no shuffle.

    ``dealt``: the rows are dealt over all cores before they are unpivoted, as a file of one row group is one task."""
    df = load_table(spark, sf_dir, family.table)
    if dealt:
        df = df.repartition(max(8, spark.sparkContext.defaultParallelism))
    long = columnize(df, F.expr(family.shard), list(family.columns), [F.expr(k) for k in family.key])
    return long.select("dataset_id", "table_id", plain_label(F.col("column")).alias("variable"), "row_key", "value_num", "value_str")


def repository_values(spark: SparkSession, sf_dir: str, families: tuple[Family, ...] = COARSE, dealt: bool = False) -> DataFrame:
    return reduce(DataFrame.unionByName, [family_values(spark, sf_dir, f, dealt) for f in families])


@dataclass(frozen=True)
class Wide:
    """Rows with their virtual table, ``table_id``, the parts of their key and the dataset columns: long only where read so."""

    df: DataFrame
    columns: tuple[str, ...]
    keys: tuple[str, ...]


def wide_family(spark: SparkSession, sf_dir: str, family: Family, share: float | None = None, gone: DataFrame | None = None) -> Wide:
    """A family's rows written once, dealt over all cores, as a file of one row group is one task.

    ``share``: that of tables in other units, see :func:`apply_unit_shift`; ``gone`` (``family, key``): rows left out."""
    keys = [F.expr(k).alias(f"key{i}") for i, k in enumerate(family.key)]
    df = load_table(spark, sf_dir, family.table)
    df = df.select(F.expr(family.shard).alias("table_id"), *keys, *[F.col(c) if share is None else as_numeric(df, c).alias(c) for c in family.columns])
    df = df.repartition(max(8, spark.sparkContext.defaultParallelism), "key0")
    if gone is not None:
        own = gone.filter(F.col("family") == family.table).select(F.col("key").cast("long").alias("gone"))
        df = df.join(own, F.col("key0") == F.col("gone"), "left_anti")
    if share is not None:
        df = df.withColumns({c: shifted_unit(F.col(c), share=share) for c in family.columns})
    return Wide(cut(df, f"workload-{family.table}"), family.columns, tuple(f"key{i}" for i in range(len(keys))))


def wide_flags(spark: SparkSession, sf_dir: str, variables: int = 12, seed: int = 5, words: bool = False) -> Wide:
    """:func:`flag_datasets`, a column for each flag."""
    base = load_table(spark, sf_dir, "orders").select(F.expr(_FLAG_TABLE).alias("table_id"), F.col("o_orderkey").cast("string").alias("key0"))
    bits = {f"flag{v}": priority_bits(seed, F.lit(v), F.col("key0")) % 2 for v in range(1, variables + 1)}
    df = base.repartition(max(8, spark.sparkContext.defaultParallelism), "key0")
    return Wide(cut(df.select("*", *[((b == 1).cast("string") if words else b.cast("double")).alias(c) for c, b in bits.items()]), "workload-flags"), tuple(bits), ("key0",))


def long_of(wides: list[Wide]) -> DataFrame:
    """The values of :func:`repository_values`, unpivoted anew in each pass over the wide rows."""
    one = lambda w: columnize(w.df, F.col("table_id"), list(w.columns), [F.col(k) for k in w.keys]).select("dataset_id", "table_id", plain_label(F.col("column")).alias("variable"), "row_key", "value_num", "value_str")
    return reduce(DataFrame.unionByName, [one(w) for w in wides])


def sizes_of(wides: list[Wide]) -> DataFrame:
    """:func:`truth_of`, counted in the wide rows."""

    def one(w: Wide) -> DataFrame:
        n = w.df.groupBy("table_id").agg(*[F.count(F.when(not_missing(F.col(c), w.df.schema[c].dataType), 1)).alias(c) for c in w.columns])
        long = n.select("table_id", F.inline(F.array(*[F.struct(F.lit(c).alias("column"), F.col(c).alias("n_values")) for c in w.columns])))
        return long.filter("n_values > 0").select(F.concat_ws(".", "table_id", "column").alias("dataset_id"), "table_id", plain_label(F.col("column")).alias("variable"), "n_values")

    return reduce(DataFrame.unionByName, [one(w) for w in wides])


def truth_of(cv: DataFrame) -> DataFrame:
    """``dataset_id, table_id, variable, n_values``: kept apart from what is scored."""
    return cv.groupBy("dataset_id", "table_id", "variable").agg(F.count("*").alias("n_values"))


def apply_unit_shift(cv: DataFrame, seed: int = 77, share: float = 0.4) -> DataFrame:
    """Values of some tables in other units: a seeded ``share`` of the tables is scaled (cents, or degrees of another
    scale), which shifts their distributions and leaves their variables."""
    return cv.withColumn("value_num", shifted_unit(F.col("value_num"), seed, share))


def shifted_unit(value: Column, seed: int = 77, share: float = 0.4) -> Column:
    u = priority_bits(seed, F.col("table_id")) / F.lit(float(1 << 32))
    return F.when(u < share / 2, value * 100.0).when(u < share, value * 1.8 + 32.0).otherwise(value)


_FLAG_TABLE = "concat('flags:', substr(o_orderpriority, 1, 1), CAST(year(o_orderdate) AS STRING))"


def flag_datasets(spark: SparkSession, sf_dir: str, variables: int = 12, seed: int = 5, words: bool = False) -> DataFrame:
    """Look-alikes: unrelated even flags over the shards of one table, as 0 and 1 or as the words true and false."""
    base = load_table(spark, sf_dir, "orders").select(F.expr(_FLAG_TABLE).alias("table_id"), F.col("o_orderkey").cast("string").alias("row_key"))
    v = base.select("table_id", "row_key", F.explode(F.sequence(F.lit(1), F.lit(variables))).alias("v"))
    bit = priority_bits(seed, F.col("v"), F.col("row_key")) % 2
    number, word = (F.lit(None).cast("double"), (bit == 1).cast("string")) if words else (bit.cast("double"), F.lit(None).cast("string"))
    name = F.concat(F.lit("flag"), F.col("v").cast("string"))
    return v.select(F.concat_ws(".", "table_id", name).alias("dataset_id"), "table_id", name.alias("variable"), "row_key", number.alias("value_num"), word.alias("value_str"))


# ------------------------------------------------------------------ the same in DuckDB


def _duck(expr: str) -> str:
    return expr.replace("AS STRING", "AS VARCHAR")


def values_sql(families: tuple[Family, ...] = COARSE) -> str:
    """A select for the numeric datasets of ``families``."""
    parts = []
    for f in families:
        key = ", ".join(f"CAST({k} AS VARCHAR)" for k in f.key)
        for c in f.columns:
            label = c.split("_", 1)[1] if "_" in c and c.split("_", 1)[0].isalpha() else c
            parts.append(f"SELECT concat({_duck(f.shard)}, '.{c}') AS dataset_id, {_duck(f.shard)} AS table_id, '{label}' AS variable, concat_ws('|', {key}) AS row_key, CAST({c} AS DOUBLE) AS value_num FROM {f.table} WHERE {c} IS NOT NULL")
    return " UNION ALL ".join(parts)


def sizes_sql(families: tuple[Family, ...]) -> str:
    """``dataset_id, table_id, variable, n_values`` of ``families`` of any kind."""
    label = lambda c: c.split("_", 1)[1] if "_" in c and c.split("_", 1)[0].isalpha() else c
    one = lambda f, c: f"SELECT concat({_duck(f.shard)}, '.{c}') AS dataset_id, {_duck(f.shard)} AS table_id, '{label(c)}' AS variable, count(*) AS n_values FROM {f.table} WHERE {c} IS NOT NULL GROUP BY ALL"
    return " UNION ALL ".join(one(f, c) for f in families for c in f.columns)


def role_sql(share: float = 0.25, seed: int = 42) -> str:
    return f"CASE WHEN {priority_sql(seed, 'table_id')} < {share} THEN 'T' ELSE 'R' END"
