"""Tables to datasets: one dataset per column, its values long, missing ones dropped.

The long form is ``dataset_id, kind, value_num, value_str, weight`` (with ``row_key`` where rows must be told apart).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.sampling import priority, priority_bits
from ..functions.text import strip_html, words

_NUMERIC = (T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.FloatType, T.DoubleType, T.DecimalType)


def not_missing(c: Column, kind: T.DataType) -> Column:
    return c.isNotNull() & ~F.isnan(c.cast("double")) if isinstance(kind, (T.FloatType, T.DoubleType)) else c.isNotNull()


def as_numeric(df: DataFrame, name: str) -> Column | None:
    """A column as double: numbers as they are, dates as epoch days, timestamps as epoch seconds, intervals as seconds."""
    kind, c = df.schema[name].dataType, F.col(f"`{name}`")
    if isinstance(kind, _NUMERIC):
        return c.cast("double")
    if isinstance(kind, T.DateType):
        return F.datediff(c, F.lit("1970-01-01").cast("date")).cast("double")
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return F.unix_seconds(c.cast("timestamp")).cast("double")
    if isinstance(kind, T.DayTimeIntervalType):
        return (F.lit("1970-01-01 00:00:00").cast("timestamp") + c).cast("double")
    return None


def flatten_nested(df: DataFrame, depth: int = 3) -> DataFrame:
    """Struct leaves as columns ``a.b``; arrays, maps and binaries stay (and are no datasets)."""
    for _ in range(depth):
        out, again = [], False
        for f in df.schema:
            if isinstance(f.dataType, T.StructType):
                again = True
                out += [F.col(f"`{f.name}`").getField(x.name).alias(f"{f.name}.{x.name}") for x in f.dataType]
            else:
                out.append(F.col(f"`{f.name}`"))
        df = df.select(*out)
        if not again:
            break
    return df


def flatten_json(df: DataFrame, name: str, leaves: dict[str, str]) -> DataFrame:
    """Adds a column ``<name>.<leaf>`` per JSON path of ``leaves`` (leaf to Spark type)."""
    made = {f"{name}.{k}": F.get_json_object(F.col(f"`{name}`"), f"$.{k}").cast(v) for k, v in leaves.items()}
    return df.withColumns(made)


def columnize(df: DataFrame, table_id: str | Column, columns: list[str] | None = None, row_id: list[Column] | None = None) -> DataFrame:
    """Unpivot ``df`` into ``table_id, column, dataset_id, value_num, value_str`` (and ``row_key``), without a shuffle.

    Numeric and string columns go to their own value column; arrays, maps and binaries are left out. One ``Expand`` over
    a pruned scan serves all columns.
    """
    table = F.lit(table_id) if isinstance(table_id, str) else table_id
    entries = []
    for name in columns or df.columns:
        c, kind = F.col(f"`{name}`"), df.schema[name].dataType
        num = as_numeric(df, name)
        if num is not None:
            entries.append(F.struct(F.lit(name).alias("column"), num.alias("value_num"), F.lit(None).cast("string").alias("value_str")))
        elif isinstance(kind, (T.StringType, T.BooleanType)):
            entries.append(F.struct(F.lit(name).alias("column"), F.lit(None).cast("double").alias("value_num"), c.cast("string").alias("value_str")))
    key = [F.concat_ws("|", *[k.cast("string") for k in row_id]).alias("row_key")] if row_id else []
    long = df.select(table.alias("table_id"), *key, F.inline(F.array(*entries)))
    long = long.filter((F.col("value_num").isNotNull() & ~F.isnan("value_num")) | F.col("value_str").isNotNull())
    return long.withColumn("dataset_id", F.concat_ws(".", "table_id", "column"))


def columnize_by_unpivot(df: DataFrame, table_id: str, columns: list[str]) -> DataFrame:
    """The same for numeric columns through ``unpivot``: ``dataset_id, value_num``."""
    wide = df.select(*[as_numeric(df, c).alias(c) for c in columns])
    long = wide.unpivot([], columns, "column", "value_num")
    return long.filter(F.col("value_num").isNotNull() & ~F.isnan("value_num")).select(F.concat(F.lit(f"{table_id}."), "column").alias("dataset_id"), "column", "value_num")


def value_histogram(cv: DataFrame, by: tuple[str, ...] = ("dataset_id",), value: str = "value_num") -> DataFrame:
    """Distinct values with their multiplicity: each is embedded once."""
    w = F.sum("weight") if "weight" in cv.columns else F.count("*")
    return cv.groupBy(*by, F.col(value)).agg(w.alias("weight"))


def dataset_stats(cv: DataFrame, by: tuple[str, ...] = ("dataset_id",), value: str = "value_num") -> DataFrame:
    """Count, mean and standard deviation per dataset; partial sums before the one small shuffle."""
    v = F.col(value)
    return cv.groupBy(*by).agg(F.count(v).alias("n"), F.avg(v).alias("mean"), F.coalesce(F.stddev_samp(v), F.lit(0.0)).alias("sd"))


def approx_stats(cv: DataFrame, value: str = "value_num", accuracy: int = 1000) -> DataFrame:
    """Sketched distinct count, quartiles and the choice of pooling over distinct values or over a sample."""
    v = F.col(value)
    out = cv.groupBy("dataset_id").agg(F.count(v).alias("n"), F.approx_count_distinct(v).alias("n_distinct"), F.percentile_approx(v, [0.25, 0.5, 0.75], accuracy).alias("quartiles"))
    return out.withColumn("by_distinct", F.col("n_distinct") <= 1000)


# ------------------------------------------------------------------ samples


def subsample(cv: DataFrame, n: int = 1000, seed: int = 42, key: str = "row_key", by: tuple[str, ...] = ("dataset_id",), slack: float = 4.0) -> DataFrame:
    """At most ``n`` rows of every dataset, without replacement: those of the lowest priority.

    Datasets of more than ``slack * n`` rows are first thinned by priority to about that many, from their counted sizes,
    before anything is sorted or shuffled; at the default ``slack`` and n = 1000 a thinned dataset falling short of n is
    a deviation of 47 standard deviations.
    """
    ranked = cv.withColumn("priority", priority(seed, *[F.col(b) for b in by], F.col(key)))
    sizes = cv.groupBy(*by).agg(F.count("*").alias("size")).filter(F.col("size") > n * slack)
    limit = F.least(F.lit(1.0), (n * slack) / F.col("size"))
    thinned = ranked.join(sizes, list(by), "left").filter((F.col("size").isNull()) | (F.col("priority") < limit)).drop("size")
    order = Window.partitionBy(*by).orderBy("priority", key)
    return thinned.withColumn("rank_no", F.row_number().over(order)).filter(F.col("rank_no") <= n).drop("rank_no")


def downsample_fraction(cv: DataFrame, fraction: float, seed: int = 42, key: str = "row_key") -> DataFrame:
    """A seeded fraction of every dataset: a map-side filter."""
    return cv.filter(priority(seed, F.col("dataset_id"), F.col(key)) < fraction)


def split_halves(cv: DataFrame, seed: int = 7, key: str = "row_key") -> DataFrame:
    """Adds ``half`` (0 or 1), disjoint and stable."""
    return cv.withColumn("half", (priority_bits(seed, F.col(key)) % 2).cast("int"))


def split_augment(cv: DataFrame, copies: int, seed: int = 11, key: str = "row_key", low: float = 0.1, high: float = 0.9) -> DataFrame:
    """Each dataset as ``copies`` pairs of disjoint parts of random proportion: ``pair_id, side`` are added.

    All rows of ``cv`` are dealt; side 0 takes those below the pair's own proportion.
    """
    pairs = cv.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
    share = low + (high - low) * priority(seed, F.col("dataset_id"), F.col("copy"))
    side = (priority(seed + 1, F.col("dataset_id"), F.col("copy"), F.col(key)) >= share).cast("int")
    return pairs.withColumns({"pair_id": F.concat_ws("#", "dataset_id", F.col("copy").cast("string")), "side": side}).drop("copy")


# ------------------------------------------------------------------ kinds


def build_vocab(texts: DataFrame, min_rows: int = 5) -> DataFrame:
    """Words (two letters or more) of string column ``value_str`` seen in at least ``min_rows`` rows."""
    return texts.select(F.explode(F.array_distinct(words(F.col("value_str")))).alias("word")).groupBy("word").agg(F.count("*").alias("n_rows")).filter(F.col("n_rows") >= min_rows)


def code_like(value: Column) -> Column:
    """Urls and code-like names: a scheme, or digits, ``#``, ``_`` or braces in a value of at most three words."""
    return value.rlike(r"^[a-z]+://") | (value.rlike(r"[0-9#_{}]") & (F.size(F.split(value, r"\s+")) <= 3))


def infer_kind(cv: DataFrame, vocab: DataFrame, majority: float = 0.5, rule: str = "words") -> DataFrame:
    """``dataset_id, kind`` (numeric, language or string) and the share of language fields.

    ``rule="words"``: a field is language when more than ``majority`` of its words are known; ``rule="any"``: when any is
    known. A dataset is language when more than ``majority`` of its fields are. Distinct values are judged once and
    weighted; markup is stripped first.
    """
    num = cv.filter("value_num IS NOT NULL").groupBy("dataset_id").agg(F.lit("numeric").alias("kind"), F.lit(0.0).alias("language_share"))
    fields = value_histogram(cv.filter("value_str IS NOT NULL"), value="value_str").withColumn("field", F.xxhash64("dataset_id", "value_str"))
    plain = F.when(F.col("value_str").rlike(r"(?i)<html|</\w+>"), strip_html(F.col("value_str"))).otherwise(F.col("value_str"))
    parts = fields.filter(~code_like(F.col("value_str"))).select("dataset_id", "field", F.explode(words(plain)).alias("word"))
    known = parts.join(vocab.select("word").withColumn("known", F.lit(1)), "word", "left").groupBy("dataset_id", "field").agg(F.avg(F.coalesce("known", F.lit(0))).alias("share"))
    is_language = (F.col("share") > majority) if rule == "words" else (F.col("share") > 0)
    judged = fields.join(known, ["dataset_id", "field"], "left").withColumn("language", F.coalesce(is_language.cast("int"), F.lit(0)))
    share = F.sum(F.col("language") * F.col("weight")) / F.sum("weight")
    text = judged.groupBy("dataset_id").agg(share.alias("language_share")).select("dataset_id", F.when(F.col("language_share") > majority, "language").otherwise("string").alias("kind"), "language_share")
    return num.unionByName(text)

