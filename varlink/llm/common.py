"""Helpers shared by the corpus operators: shared storage, whole-text expressions, Arrow kernels."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.scratch import cut, drop_cut, new_path, remove, shared_root

#: ASCII white space, as a regular-expression class body: space, TAB, LF, VT, FF, CR.
ASCII_SPACE = r"\x20\x09-\x0D"
#: The same characters, for trimming.
ASCII_SPACE_CHARS = " \t\n\x0b\x0c\r"
__all__ = ["cut", "drop_cut", "new_path", "remove", "shared_root"]
_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """One of the given tables, read by Spark only (``sf_dir`` may be any Hadoop path)."""
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


# ------------------------------------------------------------------ text expressions


def ascii_lower(text: Column) -> Column:
    """``A-Z`` lower-cased, other letters left alone; ASCII-only texts take the vectorised path."""
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, _UPPER, _UPPER.lower()))


def fresh(df: DataFrame, *wanted: str) -> list[str]:
    """Names for helper columns that clash with no column of ``df`` (case-insensitively)."""
    return free_names(df.columns, *(f"__{name}" for name in wanted))


def free_names(taken: list[str], *wanted: str) -> list[str]:
    """The ``wanted`` names, each with underscores added until it clashes with no name of ``taken``."""
    have, out = {c.lower() for c in taken}, []
    for name in wanted:
        while name.lower() in have:
            name += "_"
        have.add(name.lower())
        out.append(name)
    return out


# ------------------------------------------------------------------ Arrow kernels

#: Rows are handed to a kernel in slices of at most so many UTF-8 bytes (one row at least).
SLICE_BYTES = 4 << 20


def map_texts(df: DataFrame, text: str, fields: list[T.StructField], kernel: Callable[[list], list[list]], keep: list[str] | None = None) -> DataFrame:
    """``df`` (or its columns ``keep``) with new columns that ``kernel`` computes from the texts of one slice.

    ``kernel`` takes a list of strings (``None`` for null) and returns one list per field. Slices are bounded in bytes,
    so memory follows the longest text and not the batch.
    """
    keep = df.columns if keep is None else keep
    source = df.select(*[F.col(f"`{c}`") for c in dict.fromkeys([*keep, text])])
    schema = T.StructType([source.schema[c] for c in keep] + fields)
    names = [f.name for f in fields]
    kinds = [_ARROW[f.dataType.simpleString()] for f in fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in byte_slices(batch, text):
                made = kernel(part.column(text).to_pylist())
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), *(pa.array(v, k) for v, k in zip(made, kinds, strict=True))], names=[*keep, *names])

    return source.mapInArrow(run, schema)


def byte_slices(batch: pa.RecordBatch, column: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut ``batch`` into runs of rows whose values in ``column`` take at most ``limit`` bytes."""
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    start = total = 0
    for i, n in enumerate(sizes):
        if total + n > limit and i > start:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += n
    if len(sizes) > start:
        yield batch.slice(start)


_ARROW = {"bigint": pa.int64(), "int": pa.int32(), "double": pa.float64(), "boolean": pa.bool_(), "string": pa.string(), "binary": pa.binary()}
