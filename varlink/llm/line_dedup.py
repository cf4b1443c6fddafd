"""Operator 10: line deduplication.

Lines are split off, normalised (ASCII white space stripped, ``A-Z`` lower-cased) and hashed; the documents that hold
each hash are counted; lines over the threshold are dropped everywhere but in the largest ``doc_id`` that holds them,
and the other lines are joined again in their order.

Only ``(hash, doc_id)`` pairs travel: they are grouped by both first, so a line that a third of all documents share is
counted by partial sums, and the decisions come back to a document as the list of its own dropped hashes. A line's key
is its 128-bit digest.

Edge cases: a null or empty text is one empty line, a null text stays null in :func:`drop_repeated_lines`; rows with the
same ``doc_id`` count as one document and are cut alike; rows with a null ``doc_id`` count for nothing and keep all
lines.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ASCII_SPACE_CHARS, ascii_lower, byte_slices, cut, fresh

MIN_KEY, MIN_DOCS = 20, 3


def line_hashes(text: Column, min_key: int = MIN_KEY) -> Column:
    """The distinct hashes of the keys of ``text`` that are long enough to count."""
    keys = F.transform(F.split(ascii_lower(text), "\n", -1), lambda x: F.btrim(x, F.lit(ASCII_SPACE_CHARS)))
    keys = F.array_distinct(F.filter(keys, lambda x: F.char_length(x) >= min_key))
    return F.transform(keys, lambda x: F.unhex(F.md5(x.cast("binary"))))


def line_pairs(docs: DataFrame, min_key: int = MIN_KEY) -> DataFrame:
    """Distinct ``line_hash, doc_id``."""
    rows = docs.filter("doc_id IS NOT NULL AND text IS NOT NULL").select("doc_id", F.explode(line_hashes(F.col("text"), min_key)).alias("line_hash"))
    return rows.select("line_hash", "doc_id").distinct()


def over_threshold(pairs: DataFrame, min_docs: int = MIN_DOCS) -> DataFrame:
    """Hashes found in at least ``min_docs`` documents: ``line_hash, keeper`` (the largest ``doc_id``)."""
    return pairs.groupBy("line_hash").agg(F.count("*").alias("n"), F.max("doc_id").alias("keeper")).filter(F.col("n") >= min_docs).drop("n")


def cut_lines(text: str | None, gone: set[bytes], min_key: int = MIN_KEY) -> tuple[int, int, str]:
    """Lines of ``text``, how many of them are in ``gone``, and the text that is left."""
    lines = (text or "").split("\n")
    if not gone:
        return len(lines), 0, text or ""
    left = [x for x in lines if len(key := x.strip(ASCII_SPACE_CHARS)) < min_key or hashlib.md5(key.encode("utf-8", "surrogatepass").lower(), usedforsecurity=False).digest() not in gone]
    return len(lines), len(lines) - len(left), "\n".join(left)


def mark_lines(docs: DataFrame, min_key: int = MIN_KEY, min_docs: int = MIN_DOCS, keep: list[str] | None = None) -> tuple[DataFrame, str, str, str]:
    """``docs`` (or its columns ``keep``) with line counts and the text that is left, under the returned names."""
    keep = docs.columns if keep is None else keep
    own, gone, *added = fresh(docs, "doc", "gone", "n_lines", "n_dropped", "kept_text")
    pairs = cut(line_pairs(docs, min_key), "line-pairs")
    # a table of its own, so that the join has a plain exchange on either side and Spark can split a hot line's rows
    over = cut(over_threshold(pairs, min_docs), "line-over")
    drops = pairs.join(over, "line_hash").filter(F.col("doc_id") != F.col("keeper")).groupBy(F.col("doc_id").alias(own)).agg(F.collect_list("line_hash").alias(gone))
    carried = list(dict.fromkeys([*keep, "text"]))
    joined = docs.join(drops, F.col("doc_id") == F.col(own), "left").select(*[F.col(f"`{c}`") for c in carried], gone)
    fields = [T.StructField(added[0], T.LongType()), T.StructField(added[1], T.LongType()), T.StructField(added[2], T.StringType())]
    schema = T.StructType([joined.schema[c] for c in keep] + fields)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in byte_slices(batch, "text"):
                made = [cut_lines(t, set(g or ()), min_key) for t, g in zip(part.column("text").to_pylist(), part.column(gone).to_pylist(), strict=True)]
                n, d, t = zip(*made, strict=True)
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), pa.array(n, pa.int64()), pa.array(d, pa.int64()), pa.array(t, pa.string())], names=[*keep, *added])

    return joined.mapInArrow(run, schema), *added


def drop_repeated_lines(docs: DataFrame, min_key: int = MIN_KEY, min_docs: int = MIN_DOCS) -> DataFrame:
    """``docs`` with repeated lines dropped from ``text``; ``n_chars`` follows where it is a column.

    All documents stay, also those that lose every line.
    """
    marked, _, dropped, kept = mark_lines(docs, min_key, min_docs)
    new = {"text": F.when(F.col("`text`").isNotNull(), F.col(kept))}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col(dropped) > 0, F.char_length(F.col(kept))).otherwise(F.col("n_chars")).cast(docs.schema["n_chars"].dataType)
    return marked.select(*[(new[c] if c in new else F.col(f"`{c}`")).alias(c) for c in docs.columns])
