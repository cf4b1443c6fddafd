"""Pooling: datasets to mean embeddings, in one pass and with sums that merge.

The state of a dataset is ``sum_h, sum_g, n`` (and ``sum_sq`` for the unbiased distance): states of disjoint parts add
up. A kernel sums per dataset within its partition, so the vectors of single values never leave a worker, and what is
shuffled is one row per (partition, dataset).
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.encoding import NUMERIC_ENCODERS
from ..functions.scores import query_vector, repository_vector
from ..functions.text import hashed_word_vector
from ..nets.bilstm import CharBiLstm, encode_bytes

_STATE = "dataset_id string, sum_h array<double>, sum_g double, sum_sq double, n double"
#: Datasets whose sums a kernel holds at once; beyond it, what it has is sent on and merged later.
HELD = 2000
_WORD = re.compile(r"[^\W\d_]{2,}")
#: Sums of values that a kernel over wide rows gathers at once.
GATHERED = 1 << 22
#: Values that pass through the network together.
BATCH = 2048
#: Strings of any length are processed whole; a padded batch of them has at most so many characters (one string at least).
BATCH_CHARS = 1 << 16


class NumericEncoder:
    """Numbers to network inputs."""

    def __init__(self, form: str = "bits"):
        self.form, self.value = form, "value_num"
        self.width = NUMERIC_ENCODERS[form][1]

    def __call__(self, values: np.ndarray) -> np.ndarray:
        return NUMERIC_ENCODERS[self.form][0](values)


class WordEncoder:
    """Fields to the mean vector of their words: a dictionary of trained vectors, or hashed character n-grams.

    Unknown words are skipped; a field without a known word gives the zero vector.
    """

    def __init__(self, vectors: dict[str, np.ndarray] | None = None, width: int = 300):
        self.vectors, self.value = vectors, "value_str"
        self.width, self.short = len(next(iter(vectors.values()))) if vectors else width, {}

    def __getstate__(self) -> dict:
        return self.__dict__ | {"short": {}}  # each process keeps its own

    def one(self, text: str) -> np.ndarray:
        """Short fields repeat and are kept; each distinct word of a field is looked up once."""
        text = text or ""
        if (known := self.short.get(text)) is not None:
            return known
        words = Counter(_WORD.findall(text.lower()))
        found = [(v, n) for w, n in words.items() if (v := self.vectors.get(w) if self.vectors else hashed_word_vector(w, self.width)) is not None]
        out = np.average([v for v, _ in found], axis=0, weights=[n for _, n in found]) if found else np.zeros(self.width)
        if len(text) <= 64 and len(self.short) < 20_000:
            out.flags.writeable = False
            self.short[text] = out
        return out

    def __call__(self, values) -> np.ndarray:
        return np.stack([self.one(v) for v in values]) if len(values) else np.zeros((0, self.width))


class StringEncoder:
    """General strings for the character network."""

    value = "value_str"

    def __call__(self, values):
        return list(values)


def run_network(net, x) -> tuple[np.ndarray, np.ndarray]:
    """h and g per value, in batches; strings are sorted by length first, so padding stays small."""
    n = len(x)
    h, g = np.zeros((n, net.n_out)), np.zeros(n)
    if isinstance(net, CharBiLstm):
        order, at = sorted(range(n), key=lambda i: len(x[i])), 0
        while at < n:
            # as many strings as keep the padded batch within BATCH_CHARS, by the longest of them
            size = BATCH
            while size > 1 and size * len(x[order[min(at + size, n) - 1]]) > BATCH_CHARS:
                size //= 2
            part = order[at : at + size]
            h[part], g[part] = net.forward(*encode_bytes([x[i] for i in part], net.max_len))
            at += size
        return h, g
    for at in range(0, n, BATCH):
        h[at : at + BATCH], g[at : at + BATCH] = net.forward_h(x[at : at + BATCH]), net.forward_g(x[at : at + BATCH])
    return h, g


def _flush(held: dict) -> pa.RecordBatch:
    keys = list(held)
    return pa.RecordBatch.from_arrays(
        [pa.array(keys), pa.array([held[k][0].tolist() for k in keys], pa.list_(pa.float64())), *(pa.array([float(held[k][i]) for k in keys], pa.float64()) for i in (1, 2, 3))], names=["dataset_id", "sum_h", "sum_g", "sum_sq", "n"]
    )


def column_states(wide: DataFrame, columns: list[str], net, encoder) -> DataFrame:
    """:func:`partial_states` of wide rows, ``table_id`` and ``columns``: neither values nor their counts are shuffled.

    Rows are gathered to at most ``GATHERED`` sums and bytes; of each column, a distinct value among them passes the
    network once and counts as often as its table has it.
    """
    sent, rows = wide.sparkSession.sparkContext.broadcast((net, encoder)), max(BATCH, GATHERED // net.n_out)
    numeric = encoder.value == "value_num"
    source = wide.select("table_id", *[F.col(c).cast("double" if numeric else "string").alias(c) for c in columns])

    def gathered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
        held: list = []
        for batch in batches:
            if held and (sum(b.num_rows for b in held) + batch.num_rows > rows or sum(b.nbytes for b in held) + batch.nbytes > 8 * GATHERED):
                yield pa.Table.from_batches(held).combine_chunks()
                held = []
            held.append(batch)
        if held:
            yield pa.Table.from_batches(held).combine_chunks()

    def coded(column: pa.ChunkedArray) -> tuple[np.ndarray, list]:
        d = column.combine_chunks().dictionary_encode(null_encoding="encode")
        d = d.combine_chunks() if isinstance(d, pa.ChunkedArray) else d
        return d.indices.to_numpy(zero_copy_only=False), d.dictionary.to_pylist()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, encode = sent.value
        held: dict[str, list] = {}
        for part in gathered(batches):
            tables, names = coded(part.column("table_id"))
            for c in columns:
                if numeric:
                    v = part.column(c).to_numpy().astype(np.float64)
                    here = ~np.isnan(v)
                    distinct, at = np.unique(v[here], return_inverse=True)
                else:
                    at, distinct = coded(part.column(c))
                    here = np.array([x is not None for x in distinct], bool)[at]
                    at = at[here]
                if not len(at):
                    continue
                used = np.zeros(len(distinct), bool)
                used[at] = True
                each = np.zeros((len(distinct), own.n_out + 3))
                for i in range(0, len(distinct), BATCH):
                    some = i + np.flatnonzero(used[i : i + BATCH])
                    if len(some):
                        h, g = run_network(own, encode(distinct[some] if numeric else [distinct[k] for k in some]))
                        each[some] = np.c_[h, g, (h * h).sum(axis=1), np.ones(len(some))]
                pairs, times = np.unique(tables[here].astype(np.int64) * len(distinct) + at, return_counts=True)
                table, value = np.divmod(pairs, len(distinct))
                starts = np.flatnonzero(np.r_[True, np.diff(table) > 0])
                sums = np.add.reduceat(each[value] * times[:, None], starts, axis=0)
                for t, s in zip(table[starts], sums, strict=True):
                    name = c if names[t] is None else f"{names[t]}.{c}"
                    new = [s[: own.n_out], s[-3], s[-2], s[-1]]
                    held[name] = [x + y for x, y in zip(held[name], new, strict=True)] if name in held else new
            if len(held) >= HELD:
                yield _flush(held)
                held = {}
        if held:
            yield _flush(held)

    return source.mapInArrow(run, _STATE)


def partial_states(cv: DataFrame, net, encoder) -> DataFrame:
    """One state per (partition, dataset) of ``dataset_id, <value>`` and optionally ``weight``."""
    weighted = "weight" in cv.columns
    source = cv.select("dataset_id", encoder.value, *([F.col("weight").cast("double").alias("weight")] if weighted else []))
    sent = cv.sparkSession.sparkContext.broadcast((net, encoder))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, encode = sent.value
        held: dict[str, list] = {}
        for batch in batches:
            for at in range(0, batch.num_rows, BATCH):
                part = batch.slice(at, BATCH)
                values = part.column(encode.value)
                x = encode(values.to_numpy(zero_copy_only=False) if encode.value == "value_num" else values.to_pylist())
                h, g = run_network(own, x)
                w = part.column("weight").to_numpy(zero_copy_only=False) if weighted else np.ones(part.num_rows)
                coded = part.column("dataset_id").dictionary_encode()
                codes, names = coded.indices.to_numpy(), coded.dictionary.to_pylist()
                order = np.argsort(codes, kind="stable")
                starts = np.flatnonzero(np.r_[True, np.diff(codes[order]) > 0])
                sums = [np.add.reduceat(v[order], starts, axis=0) for v in (h * w[:, None], g * w, (h * h).sum(axis=1) * w, w)]
                for j, s in enumerate(starts):
                    name = names[codes[order[s]]]
                    if name in held:
                        for k in range(4):
                            held[name][k] = held[name][k] + sums[k][j]
                    else:
                        held[name] = [v[j] for v in sums]
                if len(held) >= HELD:
                    yield _flush(held)
                    held = {}
        if held:
            yield _flush(held)

    return source.mapInArrow(run, _STATE)


def merge_states(states: DataFrame, width: int) -> DataFrame:
    """Add the states of each dataset: sums per element, combined before the shuffle."""
    return states.groupBy("dataset_id").agg(F.array(*[F.sum(F.col("sum_h")[i]) for i in range(width)]).alias("sum_h"), F.sum("sum_g").alias("sum_g"), F.sum("sum_sq").alias("sum_sq"), F.sum("n").alias("n"))


def merge_states_wide(states: DataFrame) -> DataFrame:
    """The same for wide vectors: the elements are added in a kernel per group, not in one long generated expression.

    A group has one row per partition of the scan, each one vector.
    """

    def add(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"dataset_id": [key[0]], "sum_h": [np.sum(np.stack(list(frame["sum_h"])), axis=0).tolist()], "sum_g": [frame["sum_g"].sum()], "sum_sq": [frame["sum_sq"].sum()], "n": [frame["n"].sum()]})

    return states.groupBy("dataset_id").applyInPandas(add, _STATE)


def finalize(states: DataFrame, kind: str = "numeric", model_id: str = "model") -> DataFrame:
    """Vectors from states: ``dataset_id, kind, h, g, spread, s, n_used, model_id``; ``s`` is the search vector."""
    mean = F.transform("sum_h", lambda x: x / F.col("n"))
    out = states.select("dataset_id", F.lit(kind).alias("kind"), mean.alias("h"), (F.col("sum_g") / F.col("n")).alias("g"), "sum_sq", "n")
    inner = F.aggregate("h", F.lit(0.0), lambda s, x: s + x * x)
    spread = F.when(F.col("n") > 1, (F.col("sum_sq") / F.col("n") - inner) / (F.col("n") - 1)).otherwise(F.lit(0.0))
    return out.select("dataset_id", "kind", "h", "g", spread.alias("spread"), repository_vector(F.col("h"), F.col("g")).alias("s"), F.col("n").cast("long").alias("n_used"), F.lit(model_id).alias("model_id"))


def embed_datasets(cv: DataFrame, net, encoder=None, kind: str = "numeric", model_id: str = "model") -> DataFrame:
    """Mean embeddings of all datasets in ``cv``; a ``weight`` column pools by multiplicity."""
    encoder = encoder or NumericEncoder()
    return of_states(partial_states(cv, net, encoder), net, kind, model_id)


def of_states(states: DataFrame, net, kind: str = "numeric", model_id: str = "model") -> DataFrame:
    """Vectors from states that are yet to be added up."""
    merged = merge_states(states, net.n_out) if net.n_out <= 16 else merge_states_wide(states)
    return finalize(merged, kind, model_id)


def embed_values(cv: DataFrame, net, encoder=None) -> DataFrame:
    """``cv`` with h and g of every value: the plain path, for tests and inspection."""
    encoder = encoder or NumericEncoder()
    sent = cv.sparkSession.sparkContext.broadcast((net, encoder))
    columns = cv.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, encode = sent.value
        for batch in batches:
            for at in range(0, batch.num_rows, BATCH):
                part = batch.slice(at, BATCH)
                values = part.column(encode.value)
                h, g = run_network(own, encode(values.to_numpy(zero_copy_only=False) if encode.value == "value_num" else values.to_pylist()))
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in columns), pa.array(h.tolist(), pa.list_(pa.float64())), pa.array(g)], names=[*columns, "h", "g"])

    from pyspark.sql import types as T

    return cv.mapInArrow(run, T.StructType([*cv.schema.fields, T.StructField("h", T.ArrayType(T.DoubleType())), T.StructField("g", T.DoubleType())]))


def query_vectors(vectors: DataFrame) -> DataFrame:
    """``query_id`` with its search vector."""
    return vectors.select(F.col("dataset_id").alias("query_id"), "h", "g", query_vector(F.col("h"), F.col("g")).alias("s"))
