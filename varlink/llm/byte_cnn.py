"""Operator 5: quality classifier, a byte-level convolutional network in numpy.

Bytes are embedded, convolved with learned filters of several widths over overlapping chunks that cover the whole text,
max-pooled over all places of all chunks, and combined into one probability. Since the embedding is linear in the byte,
a filter's response is a sum of table rows, one per byte of its window; the tables have 256 rows.

The network is trained on the driver on a bounded sample of labelled rows (at most ``sample_rows``, chosen by a hash of
the id) for at most ``epochs`` rounds and about ``steps`` steps, and sent to the executors, about 50 KB. The bound is one of rows: each is learned from as a whole, pooled over all
its chunks as in scoring, so the driver needs memory in proportion to ``sample_rows`` times the texts' length.

Edge cases: null and empty texts have no window; their pooled features are zero and they get the score that the output
layer gives to these. Texts shorter than a filter are padded with spaces. Without any labelled row, or with labels of
one class only, every score is the (smoothed) share of that class. Of several rows with one id the sample takes one text
(the one with the smallest hash), of several labels the smallest. Kept columns that have the name of a result stay, and
the result takes a name of its own. An empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import free_names, map_texts


@dataclass(frozen=True)
class CnnConfig:
    widths: tuple[int, ...] = (2, 3, 5)
    filters: int = 8
    embed: int = 6
    chunk: int = 8192
    sample_rows: int = 3000
    epochs: int = 30
    steps: int = 1000
    batch: int = 32
    step: float = 4e-3
    decay: float = 1e-4
    seed: int = 7


CONFIG = CnnConfig()
THRESHOLD = 0.3


def as_bytes(raw: bytes, widths: tuple[int, ...]) -> np.ndarray:
    """The text's bytes, padded to the widest filter; an empty text stays empty."""
    return np.frombuffer(raw if len(raw) >= max(widths) or not raw else raw.ljust(max(widths), b" "), np.uint8)


def peaks(data: np.ndarray, tables: list[np.ndarray], chunk: int) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Per width, each filter's largest response over the whole of ``data`` and where it begins.

    Chunks overlap by the widest filter, so every window is seen; ties go to the first place.
    """
    widest = max(len(t) for t in tables)
    best = [np.full(t.shape[2], -np.inf, np.float32) for t in tables]
    place = [np.zeros(t.shape[2], np.int64) for t in tables]
    for at in range(0, len(data) - widest + 1, chunk):
        part = data[at : at + chunk + widest - 1]
        for k, table in enumerate(tables):
            w = len(table)
            total = table[0].take(part[: len(part) - w + 1], axis=0)
            for i in range(1, w):
                total += table[i].take(part[i : len(part) - w + 1 + i], axis=0)
            top = total.argmax(axis=0)
            high = total[top, np.arange(total.shape[1])]
            more = high > best[k]
            best[k] = np.where(more, high, best[k])
            place[k] = np.where(more, at + top, place[k])
    return best, place


@dataclass
class ByteCnn:
    """Tables per width (``width x 256 x filters``), their biases, and the output layer over the pooled features."""

    tables: list[np.ndarray]
    bias: list[np.ndarray]
    out: np.ndarray
    out_bias: float
    config: CnnConfig = field(default_factory=CnnConfig)

    def pooled(self, raw: bytes) -> np.ndarray:
        """Max-pooled responses over all chunks of ``raw``."""
        if not raw:
            return np.zeros(sum(len(b) for b in self.bias), np.float32)
        best, _ = peaks(as_bytes(raw, self.config.widths), self.tables, self.config.chunk)
        return np.tanh(np.concatenate([p + b for p, b in zip(best, self.bias, strict=True)]).clip(0))

    def score(self, text: str | None) -> float:
        raw = (text or "").encode("utf-8", "surrogatepass")
        return float(1 / (1 + np.exp(-(self.pooled(raw).astype(np.float64) @ self.out + self.out_bias))))


def train(texts: list[bytes], labels: np.ndarray, config: CnnConfig = CONFIG) -> ByteCnn:
    """Adam on the cross entropy; gradients pass to the window of each filter's maximum."""
    c, rng = config, np.random.default_rng(config.seed)
    share = (labels.sum() + 1) / (len(labels) + 2)
    n_features = c.filters * len(c.widths)
    p = {"E": rng.normal(0, 0.5, (256, c.embed)), "out": rng.normal(0, 0.3, n_features), "b": np.array(np.log(share / (1 - share)))}
    for k, w in enumerate(c.widths):
        p[f"W{k}"], p[f"c{k}"] = rng.normal(0, 1 / np.sqrt(w * c.embed), (w, c.embed, c.filters)), np.zeros(c.filters)

    def model() -> ByteCnn:
        tables = [np.einsum("be,wef->wbf", p["E"], p[f"W{k}"]).astype(np.float32) for k in range(len(c.widths))]
        return ByteCnn(tables, [p[f"c{k}"].astype(np.float32) for k in range(len(c.widths))], p["out"].copy(), float(p["b"]), c)

    if len(labels) == 0 or labels.min() == labels.max():
        p["out"][:] = 0
        return model()
    m1, m2, t = {k: np.zeros_like(v) for k, v in p.items()}, {k: np.zeros_like(v) for k, v in p.items()}, 0
    data = [as_bytes(x, c.widths) for x in texts]
    # rows of the rarer class count for more, by the square root of the odds
    odds = np.sqrt(share / (1 - share))
    weight = np.where(labels == 1, np.clip(1 / odds, 1, 4), np.clip(odds, 1, 4))
    for _ in range(c.epochs):
        order = rng.permutation(len(data))
        for at in range(0, len(order) if t < c.steps else 0, c.batch):
            rows = order[at : at + c.batch]
            tables = model().tables
            grad = {k: np.zeros_like(v) for k, v in p.items()}
            feats, places = np.zeros((len(rows), n_features)), []
            for j, r in enumerate(rows):
                if not len(data[r]):  # no window: the features stay zero and nothing flows back
                    places.append([np.zeros((c.filters, w), np.uint8) for w in c.widths])
                    continue
                best, place = peaks(data[r], tables, c.chunk)
                places.append([data[r][place[k][:, None] + np.arange(w)] for k, w in enumerate(c.widths)])
                feats[j] = np.concatenate([b + p[f"c{k}"] for k, b in enumerate(best)])
            act = np.tanh(feats.clip(0))
            z = act @ p["out"] + p["b"]
            d = (1 / (1 + np.exp(-z)) - labels[rows]) * weight[rows] / len(rows)
            grad["out"], grad["b"] = act.T @ d + c.decay * p["out"], d.sum()
            back = d[:, None] * p["out"] * (1 - act**2) * (feats > 0)
            for k, w in enumerate(c.widths):
                g = back[:, k * c.filters : (k + 1) * c.filters]
                grad[f"c{k}"] += g.sum(axis=0)
                windows = np.stack([own[k] for own in places])  # rows x filters x width
                for i in range(w):
                    e = p["E"][windows[:, :, i]]  # rows x filters x embed
                    grad[f"W{k}"][i] += np.einsum("rfe,rf->ef", e, g)
                    np.add.at(grad["E"], windows[:, :, i], g[:, :, None] * p[f"W{k}"][i].T[None])
            t += 1
            for k in p:
                m1[k] = 0.9 * m1[k] + 0.1 * grad[k]
                m2[k] = 0.999 * m2[k] + 0.001 * grad[k] ** 2
                p[k] = p[k] - c.step * (m1[k] / (1 - 0.9**t)) / (np.sqrt(m2[k] / (1 - 0.999**t)) + 1e-8)
    return model()


def held_out(doc_id: Column) -> Column:
    """True for the fifth of the ids whose labels are never learned from."""
    return (F.crc32(doc_id.cast("string").cast("binary")) % 5) == 0


def training_sample(docs: DataFrame, labels: DataFrame, config: CnnConfig = CONFIG) -> DataFrame:
    """At most ``sample_rows`` labelled rows outside the held-out fifth, with ``doc_id``, ``raw`` (whole texts) and ``label``."""
    known = labels.filter("doc_id IS NOT NULL AND quality IS NOT NULL").filter(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.min("quality").alias("label"))
    # the sample is chosen among the ids, before any text moves
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(config.sample_rows)
    raw = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    return docs.select("doc_id", raw.alias("raw")).join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "label").agg(F.min_by("raw", F.xxhash64("raw")).alias("raw"))


def fit(docs: DataFrame, labels: DataFrame, config: CnnConfig = CONFIG) -> ByteCnn:
    rows = sorted(training_sample(docs, labels, config).collect(), key=lambda r: r["doc_id"])
    return train([bytes(r["raw"]) for r in rows], np.array([r["label"] for r in rows], float), config)


def score_quality(docs: DataFrame, model: ByteCnn, threshold: float = THRESHOLD, keep: list[str] | None = None) -> DataFrame:
    """``docs`` with ``score`` and ``predicted`` as last columns, under names that clash with no kept one."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def kernel(texts: list) -> list[list]:
        scores = [sent.value.score(t) for t in texts]
        return [scores, [int(s >= threshold) for s in scores]]

    keep = docs.columns if keep is None else keep
    score, predicted = free_names(keep, "score", "predicted")
    return map_texts(docs, "text", [T.StructField(score, T.DoubleType()), T.StructField(predicted, T.IntegerType())], kernel, keep)
