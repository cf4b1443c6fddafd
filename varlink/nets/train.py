"""Training on triplets of datasets: on the driver for packed repositories, or by gradients summed over executors."""

from __future__ import annotations

import pickle
import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

from .bilstm import CharBiLstm, encode_bytes
from .mlp import Params, SetNet
from .objectives import OBJECTIVES, pick_negatives


@dataclass
class TrainConfig:
    step: float = 1e-3
    batch: int = 32
    steps_per_epoch: int = 40
    epochs: int = 30
    patience: int = 5
    min_delta: float = 1e-3
    values: int = 64
    augment: float = 0.25
    objective: str = "xent"
    sampler: str = "uniform"
    seed: int = 42


@dataclass
class Packed:
    """Datasets packed for training: per dataset an array of inputs (rows of features, or strings), its variable and
    its weights; ``variable`` None marks datasets without any annotated match."""

    ids: list[str]
    inputs: list
    variable: list
    table: list[str] | None = None


class Adam:
    def __init__(self, params: Params, step: float, b1: float = 0.9, b2: float = 0.999, eps: float = 1e-8):
        self.step, self.b1, self.b2, self.eps, self.t = step, b1, b2, eps, 0
        self.m, self.v = {k: np.zeros_like(x) for k, x in params.items()}, {k: np.zeros_like(x) for k, x in params.items()}

    def update(self, params: Params, grad: Params) -> None:
        self.t += 1
        for k, g in grad.items():
            self.m[k] = self.b1 * self.m[k] + (1 - self.b1) * g
            self.v[k] = self.b2 * self.v[k] + (1 - self.b2) * g * g
            params[k] -= self.step * (self.m[k] / (1 - self.b1**self.t)) / (np.sqrt(self.v[k] / (1 - self.b2**self.t)) + self.eps)


# ------------------------------------------------------------------ triplets


class TripletSampler:
    """Seeded triplets: an anchor with a positive of its variable and a negative of another.

    A pair without annotation counts as unmatched. A share ``augment`` of the positives are two disjoint random parts of
    one dataset. Negatives come from a random table first where tables are known, so wide tables do not dominate.
    """

    def __init__(self, data: Packed, config: TrainConfig):
        self.data, self.c, self.rng = data, config, np.random.default_rng(config.seed)
        groups: dict = {}
        for i, v in enumerate(data.variable):
            if v is not None:
                groups.setdefault(v, []).append(i)
        self.groups = {v: np.array(g) for v, g in groups.items() if len(g) > 1}
        self.names = sorted(self.groups, key=str)
        self.big = [i for i, x in enumerate(data.inputs) if len(x) >= 4]
        self.tables: dict = {}
        for i, t in enumerate(data.table or data.ids):
            self.tables.setdefault(t, []).append(i)
        self.table_names = sorted(self.tables)

    def take(self, i: int, part: slice | np.ndarray | None = None):
        x = self.data.inputs[i]
        idx = np.arange(len(x)) if part is None else part
        if len(idx) > self.c.values:
            idx = self.rng.choice(idx, self.c.values, replace=False)
        return x[idx] if isinstance(x, np.ndarray) else [x[j] for j in idx]

    def negative(self, a: int) -> int:
        for _ in range(64):
            t = self.tables[self.table_names[self.rng.integers(len(self.table_names))]]
            n = t[self.rng.integers(len(t))]
            if n != a and (self.data.variable[n] is None or self.data.variable[n] != self.data.variable[a]):
                return n
        raise ValueError("no dataset of another variable was found")

    def draw(self) -> tuple:
        """``(index, sample)`` of anchor, positive and negative."""
        rng = self.rng
        if self.big and (not self.names or rng.random() < self.c.augment):
            a = self.big[rng.integers(len(self.big))]
            order, share = rng.permutation(len(self.data.inputs[a])), rng.uniform(0.1, 0.9)
            cut = int(np.clip(round(share * len(order)), 1, len(order) - 1))
            pair = (a, self.take(a, order[:cut])), (a, self.take(a, order[cut:]))
        else:
            group = self.groups[self.names[rng.integers(len(self.names))]]
            a, p = rng.choice(group, 2, replace=False)
            pair = (a, self.take(a)), (p, self.take(p))
        n = self.negative(pair[0][0])
        return *pair, (n, self.take(n))


# ------------------------------------------------------------------ one step


def set_forward(net, sets: list) -> tuple[np.ndarray, np.ndarray, dict]:
    """Pooled h and g of the sets and what the way back needs."""
    sizes = np.array([len(s) for s in sets])
    owner = np.repeat(np.arange(len(sets)), sizes)
    cache: dict = {"owner": owner, "sizes": sizes}
    starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
    if isinstance(net, CharBiLstm):
        flat = [v for s in sets for v in s]
        distinct, where = np.unique(np.array(flat, dtype=object).astype(str), return_inverse=True)
        ids, length = encode_bytes(list(distinct), net.max_len)
        cache["net"] = {}
        h, g = net.forward(ids, length, cache["net"])
        cache["where"] = where
        h, g = h[where], g[where]
    else:
        x = np.concatenate(sets)
        cache["h"], cache["g"] = [], []
        h, g = net.forward_h(x, cache["h"]), net.forward_g(x, cache["g"] if net.use_g else None)
    return np.add.reduceat(h, starts, axis=0) / sizes[:, None], np.add.reduceat(g, starts) / sizes, cache


def set_backward(net, cache: dict, dh: np.ndarray, dg: np.ndarray, grad: Params) -> None:
    each_h, each_g = (dh / cache["sizes"][:, None])[cache["owner"]], (dg / cache["sizes"])[cache["owner"]]
    if isinstance(net, CharBiLstm):
        n = len(cache["net"]["h"])
        sum_h, sum_g = np.zeros((n, each_h.shape[1])), np.zeros(n)
        np.add.at(sum_h, cache["where"], each_h)
        np.add.at(sum_g, cache["where"], each_g)
        net.backward(cache["net"], sum_h, sum_g, grad)
    else:
        net.backward_h(cache["h"], each_h, grad)
        if net.use_g:
            net.backward_g(cache["g"], each_g, grad)


def triplet_gradient(net, anchors: list, positives: list, negatives: list, objective: str = "xent", variables: list | None = None, sampler: str = "uniform", rng=None) -> tuple[float, Params]:
    """Mean loss of the triplets and its gradient. Other samplers choose the negatives anew within the batch."""
    n, grad = len(anchors), net.zero_grad()
    h, g, cache = set_forward(net, [*anchors, *positives, *negatives])
    a, p, q = np.arange(n), np.arange(n, 2 * n), np.arange(2 * n, 3 * n)
    score = lambda i, j: ((h[i] - h[j]) ** 2).sum(axis=-1) + g[i] + g[j]
    dp = score(a, p)
    if sampler != "uniform":
        everyone = np.arange(3 * n)
        d = ((h[a][:, None] - h[None]) ** 2).sum(axis=2) + g[a][:, None] + g[None]
        v = np.array([str(x) for x in variables])
        q = pick_negatives(d, (v[a][:, None] != v[None]) & (everyone[None] != a[:, None]), dp, sampler, rng)
        q = np.where(q < 0, np.arange(2 * n, 3 * n), q)
    loss, sp, sn = OBJECTIVES[objective](dp, score(a, q))
    dh, dg = np.zeros_like(h), np.zeros_like(g)
    for j, s in ((p, sp), (q, sn)):
        step = 2 * (h[a] - h[j]) * s[:, None] / n
        np.add.at(dh, a, step)
        np.add.at(dh, j, -step)
        np.add.at(dg, a, s / n)
        np.add.at(dg, j, s / n)
    set_backward(net, cache, dh, dg, grad)
    return float(loss.mean()), grad


# ------------------------------------------------------------------ loops


@dataclass
class History:
    loss: list[float] = field(default_factory=list)
    seconds: float = 0.0
    gradient_norm: list[float] = field(default_factory=list)


def should_stop(losses: list[float], patience: int, min_delta: float) -> bool:
    """No epoch of the last ``patience`` brought the loss ``min_delta`` (relative) below the best before them."""
    if len(losses) <= patience:
        return False
    best = min(losses[:-patience])
    return min(losses[-patience:]) > best - min_delta * abs(best)


def train(net, data: Packed, config: TrainConfig | None = None) -> History:
    """Adam on the driver; the packed data are at most ``values`` inputs a dataset."""
    c = config or TrainConfig()
    sampler, adam, out, began = TripletSampler(data, c), Adam(net.params, c.step), History(), time.time()
    for _ in range(c.epochs):
        total = 0.0
        for _ in range(c.steps_per_epoch):
            batch = [sampler.draw() for _ in range(c.batch)]
            parts = [[x[k][1] for x in batch] for k in range(3)]
            variables = [data.variable[x[k][0]] for k in range(3) for x in batch]
            loss, grad = triplet_gradient(net, *parts, c.objective, variables, c.sampler, sampler.rng)
            adam.update(net.params, grad)
            total += loss
            out.gradient_norm.append(float(np.sqrt(sum((g * g).sum() for g in grad.values()))))
        out.loss.append(total / c.steps_per_epoch)
        if should_stop(out.loss, c.patience, c.min_delta):
            break
    out.seconds = time.time() - began
    return out


def gradient_step(net, triplets: DataFrame, objective: str = "xent") -> tuple[float, Params, int]:
    """Summed gradients of a DataFrame of triplets (``anchor, positive, negative``: arrays of inputs, rows flattened to
    ``n_in`` features each).

    Each partition sends one row (its loss, gradient and count), and these rows are merged in a tree over partitions;
    the driver gets one.
    """
    sent = triplets.sparkSession.sparkContext.broadcast(net)

    def part(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        loss, grad, count = 0.0, None, 0
        for f in frames:
            if not len(f):
                continue
            own = sent.value
            sets = [[np.asarray(list(x), np.float64).reshape(-1, own.n_in) for x in f[c]] for c in ("anchor", "positive", "negative")]
            one, g = triplet_gradient(own, *sets, objective)
            loss, count = loss + one * len(f), count + len(f)
            g = {k: v * len(f) for k, v in g.items()}
            grad = g if grad is None else {k: grad[k] + v for k, v in g.items()}
        if count:
            yield pd.DataFrame({"loss": [loss], "n": [count], "grad": [pickle.dumps(grad)]})

    def merge(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        loss, n, grad = 0.0, 0, None
        for f in frames:
            for one, m, g in zip(f["loss"], f["n"], f["grad"], strict=True):
                g = pickle.loads(g)
                loss, n, grad = loss + one, n + m, g if grad is None else {k: grad[k] + v for k, v in g.items()}
        if n:
            yield pd.DataFrame({"loss": [loss], "n": [n], "grad": [pickle.dumps(grad)]})

    schema = "loss double, n long, grad binary"
    sums, parts = triplets.mapInPandas(part, schema), max(1, triplets.rdd.getNumPartitions())
    while parts > 1:  # a tree: 16 gradients meet in a task
        parts = (parts + 15) // 16
        sums = sums.repartition(parts).mapInPandas(merge, schema)
    row = sums.first()
    if row is None:
        return 0.0, net.zero_grad(), 0
    return row["loss"] / row["n"], {k: v / row["n"] for k, v in pickle.loads(row["grad"]).items()}, row["n"]


def train_distributed(net, triplets: DataFrame, config: TrainConfig | None = None, steps: int = 20) -> History:
    """Full-batch Adam over a cached DataFrame of triplets: one broadcast and one gradient a step."""
    c = config or TrainConfig()
    adam, out, began = Adam(net.params, c.step), History(), time.time()
    for _ in range(steps):
        loss, grad, _ = gradient_step(net, triplets, c.objective)
        adam.update(net.params, grad)
        out.loss.append(loss)
        if should_stop(out.loss, c.patience, c.min_delta):
            break
    out.seconds = time.time() - began
    return out


# ------------------------------------------------------------------ storage


def save_model(spark, net, path: str, model_id: str) -> None:
    """Parameters as rows ``(model_id, shape, spec, name, values)``."""
    spec = {k: v for k, v in vars(net).items() if k != "params"} | {"class": type(net).__name__}
    rows = [(model_id, str(spec), k, list(map(int, v.shape)), v.ravel().astype(float).tolist()) for k, v in net.params.items()]
    spark.createDataFrame(rows, "model_id string, spec string, name string, shape array<int>, data array<double>").coalesce(1).write.mode("overwrite").parquet(path)


def load_model(spark, path: str):
    """The network saved at ``path`` and its id; a model is a few megabytes."""
    import ast

    rows = spark.read.parquet(path).collect()
    spec = ast.literal_eval(rows[0]["spec"])
    net = {"SetNet": SetNet, "CharBiLstm": CharBiLstm}[spec.pop("class")](**spec)
    net.params = {r["name"]: np.array(r["data"]).reshape(r["shape"]) for r in rows}
    return net, rows[0]["model_id"]
