"""Character-level bidirectional recurrent network for general strings.

Strings become UTF-8 bytes, whole by default (``max_len`` bounds them for callers who want that). Two stacked bidirectional layers; the final states of both directions of the top layer feed
separate dense heads: ``h`` (tanh) and ``g`` (squared scalar).
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from .mlp import Params


def encode_bytes(strings: list[str], max_len: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Byte ids, 0-padded (a byte b is b + 1), and lengths (at least 1)."""
    raw = [s.encode("utf-8", "surrogatepass")[:max_len] for s in strings]
    length = np.array([max(1, len(r)) for r in raw])
    ids = np.zeros((len(raw), int(length.max(initial=1))), np.int64)
    for i, r in enumerate(raw):
        ids[i, : len(r)] = np.frombuffer(r, np.uint8).astype(np.int64) + 1
    return ids, length


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


@dataclass
class CharBiLstm:
    units: int = 128
    n_out: int = 300
    depth: int = 2
    max_len: int | None = None
    char_dim: int = 32
    use_g: bool = True
    params: Params = field(default_factory=dict)

    def init(self, seed: int = 42) -> CharBiLstm:
        rng, u = np.random.default_rng(seed), self.units
        self.params["E"] = rng.normal(0, 0.3, (257, self.char_dim))
        for k in range(self.depth):
            n_in = self.char_dim if k == 0 else 2 * u
            for way in "fb":
                self.params[f"W{k}{way}"] = rng.normal(0, 1 / np.sqrt(n_in + u), (n_in + u, 4 * u))
                bias = np.zeros(4 * u)
                bias[u : 2 * u] = 1.0  # the forget gate starts open
                self.params[f"b{k}{way}"] = bias
        self.params["Hh"], self.params["bh"] = rng.normal(0, np.sqrt(2 / (2 * u + self.n_out)), (2 * u, self.n_out)), np.zeros(self.n_out)
        self.params["Hg"], self.params["bg"] = rng.normal(0, 0.1 / np.sqrt(2 * u), (2 * u, 1)), np.full(1, 0.1)
        return self

    def zero_grad(self) -> Params:
        return {k: np.zeros_like(v) for k, v in self.params.items()}

    def _run(self, x: np.ndarray, mask: np.ndarray, k: int, way: str) -> tuple[np.ndarray, list]:
        """All states of one direction, in the order of the text; padding keeps the state."""
        n, t, u = x.shape[0], x.shape[1], self.units
        w, b = self.params[f"W{k}{way}"], self.params[f"b{k}{way}"]
        h, c, out, steps = np.zeros((n, u)), np.zeros((n, u)), np.zeros((n, t, u)), []
        for s in range(t) if way == "f" else reversed(range(t)):
            z = np.concatenate([x[:, s], h], axis=1)
            a = z @ w + b
            i, f, o, g = _sigmoid(a[:, :u]), _sigmoid(a[:, u : 2 * u]), _sigmoid(a[:, 2 * u : 3 * u]), np.tanh(a[:, 3 * u :])
            new = f * c + i * g
            tc, m = np.tanh(new), mask[:, s, None]
            steps.append((s, z, i, f, o, g, c, tc))
            h, c = m * (o * tc) + (1 - m) * h, m * new + (1 - m) * c
            out[:, s] = h
        return out, steps

    def _run_back(self, d_out: np.ndarray, mask: np.ndarray, steps: list, k: int, way: str, grad: Params) -> np.ndarray:
        n, t, u = d_out.shape
        w, n_in = self.params[f"W{k}{way}"], self.params[f"W{k}{way}"].shape[0] - self.units
        dx, dh, dc = np.zeros((n, t, n_in)), np.zeros((n, u)), np.zeros((n, u))
        for s, z, i, f, o, g, c, tc in reversed(steps):
            m = mask[:, s, None]
            dh = dh + d_out[:, s]
            own, d_new = dh * m, dc * m
            d_new = d_new + own * o * (1 - tc * tc)
            da = np.concatenate([d_new * g * i * (1 - i), d_new * c * f * (1 - f), own * tc * o * (1 - o), d_new * i * (1 - g * g)], axis=1)
            grad[f"W{k}{way}"] += z.T @ da
            grad[f"b{k}{way}"] += da.sum(axis=0)
            dz = da @ w.T
            dx[:, s] = dz[:, :n_in]
            dh, dc = dh * (1 - m) + dz[:, n_in:], dc * (1 - m) + d_new * f
        return dx

    def forward(self, ids: np.ndarray, length: np.ndarray, cache: dict | None = None) -> tuple[np.ndarray, np.ndarray]:
        """``h`` and ``g`` per string."""
        mask = (np.arange(ids.shape[1])[None] < length[:, None]).astype(np.float64)
        x, runs = self.params["E"][ids], []
        for k in range(self.depth):
            f, sf = self._run(x, mask, k, "f")
            b, sb = self._run(x, mask, k, "b")
            runs.append((sf, sb))
            x = np.concatenate([f, b], axis=2)
        u = self.units
        top = np.concatenate([x[:, -1, :u], x[:, 0, u:]], axis=1)  # the last state of either direction
        h, z = np.tanh(top @ self.params["Hh"] + self.params["bh"]), top @ self.params["Hg"] + self.params["bg"]
        if cache is not None:
            cache.update(ids=ids, mask=mask, runs=runs, top=top, h=h, z=z)
        return h, (z * z)[:, 0] if self.use_g else np.zeros(len(ids))

    def backward(self, cache: dict, dh: np.ndarray, dg: np.ndarray, grad: Params) -> None:
        da = dh * (1 - cache["h"] ** 2)
        dz = dg[:, None] * 2 * cache["z"] * self.use_g
        grad["Hh"] += cache["top"].T @ da
        grad["bh"] += da.sum(axis=0)
        grad["Hg"] += cache["top"].T @ dz
        grad["bg"] += dz.sum(axis=0)
        d_top, u, mask = da @ self.params["Hh"].T + dz @ self.params["Hg"].T, self.units, cache["mask"]
        d = np.zeros((*mask.shape, 2 * u))
        d[:, -1, :u], d[:, 0, u:] = d_top[:, :u], d_top[:, u:]
        for k in reversed(range(self.depth)):
            sf, sb = cache["runs"][k]
            d = self._run_back(d[:, :, :u], mask, sf, k, "f", grad) + self._run_back(d[:, :, u:], mask, sb, k, "b", grad)
        np.add.at(grad["E"], cache["ids"], d)
