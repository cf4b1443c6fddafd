"""Fully connected set networks: ``h`` (tanh throughout) and ``g`` (ReLU, squared output), pooled by the mean."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

Params = dict[str, np.ndarray]


@dataclass
class SetNet:
    """``h`` and ``g`` for values given as ``n_in`` features.

    ``layers`` counts weight layers. ``use_g=False`` is the ablation with a constant adjustment of zero.
    """

    n_in: int = 32
    hidden: int = 300
    n_out: int = 300
    layers: int = 3
    use_g: bool = True
    g_scale: float = 0.1
    params: Params = field(default_factory=dict)

    def init(self, seed: int = 42) -> SetNet:
        """Glorot for tanh, He for ReLU; the last layer of g starts small."""
        rng = np.random.default_rng(seed)
        size = [self.n_in] + [self.hidden] * (self.layers - 1)
        for net, last in (("h", self.n_out), ("g", 1)):
            for k, (a, b) in enumerate(zip(size, size[1:] + [last], strict=True)):
                sd = np.sqrt(2 / (a + b)) if net == "h" else np.sqrt(2 / a) * (self.g_scale if k == self.layers - 1 else 1)
                self.params[f"{net}W{k}"], self.params[f"{net}b{k}"] = rng.normal(0, sd, (a, b)), np.zeros(b)
        return self

    def init_formula(self, a: float = 0.7, b: float = 1.3, c: float = 2.1) -> SetNet:
        """Weights ``sin(a i + b j + c k) / sqrt(inputs)`` (i, j, k from 1; g's shifted by 0.5): any engine can make them."""
        size = [self.n_in] + [self.hidden] * (self.layers - 1)
        for net, last, shift in (("h", self.n_out, 0.0), ("g", 1, 0.5)):
            for k, (m, n) in enumerate(zip(size, size[1:] + [last], strict=True)):
                i, j = np.arange(1, m + 1)[:, None], np.arange(1, n + 1)[None]
                self.params[f"{net}W{k}"], self.params[f"{net}b{k}"] = np.sin(a * i + b * j + c * (k + 1) + shift) / np.sqrt(m), np.zeros(n)
        return self

    # per value

    def forward_h(self, x: np.ndarray, cache: list | None = None) -> np.ndarray:
        for k in range(self.layers):
            y = np.tanh(x @ self.params[f"hW{k}"] + self.params[f"hb{k}"])
            if cache is not None:
                cache.append((x, y))
            x = y
        return x

    def forward_g(self, x: np.ndarray, cache: list | None = None) -> np.ndarray:
        if not self.use_g:
            return np.zeros(len(x))
        for k in range(self.layers):
            z = x @ self.params[f"gW{k}"] + self.params[f"gb{k}"]
            if cache is not None:
                cache.append((x, z))
            x = z * z if k == self.layers - 1 else np.maximum(z, 0)
        return x[:, 0]

    def backward_h(self, cache: list, d: np.ndarray, grad: Params) -> np.ndarray:
        for k in reversed(range(self.layers)):
            x, y = cache[k]
            d = d * (1 - y * y)
            grad[f"hW{k}"] += x.T @ d
            grad[f"hb{k}"] += d.sum(axis=0)
            d = d @ self.params[f"hW{k}"].T
        return d

    def backward_g(self, cache: list, d: np.ndarray, grad: Params) -> np.ndarray:
        d = d[:, None]
        for k in reversed(range(self.layers)):
            x, z = cache[k]
            d = d * (2 * z if k == self.layers - 1 else (z > 0))
            grad[f"gW{k}"] += x.T @ d
            grad[f"gb{k}"] += d.sum(axis=0)
            d = d @ self.params[f"gW{k}"].T
        return d

    # per batch of datasets

    def zero_grad(self) -> Params:
        return {k: np.zeros_like(v) for k, v in self.params.items()}

    def embed_sets(self, x: np.ndarray, weight: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Weighted means of h and g over the runs of rows that begin at ``starts``."""
        total = np.add.reduceat(weight, starts)
        h = np.add.reduceat(self.forward_h(x) * weight[:, None], starts, axis=0) / total[:, None]
        return h, np.add.reduceat(self.forward_g(x) * weight, starts) / total


def formula_sql(net: str, a: float = 0.7, b: float = 1.3, c: float = 2.1) -> str:
    """SQL of a formula-initialised weight, with columns i, j and layer k from 1 and m inputs."""
    shift = 0.5 if net == "g" else 0.0
    return f"sin({a} * i + {b} * j + {c} * k + {shift}) / sqrt(m)"
