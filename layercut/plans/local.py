"""NumPy twin of all passes: the ground truth for tiny networks, and the brute-force partition."""

from __future__ import annotations

from itertools import product

import numpy as np

from ..functions.activation import np_activate, np_prime


class LocalNetwork:
    """Dense-index copy of a small network: links[k] = (rows, cols, values) with positions in ids[k + 1] and ids[k]."""

    def __init__(self, weights: list[tuple[int, int, int, float]], neurons: list[tuple[int, int]], depth: int, activation: str = "sigmoid"):
        self.depth, self.activation = depth, activation
        self.ids = [sorted(n for k, n in neurons if k == layer) for layer in range(depth + 1)]
        self.at = [{n: i for i, n in enumerate(ids)} for ids in self.ids]
        self.links = []
        for k in range(1, depth + 1):
            rows = [(self.at[k][r], self.at[k - 1][c], w) for layer, r, c, w in weights if layer == k]
            self.links.append((np.array([r[0] for r in rows], dtype=int), np.array([r[1] for r in rows], dtype=int), np.array([r[2] for r in rows], dtype=float)))

    @classmethod
    def of(cls, net) -> LocalNetwork:
        w = [tuple(r) for r in net.weights.select("layer", "row", "col", "w").collect()]
        return cls(w, [tuple(r) for r in net.neurons.select("layer", "neuron").collect()], net.depth, net.activation)

    def forward(self, x: np.ndarray) -> tuple[list[np.ndarray], list[np.ndarray]]:
        zs, xs = [x], [x]
        for k in range(self.depth):
            rows, cols, w = self.links[k]
            z = np.bincount(rows, weights=w * xs[-1][cols], minlength=len(self.ids[k + 1]))
            zs.append(z)
            xs.append(np_activate(z, self.activation))
        return zs, xs

    def backward(self, zs, xs, y: np.ndarray, loss: str = "mse_half") -> list[np.ndarray]:
        slope = xs[-1] - y if loss == "mse_half" else 2 * (xs[-1] - y) / len(y)
        deltas = [slope * np_prime(zs[-1], xs[-1], self.activation)]
        for k in range(self.depth - 1, 0, -1):
            rows, cols, w = self.links[k]
            s = np.bincount(cols, weights=w * deltas[0][rows], minlength=len(self.ids[k]))
            deltas.insert(0, s * np_prime(zs[k], xs[k], self.activation))
        return deltas

    def gradients(self, x: np.ndarray, y: np.ndarray, loss: str = "mse_half") -> list[np.ndarray]:
        zs, xs = self.forward(x)
        return [d[r] * xs[k][c] for k, ((r, c, _), d) in enumerate(zip(self.links, self.backward(zs, xs, y, loss), strict=True))]

    def update(self, grads: list[np.ndarray], eta: float) -> None:
        self.links = [(r, c, w - eta * g) for (r, c, w), g in zip(self.links, grads, strict=True)]

    def train_sequential(self, pairs, eta: float, epochs: int = 1, loss: str = "mse_half") -> None:
        """One vector at a time; the weights change between vectors."""
        for _ in range(epochs):
            for x, y in pairs:
                self.update(self.gradients(x, y, loss), eta)

    def loss(self, x: np.ndarray, y: np.ndarray, kind: str = "mse_half") -> float:
        d = (self.forward(x)[1][-1] - y) ** 2
        return float(d.sum() / 2 if kind == "mse_half" else d.mean())

    def weights(self) -> list[tuple[int, int, int, float]]:
        return [(k + 1, self.ids[k + 1][r], self.ids[k][c], float(w)) for k, (rs, cs, ws) in enumerate(self.links) for r, c, w in zip(rs, cs, ws, strict=True)]


def brute_force_partition(rows: list[list[int]], p: int, cap: int, fixed: dict[int, int] | None = None) -> tuple[int, list[int]]:
    """(least sum of lambda - 1, parts) over all assignments of up to about ten rows (lists of nets) within the capacity."""
    fixed, best = fixed or {}, None
    nets = sorted({n for r in rows for n in r})
    for parts in product(range(p), repeat=len(rows)):
        if max(sum(len(r) for r, m in zip(rows, parts, strict=True) if m == q) for q in range(p)) > cap:
            continue
        cut = sum(len({m for r, m in zip(rows, parts, strict=True) if n in r} | ({fixed[n]} if n in fixed else set())) - 1 for n in nets)
        if best is None or cut < best[0]:
            best = cut, list(parts)
    if best is None:
        raise ValueError("no assignment fits the capacity")
    return best
