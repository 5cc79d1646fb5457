"""The learned compression network to compare with: a small network onto the unit sphere, trained to keep the order of
neighbours (a hinge on triplets) and to spread points out (an entropy term from nearest neighbours), then quantized."""

from __future__ import annotations

import numpy as np

from vecgraph.operators.quantize import Quantizer, fit_books, row_blocks

from .loop import Adam, one_cycle


class Network:
    """Two layers and a scaling to length one."""

    def __init__(self, w1: np.ndarray, b1: np.ndarray, w2: np.ndarray) -> None:
        self.w = {"w1": w1, "b1": b1, "w2": w2}

    @classmethod
    def start(cls, d: int, hidden: int, out: int, seed: int) -> Network:
        r = np.random.default_rng(seed)
        return cls(r.normal(0, np.sqrt(2 / d), (d, hidden)), np.zeros(hidden), r.normal(0, np.sqrt(1 / hidden), (hidden, out)))

    def forward(self, x: np.ndarray) -> tuple[np.ndarray, tuple]:
        a = np.maximum(x @ self.w["w1"] + self.w["b1"], 0)
        z = a @ self.w["w2"]
        n = np.linalg.norm(z, axis=1, keepdims=True) + 1e-12
        return z / n, (x, a, z / n, n)

    def __call__(self, x: np.ndarray) -> np.ndarray:
        return self.forward(x)[0]

    def back(self, kept: tuple, g: np.ndarray) -> dict[str, np.ndarray]:
        x, a, y, n = kept
        gz = (g - y * (g * y).sum(1, keepdims=True)) / n
        ga = (gz @ self.w["w2"].T) * (a > 0)
        return {"w1": x.T @ ga, "b1": ga.sum(0), "w2": a.T @ gz}


def spread(y: np.ndarray) -> tuple[float, np.ndarray]:
    """Minus the mean log distance to the nearest other point of the batch, and its gradient."""
    d = ((y[:, None] - y[None]) ** 2).sum(-1)
    np.fill_diagonal(d, np.inf)
    near = d.argmin(1)
    dist = d[np.arange(len(y)), near] + 1e-12
    g = np.zeros_like(y)
    pull = -(y - y[near]) / dist[:, None] / len(y)
    g += pull
    np.add.at(g, near, -pull)
    return float(-0.5 * np.log(dist).mean()), g


def train_neural(x: np.ndarray, triplets: tuple[np.ndarray, np.ndarray, np.ndarray], m: int, k: int, d_out: int = 40, lam: float = 0.005, hidden: int = 128, steps: int = 300, size: int = 128, rate: float = 1e-3, margin: float = 0.05, seed: int = 1) -> tuple[Quantizer, list[float]]:
    """triplets: places of anchors, scopes of positives, scopes of negatives in x."""
    net, adam, rng, losses = Network.start(x.shape[1], hidden, d_out, seed), Adam(rate), np.random.default_rng(seed), []
    anchors, pos, neg = triplets
    for step in range(steps):
        pick = rng.integers(0, len(anchors), size)
        a = anchors[pick]
        p, n = pos[pick, rng.integers(0, pos.shape[1], size)], neg[pick, rng.integers(0, neg.shape[1], size)]
        (ya, ka), (yp, kp), (yn, kn) = (net.forward(x[i]) for i in (a, p, n))
        gap = margin + ((ya - yp) ** 2).sum(1) - ((ya - yn) ** 2).sum(1)
        on = (gap > 0)[:, None] / size
        ent, ge = spread(ya)
        total: dict[str, np.ndarray] = {}
        for kept, g in ((ka, 2 * (yn - yp) * on + lam * ge), (kp, -2 * (ya - yp) * on), (kn, 2 * (ya - yn) * on)):
            for name, v in net.back(kept, g).items():
                total[name] = total.get(name, 0) + v
        adam.n = step + 1
        for name, g in total.items():
            net.w[name] = adam.step(name, net.w[name], g, one_cycle(step, steps, rate))
        losses.append(float(np.maximum(gap, 0).mean() + lam * ent))
    y = np.concatenate([net(x[at]) for at in row_blocks(len(x), hidden)])  # the hidden layer is wider than x
    return Quantizer("neural", fit_books(y, m, k, 25), None, net), losses


def network_bytes(net: Network) -> int:
    return 4 * sum(v.size for v in net.w.values())
