"""Losses of the learned quantizer and their gradients by rotation and codewords.

A vector is rotated, each chunk gets soft weights over its codewords (with Gumbel noise), and the soft vector
is their weighted sum. Neighbourhood loss: a hinge on quantized triplets. Routing loss: minus the log chance of
the teacher's vertex among the unvisited candidates, by distance of their soft vectors to the rotated query.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from vecgraph.operators.soft import log_softmax


def uniform(seed: int, epoch: int, ids: np.ndarray, m: int, k: int) -> np.ndarray:
    """n x M x K numbers in (0, 1) from a hash of seed, epoch, id, chunk and codeword: the same in any partitioning."""
    a, b, c = (np.uint64(v) for v in (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB))
    with np.errstate(over="ignore"):  # arithmetic is modulo 2^64
        x = ids.astype(np.int64).view(np.uint64)[:, None, None] * a + np.uint64((seed * 1_000_033 + epoch) & 0xFFFFFFFF) * b
        x = x + np.arange(m, dtype=np.uint64)[None, :, None] * np.uint64(1_000_003) + np.arange(k, dtype=np.uint64)[None, None, :]
        x = (x ^ (x >> np.uint64(30))) * b
        x = (x ^ (x >> np.uint64(27))) * c
    x ^= x >> np.uint64(31)
    return ((x >> np.uint64(11)).astype(np.float64) + 0.5) / 2.0**53


@dataclass
class Sums:
    """What a batch (or a partition of it) adds up to."""

    rotation: np.ndarray
    books: np.ndarray
    loss: dict[str, float] = field(default_factory=dict)
    count: dict[str, int] = field(default_factory=dict)

    def add(self, other: Sums) -> Sums:
        keys = {*self.loss, *other.loss}
        return Sums(self.rotation + other.rotation, self.books + other.books, {k: self.loss.get(k, 0) + other.loss.get(k, 0) for k in keys}, {k: self.count.get(k, 0) + other.count.get(k, 0) for k in keys})


class Soft:
    """Soft vectors of rows x, kept for the way back."""

    def __init__(self, x: np.ndarray, rotation: np.ndarray, books: np.ndarray, temperature: float, noise: np.ndarray | None, straight: bool = False) -> None:
        self.x, self.books, self.t = x, books, temperature
        m, k, w = books.shape
        self.y = (x @ rotation.T).reshape(len(x), m, w)
        d = (self.y**2).sum(-1)[..., None] - 2 * np.einsum("nmw,mkw->nmk", self.y, books) + (books**2).sum(-1)[None]
        logits = -d / temperature
        if noise is not None:
            logits = logits + noise
        self.w = np.exp(log_softmax(logits))
        self.out = np.einsum("nmk,mkw->nmw", self.w, books).reshape(len(x), -1)
        if straight:  # hard vectors forward, soft gradients back
            self.out = books[np.arange(m)[None], d.argmin(-1)].reshape(len(x), -1)

    def back(self, g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(by rotation, by books) from the gradient by the soft vectors."""
        m, k, w = self.books.shape
        g = g.reshape(len(g), m, w)
        gw = np.einsum("nmw,mkw->nmk", g, self.books)
        gl = self.w * (gw - (gw * self.w).sum(-1, keepdims=True))
        total = gl.sum(-1)
        gy = -(2 / self.t) * (total[..., None] * self.y - np.einsum("nmk,mkw->nmw", gl, self.books))
        by_books = np.einsum("nmk,nmw->mkw", self.w, g) + (2 / self.t) * (np.einsum("nmk,nmw->mkw", gl, self.y) - gl.sum(0)[..., None] * self.books)
        return gy.reshape(len(g), -1).T @ self.x, by_books


def neighbour(rotation: np.ndarray, books: np.ndarray, x: tuple[np.ndarray, np.ndarray, np.ndarray], noise: tuple | None, temperature: float, margin: float, straight: bool = False) -> Sums:
    """x: anchors, positives, negatives."""
    a, p, n = (Soft(v, rotation, books, temperature, noise[i] if noise else None, straight) for i, v in enumerate(x))
    gap = margin + ((a.out - p.out) ** 2).sum(1) - ((a.out - n.out) ** 2).sum(1)
    on = (gap > 0)[:, None]
    gr, gb = np.zeros_like(rotation), np.zeros_like(books)
    for s, g in ((a, 2 * (n.out - p.out)), (p, -2 * (a.out - p.out)), (n, 2 * (a.out - n.out))):
        r, b = s.back(g * on)
        gr, gb = gr + r, gb + b
    return Sums(gr, gb, {"nbr": float(np.maximum(gap, 0).sum())}, {"nbr": len(gap)})


def routing(rotation: np.ndarray, books: np.ndarray, q: np.ndarray, cands: np.ndarray, row: np.ndarray, target: np.ndarray, noise: np.ndarray | None, temperature: float, tau: float, straight: bool = False) -> Sums:
    """q: one query per trace row; cands: unvisited candidates' vectors, `row` the trace row of each; target: whether it is the teacher's."""
    s = Soft(cands, rotation, books, temperature, noise, straight)
    y = q @ rotation.T
    diff = s.out - y[row]
    logit = -(diff**2).sum(1) / tau
    top = np.full(len(q), -np.inf)
    np.maximum.at(top, row, logit)
    z = np.zeros(len(q))
    np.add.at(z, row, np.exp(logit - top[row]))
    logp = logit - top[row] - np.log(z)[row]
    gd = (target - np.exp(logp)) / tau  # by the squared distances
    g = 2 * gd[:, None] * diff
    gr, gb = s.back(g)
    by_q = np.zeros_like(y)
    np.add.at(by_q, row, -g)
    return Sums(gr + by_q.T @ q, gb, {"route": float(-logp[target > 0].sum())}, {"route": int(target.sum())})


def reconstruction(rotation: np.ndarray, books: np.ndarray, x: np.ndarray, noise: np.ndarray | None, temperature: float, straight: bool = False) -> Sums:
    s = Soft(x, rotation, books, temperature, noise, straight)
    y = x @ rotation.T
    diff = s.out - y
    gr, gb = s.back(2 * diff)
    return Sums(gr - (2 * diff).T @ x, gb, {"recon": float((diff**2).sum())}, {"recon": len(x)})
