"""The neighbour-regression refinement to compare with: a vector is rebuilt from its own code and the decoded codes of its
first linked neighbours, with weights by least squares (one set of weights, or a small codebook of them), and candidates
are ranked anew by the rebuilt vectors."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecgraph.functions.kernels import fold, lists
from vecgraph.operators.quantize import Quantizer
from vecgraph.operators.walk import Index, Kernel, assemble, code_distance, descend, walk
from vecgraph.session import ship

#: Rows whose links are decoded at once in a fit.
FIT_ROWS = 4096


def parts_of(index: Index, places: np.ndarray, q: Quantizer, links: int) -> np.ndarray:
    """n x (links + 1) x D: own decoded vector, then the linked ones' (the own one again where there are fewer)."""
    near = index.neighbours[places][:, :links]
    near = np.concatenate([near, np.full((len(near), max(0, links - near.shape[1])), -1)], 1)
    near = np.where(near >= 0, near, places[:, None])
    all_ = np.concatenate([places[:, None], near], 1)
    return q.decode(index.codes[all_.ravel()]).reshape(*all_.shape, -1)


def fit_weights(index: Index, x: np.ndarray, q: Quantizer, links: int = 8, entries: int = 1, rounds: int = 5, ridge: float = 1e-6, places: np.ndarray | None = None) -> np.ndarray:
    """entries x (links + 1) weights: normal equations over all rows, or those at `places`, added up in blocks of FIT_ROWS; with more entries each row takes its best set and they are fitted anew."""
    places = np.arange(len(x)) if places is None else places
    w = np.zeros((entries, links + 1))
    group = np.arange(len(places)) % entries
    cuts = [slice(i, i + FIT_ROWS) for i in range(0, len(places), FIT_ROWS)]
    parts = lambda at: (parts_of(index, places[at], q, links), q.turned(x[places[at]]))
    for _ in range(rounds if entries > 1 else 1):
        left, right = np.zeros((entries, links + 1, links + 1)), np.zeros((entries, links + 1))
        for at in cuts:
            z, y = parts(at)
            for e in range(entries):
                ze, ye = z[group[at] == e], y[group[at] == e]
                left[e] += np.einsum("nad,nbd->ab", ze, ze)
                right[e] += np.einsum("nad,nd->a", ze, ye)
        for e in np.unique(group):
            w[e] = np.linalg.solve(left[e] + ridge * np.eye(links + 1), right[e])
        for at in cuts if entries > 1 else ():
            z, y = parts(at)
            group[at] = np.stack([((np.einsum("a,nad->nd", v, z) - y) ** 2).sum(1) for v in w], 1).argmin(1)
    return w


def weights_over(rows: DataFrame, q: Quantizer, keep: Callable[[np.ndarray], np.ndarray], links: int = 8, ridge: float = 1e-6) -> np.ndarray:
    """The one set of weights of all rows of an index with codes and vectors whose ids are to `keep`: each shard adds its part to the
    normal equations, and their sums come to the driver."""
    ship(rows.sparkSession)
    n = links + 1

    def run(shard: pa.Table) -> pa.Table:
        idx, total = assemble(shard), np.zeros((n, n + 1))
        places = np.flatnonzero(keep(idx.ids))
        for i in range(0, len(places), FIT_ROWS):
            at = places[i : i + FIT_ROWS]
            z, y = parts_of(idx, at, q, links), q.turned(idx.vectors[at])
            total += np.concatenate([np.einsum("nad,nbd->ab", z, z), np.einsum("nad,nd->a", z, y)[:, None]], 1)
        return pa.table({"s": lists(total.reshape(1, -1))})

    sums = rows.groupBy("shard").applyInArrow(run, "s array<double>").select(F.posexplode("s").alias("i", "x")).groupBy("i").agg(F.sum("x").alias("x"))
    total = np.array([r.x for r in sums.orderBy("i").collect()]).reshape(-1, n + 1)
    return np.linalg.solve(total[:, :n] + ridge * np.eye(n), total[:, n])[None] if len(total) else np.zeros((1, n))


def linkreg_searcher(q: Quantizer, weights: np.ndarray) -> Kernel:
    """A code-only walk (from where the upper levels lead, if there are any) whose last list is ranked by distances to the rebuilt
    vectors (first set of weights)."""
    links = weights.shape[1] - 1

    def kernel(idx: Index, ids: np.ndarray, x: np.ndarray, h: int) -> Iterator[pa.RecordBatch]:
        dist = code_distance(idx, q.lut(x))
        start, above = descend(idx, len(x), dist) if idx.upper else (None, 0)
        w = walk(idx, len(x), dist, h, entry=start)
        row, col = np.nonzero(w.place >= 0)
        place = w.place[row, col]
        built = np.einsum("a,nad->nd", weights[0], parts_of(idx, place, q, links))
        d = fold((built - q.turned(x)[row]) ** 2)
        ok = idx.ids[place] != ids[row]
        hops = (w.hops + above)[row][ok]
        yield pa.RecordBatch.from_arrays([pa.array(c) for c in (ids[row][ok], idx.ids[place][ok], d[ok], hops, np.zeros(len(hops), np.int64))], ["qid", "vid", "d2", "hops", "reads"])

    return kernel
