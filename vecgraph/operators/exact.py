"""Exact neighbours and the graphs defined by distance alone.

All pairs of a stated query set and a base meet in cells (query block, base part): a cell keeps one block of
queries, of bounded size, and streams its part of the base; nothing is crossed by a join.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from vecgraph.functions.kernels import d2_pairs, fold, matrix
from vecgraph.session import ship, shuffle_partitions

#: Queries in a block (of a nearest-neighbour search: at least and at most), and answers that a cell keeps.
BLOCK, WIDEST, KEPT = 2048, 1 << 15, 1 << 20
#: Distances that a nearest-neighbour search looks at in one go.
SCAN_CELLS = 1 << 19


def grid(n: int, tasks: int, least: int, most: int) -> tuple[int, int]:
    """(blocks of queries, parts of the base) with about `tasks` cells. The base is sent once per block and the queries once per part,
    so blocks are as many as parts where their size, from `least` to `most` queries, allows it."""
    block = max(min(least, most), min(most, -(-n // max(1, int(tasks**0.5)))))
    blocks = max(1, -(-n // block))
    return blocks, max(1, -(-tasks // blocks))


def in_cells(base: DataFrame, queries: DataFrame, kernel, schema: str, block: int = BLOCK, most: int | None = None) -> DataFrame:
    """kernel(query ids, query matrix) -> object with add(ids, matrix) and out(): run over every cell. `most`: queries that a block may
    have where more than `block` save shuffled rows."""
    ship(base.sparkSession)
    blocks, parts = grid(queries.count(), shuffle_partitions(base.sparkSession), block, most or block)
    own = F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")
    ask = queries.select(F.lit(0).alias("kind"), "id", "vec", F.explode(F.transform(F.sequence(F.lit(0), F.lit(parts - 1)), lambda p: (own * parts + p).cast("int"))).alias("cell"))
    part = F.pmod(F.xxhash64("id", F.lit(7)), F.lit(parts)).cast("int")
    rows = base.select(F.lit(1).alias("kind"), "id", "vec", F.explode(F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda b: (b * parts + part).cast("int"))).alias("cell"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, ids, vecs, state = None, [], [], None
        for b in batches:
            t = pa.table(b)
            cell, kind, num = (t[c].to_numpy() for c in ("cell", "kind", "id"))
            x = matrix(t["vec"])
            for c in np.unique(cell):
                if c != at:
                    if state is not None:
                        yield from state.out()
                    at, ids, vecs, state = c, [], [], None
                here = cell == c
                q, r = here & (kind == 0), here & (kind == 1)
                if q.any():
                    ids.append(num[q])
                    vecs.append(x[q])
                if r.any() and ids:
                    state = state or kernel(np.concatenate(ids), np.concatenate(vecs))
                    state.add(num[r], x[r])
        if state is not None:
            yield from state.out()

    dealt = ask.unionByName(rows).repartitionById(blocks * parts, F.col("cell")).sortWithinPartitions("cell", "kind")
    return dealt.select("cell", "kind", "id", "vec").mapInArrow(run, schema)


class Nearest:
    """The k nearest of each query so far. A matrix product, whose rounding is bounded, leaves out what can't be among them; the rest is
    measured with components added in order."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, k: int, own: bool) -> None:
        self.ids, self.x, self.k, self.own = ids, x, k, own
        self.best, self.d = np.full((len(ids), k), np.iinfo(np.int64).max), np.full((len(ids), k), np.inf)
        self.order = np.argsort(ids, kind="stable")
        self.norm, self.twice = (x * x).sum(1), -2.0 * x

    def themselves(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Pairs of a query and a row of the same id."""
        lo, hi = (np.searchsorted(self.ids, ids, side, sorter=self.order) for side in ("left", "right"))
        n = hi - lo
        at = np.repeat(lo, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        return self.order[at], np.repeat(np.arange(len(ids)), n)

    def close(self, ids: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query, row, d2) of all pairs that may be among the k nearest."""
        norm = (x * x).sum(1)
        most = self.norm.max(initial=0) + norm.max(initial=0)
        if not np.isfinite(4 * most):  # vectors without a length, or of one beyond numbers
            q, r = (i.ravel() for i in np.indices((len(self.ids), len(ids))))
        else:
            slack = 8 * (x.shape[1] + 4) * np.finfo(float).eps * most
            far = self.twice @ x.T  # less the query's own part, which all rows share
            far += norm[None]
            if not self.own:
                far[self.themselves(ids)] = np.inf
            bound = self.d[:, -1] - self.norm + slack
            if len(ids) > self.k and not np.isfinite(bound).all():
                bound = np.minimum(bound, np.partition(far, self.k - 1, 1)[:, self.k - 1] + 2 * slack)
            q, r = np.divmod(np.flatnonzero(far <= bound[:, None]), len(ids))
        if not self.own:
            other = self.ids[q] != ids[r]
            q, r = q[other], r[other]
        if 8 * len(q) > len(self.ids) * len(ids):
            return q, r, d2_pairs(self.x, x)[q, r]
        cuts = range(0, len(q), max(1, SCAN_CELLS // max(1, x.shape[1])))
        d = [fold((self.x[q[i : i + cuts.step]] - x[r[i : i + cuts.step]]) ** 2) for i in cuts]
        return q, r, np.concatenate(d) if d else np.empty(0)

    def add(self, ids: np.ndarray, x: np.ndarray) -> None:
        step = max(64, SCAN_CELLS // max(1, len(self.ids)))
        for i in range(0, len(ids), step):
            q, r, d = self.close(ids[i : i + step], x[i : i + step])
            who, last = ids[i : i + step][r], self.d[q, -1]
            better = np.flatnonzero((d < last) | ((d == last) & (who < self.best[q, -1])))
            some = np.unique(q[better])
            row = np.concatenate([np.repeat(some, self.k), q[better]])
            d = np.concatenate([self.d[some].ravel(), d[better]])
            who = np.concatenate([self.best[some].ravel(), who[better]])
            order = np.lexsort((who, d, row))
            first = np.searchsorted(row[order], some)
            keep = order[(first[:, None] + np.arange(self.k)).ravel()]
            self.d[some], self.best[some] = d[keep].reshape(-1, self.k), who[keep].reshape(-1, self.k)

    def out(self) -> Iterator[pa.RecordBatch]:
        ok = np.isfinite(self.d)
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(self.ids, ok.sum(1))), pa.array(self.best[ok]), pa.array(self.d[ok])], ["qid", "vid", "d2"])


class Within:
    def __init__(self, ids: np.ndarray, x: np.ndarray, theta: float) -> None:
        self.ids, self.x, self.theta, self.found = ids, x, theta, []

    def add(self, ids: np.ndarray, x: np.ndarray) -> None:
        for i in range(0, len(ids), 1024):
            d = d2_pairs(self.x, x[i : i + 1024])
            q, r = np.nonzero((d <= self.theta) & (self.ids[:, None] != ids[None, i : i + 1024]))
            self.found.append((self.ids[q], ids[i + r], d[q, r]))

    def out(self) -> Iterator[pa.RecordBatch]:
        for q, r, d in self.found:
            yield pa.RecordBatch.from_arrays([pa.array(q), pa.array(r), pa.array(d)], ["src", "dst", "d2"])


def top(rows: DataFrame, k: int, by: str | list[str] = "qid", order: tuple[str, ...] = ("d2", "vid")) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy(by).orderBy(*order))
    return rows.withColumn("rank", rank.cast("int")).where(F.col("rank") <= k)


def exact_knn(base: DataFrame, queries: DataFrame, k: int, own: bool = False) -> DataFrame:
    """(qid, rank, vid, d2): the k nearest rows by squared distance, ties by id; `own`: a query's own id counts."""
    near = in_cells(base, queries, lambda i, x: Nearest(i, x, k, own), "qid long, vid long, d2 double", BLOCK, max(1, min(WIDEST, KEPT // max(1, k))))
    return top(near, k).select("qid", "rank", "vid", "d2")


def eps_check(result: DataFrame, truth: DataFrame, eps: float) -> DataFrame:
    """(qid, ok): whether each returned distance is within (1+eps) of the true one of its rank."""
    t = truth.select("qid", "rank", F.col("d2").alias("t2"))
    pair = result.select("qid", "rank", "d2").join(t, ["qid", "rank"])
    return pair.groupBy("qid").agg(F.min(F.sqrt("d2") <= (1 + eps) * F.sqrt("t2")).alias("ok"))


def knn_graph(base: DataFrame, k: int) -> DataFrame:
    """(src, dst, d2): every row's k nearest others."""
    return exact_knn(base, base, k).select(F.col("qid").alias("src"), F.col("vid").alias("dst"), "d2")


def sym_knn_graph(base: DataFrame, k: int) -> DataFrame:
    g = knn_graph(base, k)
    return g.unionByName(g.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "d2")).groupBy("src", "dst").agg(F.min("d2").alias("d2"))


def threshold_graph(base: DataFrame, theta: float) -> DataFrame:
    """(src, dst, d2) for all ordered pairs within squared distance theta."""
    return in_cells(base, base, lambda i, x: Within(i, x, theta), "src long, dst long, d2 double")


def pivots(base: DataFrame, n: int) -> np.ndarray:
    """n rows by hash order (bounded by n)."""
    return np.array([r.vec for r in base.orderBy(F.md5(F.col("id").cast("string")), "id").limit(n).collect()])


def threshold_graph_cells(base: DataFrame, theta: float, n_pivots: int = 16) -> DataFrame:
    """The same rows by a rewrite to an equi-join on cells: a row's home is its nearest pivot's cell, and it visits
    every cell whose pivot is at most 2*sqrt(theta) farther; two rows within theta meet in either's home."""
    ship(base.sparkSession)
    p, reach = pivots(base, n_pivots), 2 * np.sqrt(theta) + 1e-9

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            t = pa.table(b)
            d = np.sqrt(d2_pairs(matrix(t["vec"]), p))
            home = d.argmin(1)
            row, cell = np.nonzero(d <= d.min(1)[:, None] + reach)
            take = t.take(pa.array(row))
            yield from take.append_column("cell", pa.array(cell.astype(np.int32))).append_column("home", pa.array(home[row] == cell)).combine_chunks().to_batches()

    placed = base.select("id", "vec").mapInArrow(place, "id long, vec array<double>, cell int, home boolean")

    # home rows are sent ahead of all rows of their cell
    ahead = placed.where("home").withColumn("ask", F.lit(0))
    after = placed.withColumn("ask", F.lit(1))

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, ids, vecs = None, [], []
        for b in batches:
            t = pa.table(b)
            cell, ask, num = (t[c].to_numpy() for c in ("cell", "ask", "id"))
            x = matrix(t["vec"])
            for c in np.unique(cell):
                if c != at:
                    at, ids, vecs = c, [], []
                h, r = (cell == c) & (ask == 0), (cell == c) & (ask == 1)
                if h.any():
                    ids.append(num[h])
                    vecs.append(x[h])
                if r.any() and ids:
                    got = Within(np.concatenate(ids), np.concatenate(vecs), theta)
                    got.add(num[r], x[r])
                    yield from got.out()

    dealt = ahead.unionByName(after).repartitionById(n_pivots, F.col("cell")).sortWithinPartitions("cell", "ask")
    return dealt.select("cell", "ask", "id", "vec").mapInArrow(meet, "src long, dst long, d2 double")


def mean_vector(base: DataFrame) -> list[float]:
    """One number per dimension."""
    mean = base.select(F.posexplode("vec").alias("i", "x")).groupBy("i").agg(F.avg("x").alias("x"))
    return [r.x for r in mean.orderBy("i").collect()]


def medoid(base: DataFrame) -> DataFrame:
    """(vid, d2): the row nearest to the mean."""
    from vecgraph.functions.columns import d2

    mean = mean_vector(base)
    far = base.select("id", d2(F.col("vec"), F.lit(mean).cast("array<double>")).alias("d2"))
    best: Column = F.min(F.struct("d2", "id"))
    return far.agg(best.alias("b")).select(F.col("b.id").alias("vid"), F.col("b.d2").alias("d2"))


def bijection_check(base: DataFrame, edges: DataFrame) -> DataFrame:
    """(n_vectors, n_vertices, missing, extra): whether vertices and vectors are the same ids."""
    v = edges.select(F.col("src").alias("vid")).unionByName(edges.select(F.col("dst").alias("vid"))).distinct()
    j = base.select("id").join(v, F.col("id") == F.col("vid"), "full_outer")
    return j.agg(F.count("id").alias("n_vectors"), F.count("vid").alias("n_vertices"), F.sum(F.when(F.col("vid").isNull(), 1).otherwise(0)).cast("long").alias("missing"), F.sum(F.when(F.col("id").isNull(), 1).otherwise(0)).cast("long").alias("extra"))
