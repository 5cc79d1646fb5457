"""Exact top-k search by inner product with multi-resolution segment statistics.

For a vector cut into segments of w components, <q, x> <= sum over segments of w * (mean_q * mean_x +
dev_q * dev_x) (Cauchy-Schwarz on the centred parts). Fewer, longer segments give a cheaper and looser
bound. Each batch of rows passes a coarse level, then a fine one; only pairs whose bound still reaches
the query's k-th best score get an exact score. Bounds carry a slack for rounding, so results are exact.

Queries and rows meet in cells: queries in blocks of a fixed size, rows in parts. A cell holds one block
of queries (bounded) and streams its rows; each cell returns k rows per query, and a window picks the k.

Defined cases: null vectors, vectors holding null or non-finite components and empty vectors take no part;
vectors of another length than the query's are no candidates; rows with the query's own id are left out;
ties go to the smaller id, equal ids stay as separate rows; an empty table gives an empty result.
Scores are exact while |q| * |x| < 2^53.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecgraph.session import ship, shuffle_partitions

from .common import column

#: Queries held by a cell at once.
BLOCK = 8192
LEVELS = (4, 16)


def segment_features(x: np.ndarray, segments: int) -> np.ndarray:
    """Rows of sqrt(w)*mean and sqrt(w)*dev of each segment: their dot product bounds the inner product."""
    cuts = np.array_split(np.arange(x.shape[1]), min(segments, x.shape[1]))
    mean = np.stack([x[:, c].mean(1) * np.sqrt(len(c)) for c in cuts], 1)
    dev = np.stack([x[:, c].std(1) * np.sqrt(len(c)) for c in cuts], 1)
    return np.concatenate([mean, dev], 1)


class Block:
    """One block of queries with their best k so far."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, k: int) -> None:
        self.ids, self.v, self.k = ids, vectors, k
        self.features = [segment_features(vectors, s) for s in LEVELS]
        self.norm = np.linalg.norm(vectors, axis=1)
        self.floor = np.full(len(ids), -np.inf)
        self.q = np.empty(0, np.int64)
        self.id = np.empty(0, np.int64)
        self.score = np.empty(0)
        self.exact = 0

    def survivors(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        slack = 1e-9 * self.norm[:, None] * np.linalg.norm(x, axis=1)[None, :] + 1e-6
        alive = None
        for level, feature in zip(LEVELS, self.features, strict=True):
            seen = segment_features(x, level)
            if alive is None:
                alive = np.nonzero(feature @ seen.T + slack >= self.floor[:, None])
                continue
            q, r = alive
            keep = np.concatenate([np.einsum("ij,ij->i", feature[q[i : i + 65536]], seen[r[i : i + 65536]]) for i in range(0, len(q), 65536)] or [np.empty(0)]) + slack[q, r] >= self.floor[q]
            alive = q[keep], r[keep]
        return alive

    def offer(self, ids: np.ndarray, x: np.ndarray) -> None:
        q, r = self.survivors(x)
        if not len(q):
            return
        self.exact += len(q)
        if len(q) > 0.1 * len(self.ids) * len(ids):
            score = (self.v @ x.T)[q, r]
        else:
            score = np.concatenate([np.einsum("ij,ij->i", self.v[q[i : i + 65536]], x[r[i : i + 65536]]) for i in range(0, len(q), 65536)])
        keep = (score >= self.floor[q]) & (ids[r] != self.ids[q])
        q, i, s = (np.concatenate(p) for p in ((self.q, q[keep]), (self.id, ids[r[keep]]), (self.score, score[keep])))
        order = np.lexsort((i, -s, q))
        q, i, s = q[order], i[order], s[order]
        start = np.searchsorted(q, q, "left")
        rank = np.arange(len(q)) - start
        best = rank < self.k
        self.q, self.id, self.score = q[best], i[best], s[best]
        last = rank[best] == self.k - 1
        self.floor[self.q[last]] = self.score[last]


def exact_topk(vectors: DataFrame, queries: DataFrame, k: int, id_col: str = "vec_id") -> DataFrame:
    """vectors/queries(id, vec array<bigint>) -> (query_id, rank, vec_id, score long): each query's k best rows."""
    spark = vectors.sparkSession
    ship(spark)
    blocks = max(1, -(-queries.count() // BLOCK))
    parts = shuffle_partitions(spark)
    cells = blocks * parts
    key = F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")
    ask = queries.select(F.col(id_col).alias("id"), "vec").withColumn("cell", F.explode(F.transform(F.sequence(F.lit(0), F.lit(parts - 1)), lambda p: (key * parts + p).cast("int")))).withColumn("kind", F.lit(0))
    part = F.pmod(F.xxhash64("id", F.lit(11)), F.lit(parts)).cast("int")
    rows = vectors.select(F.col(id_col).alias("id"), "vec").withColumn("cell", F.explode(F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda b: (b * parts + part).cast("int")))).withColumn("kind", F.lit(1))

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        gathered: dict[int, tuple[list, list]] = {}
        held: dict[int, Block] = {}
        at = None

        def out() -> Iterator[pa.RecordBatch]:
            for b in held.values():
                yield pa.RecordBatch.from_arrays([pa.array(b.ids[b.q]), pa.array(b.id), pa.array(np.rint(b.score).astype(np.int64))], ["query_id", "vec_id", "score"])

        for batch in batches:
            cell, kind, ids = (column(batch, c).to_numpy(zero_copy_only=False) for c in ("cell", "kind", "id"))
            lists = column(batch, "vec")
            ends = lists.offsets.to_numpy()
            flat = lists.values.to_numpy(zero_copy_only=False).astype(np.float64)
            size = np.diff(ends)
            for c in np.unique(cell):
                if c != at:
                    yield from out()
                    at, gathered, held = c, {}, {}
                for d in np.unique(size[cell == c]):
                    here = np.flatnonzero((cell == c) & (size == d))
                    x = flat[ends[here][:, None] + np.arange(d)]
                    ask_rows = kind[here] == 0
                    if ask_rows.any():
                        g = gathered.setdefault(d, ([], []))
                        g[0].append(ids[here][ask_rows])
                        g[1].append(x[ask_rows])
                    x, own = x[~ask_rows], ids[here][~ask_rows]
                    if not len(x) or d not in gathered:
                        continue
                    if d not in held:
                        held[d] = Block(np.concatenate(gathered[d][0]), np.concatenate(gathered[d][1]), k)
                    step, i = 32, 0
                    while i < len(x):
                        held[d].offer(own[i : i + step], x[i : i + step])
                        i, step = i + step, min(2 * step, 1024)
        yield from out()

    near = ask.unionByName(rows).repartitionById(cells, F.col("cell")).sortWithinPartitions("cell", "kind").select("cell", "kind", "id", "vec").mapInArrow(search, "query_id long, vec_id long, score long")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return near.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def integer_vectors(vectors: DataFrame, scale: int = 256, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """floor(scale * x) of each component as a double; rows that take no part are left out."""
    v = F.col(vec_col).cast("array<double>")
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return vectors.where(F.col(id_col).isNotNull() & v.isNotNull() & ~F.coalesce(bad, F.lit(True)) & (F.size(v) > 0)).select(F.col(id_col).cast("long").alias(id_col), F.transform(v, lambda x: F.floor(x * scale).cast("long")).alias("vec"))
