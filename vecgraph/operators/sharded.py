"""An index cut into shards of bounded size: vectors go to cells of a coarse k-means, each cell has a graph of its own.

A query asks its nearest cells; a window merges their answers. The index table is stored in buckets by shard, so a search
shuffles only queries and answers, and reads only the shards that are asked. Cells that exceed SHARD_ROWS are cut again by
hash, so a shard always fits a task.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecgraph.functions.kernels import d2_blas, matrix
from vecgraph.measures import recall
from vecgraph.session import materialize, ship

from . import graphs
from .exact import exact_knn
from .quantize import Quantizer, encode, kmeans, sample
from .walk import SHARD_ROWS, beam_search, index_rows, keep_index


def place(base: DataFrame, centres: np.ndarray, most: int) -> tuple[DataFrame, dict[int, list[int]]]:
    """(id, vec, shard, far) of every row, far from its cell's centre; and the shards of each cell, none of more than about `most` rows."""
    ship(base.sparkSession)

    def nearest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                cell = d2_blas(matrix(b.column(1)), centres).argmin(1).astype(np.int32)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(cell)], ["id", "vec", "cell"])

    placed = base.select("id", "vec").mapInArrow(nearest, "id long, vec array<double>, cell int")
    size = {r.cell: r["n"] for r in placed.groupBy("cell").agg(F.count("*").alias("n")).collect()}
    parts, at = {}, 0
    for c in sorted(size):
        n = -(-size[c] // most)
        parts[c] = list(range(at, at + n))
        at += n
    first, many = (np.zeros(len(centres), np.int64) for _ in range(2))
    for c, p in parts.items():
        first[c], many[c] = p[0], len(p)

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                cell, num, x = b.column(2).to_numpy(), b.column(0).to_numpy(), matrix(b.column(1))
                mixed = (num.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)
                shard = first[cell] + (mixed % many[cell].astype(np.uint64)).astype(np.int64)
                far = ((x - centres[cell]) ** 2).sum(1)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(shard.astype(np.int32)), pa.array(far)], ["id", "vec", "shard", "far"])

    return materialize(placed.mapInArrow(assign, "id long, vec array<double>, shard int, far double")), parts


def entries(placed: DataFrame) -> DataFrame:
    """(vid) of each shard: the row nearest to its cell's centre."""
    return placed.groupBy("shard").agg(F.min(F.struct("far", "id")).alias("b")).select(F.col("b.id").alias("vid"))


def stored_index(base: DataFrame, edges: DataFrame, codes: DataFrame | None, vectors: bool, entry: DataFrame | None = None, most: int | None = None, allowed: DataFrame | None = None) -> DataFrame:
    """One graph as a stored index: a single shard (entered at `entry`, or the vertex nearest to the mean) while its rows fit one, and
    otherwise cut by coarse cells, links between shards being dropped; each shard is then entered at the row nearest to its centre."""
    n, most = base.count(), most or SHARD_ROWS
    if n <= most:
        entry = entry if entry is not None else base.sparkSession.createDataFrame([(graphs.entry_vertex(base),)], "vid long") if n else base.select(F.col("id").alias("vid"))
        return keep_index(index_rows(base, edges, codes, entry, vectors, None, allowed))
    placed, parts = place(base, kmeans(sample(base, 100_000), -(-2 * n // most), 8)[0], most)
    rows = index_rows(placed.select("id", "vec"), edges, codes, entries(placed), vectors, placed.select(F.col("id").alias("vid"), "shard"), allowed)
    return keep_index(rows, 1 + max(x for p in parts.values() for x in p))


@dataclass(frozen=True)
class ShardedIndex:
    rows: DataFrame
    centres: np.ndarray
    parts: dict[int, list[int]]  # shards of each cell
    quantizer: Quantizer

    @classmethod
    def build(cls, base: DataFrame, q: Quantizer, cells: int, kind: str = "spread", degree: int = 16, pool: int = 32, most: int = SHARD_ROWS) -> ShardedIndex:
        centres = kmeans(sample(base, 100_000), cells, 8)[0]
        placed, parts = place(base, centres, most)
        n_shards = max(1, sum(map(len, parts.values())))

        def links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            at, held = None, []

            def out() -> Iterator[pa.RecordBatch]:
                if held:
                    t = pa.concat_tables(held)
                    s, d, d2, lv = graphs.shard_links(kind, t["id"].to_numpy(), matrix(t["vec"]), degree, pool, 1.2, 0.5)
                    yield pa.RecordBatch.from_arrays([pa.array(s), pa.array(d), pa.array(d2.astype(float)), pa.array(lv.astype(np.int32))], ["src", "dst", "d2", "level"])

            for b in batches:
                t = pa.table(b)
                shard = t["shard"].to_numpy()
                for x in np.unique(shard):
                    if x != at:
                        yield from out()
                        at, held = x, []
                    held.append(t.filter(pa.array(shard == x)))
            yield from out()

        edges = materialize(placed.select("shard", "id", "vec").repartitionById(n_shards, F.col("shard")).sortWithinPartitions("shard", "id").mapInArrow(links, graphs.EDGES))
        where = placed.select(F.col("id").alias("vid"), "shard")
        entry = entries(placed)
        if kind == "layered":  # the smallest id on each shard's highest level that has links
            top = edges.join(where, F.col("src") == F.col("vid")).groupBy("shard").agg(F.max(F.struct("level", (-F.col("src")).alias("s"))).alias("b"))
            entry = placed.groupBy("shard").agg(F.min(F.struct("far", "id")).alias("e")).join(top, "shard", "left").select(F.coalesce(-F.col("b.s"), "e.id").alias("vid"))
        else:
            edges = edges.where("level = 0").drop("level")
        rows = index_rows(placed.select("id", "vec"), edges, encode(placed, q), entry, True, where)
        return cls(keep_index(rows, n_shards), centres, parts, q)

    def recode(self, q: Quantizer, vectors: bool = True) -> ShardedIndex:
        """The same shards and graphs with another quantizer's codes; without `vectors` for code-only searches."""
        codes = encode(self.rows.select(F.col("vid").alias("id"), "vec"), q)
        n = 1 + max(x for p in self.parts.values() for x in p)
        return ShardedIndex(keep_index(self.rows.drop("code", *([] if vectors else ["vec"])).join(codes, "vid"), n), self.centres, self.parts, q)

    def route(self, queries: DataFrame, probes: int) -> DataFrame:
        """(shard, id, vec): each query once for every shard of its nearest cells."""
        centres, parts = self.centres, self.parts
        known = np.array(sorted(parts))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if not b.num_rows:
                    continue
                near = known[np.argsort(d2_blas(matrix(b.column(1)), centres[known]), 1, kind="stable")[:, :probes]]
                row = [(i, s) for i, cells in enumerate(near) for c in cells for s in parts[int(c)]]
                take = b.take(pa.array([i for i, _ in row]))
                yield pa.RecordBatch.from_arrays([pa.array([s for _, s in row], pa.int32()), *take.columns], ["shard", "id", "vec"])

        return queries.select("id", "vec").mapInArrow(run, "shard int, id long, vec array<double>")

    def asked(self, queries: DataFrame, probes: int) -> tuple[DataFrame, DataFrame]:
        """(rows of the shards that are asked, routed queries); the list of shards asked has at most one row per shard."""
        ask = materialize(self.route(queries, probes))
        return self.rows.join(F.broadcast(ask.select("shard").distinct()), "shard", "left_semi"), ask

    def settle(self, base: DataFrame, asked: DataFrame, floor: float, probes: int, h: int, k: int, mode: str = "disk_tier") -> tuple[int, int, float]:
        """(cells, beam, recall): both are doubled from those given until the answers for `asked`, rows that are not among the queries, hold
        the floor's share of their true neighbours among all rows by two standard errors, or until all cells are asked with a beam as wide
        as the largest shard. Without rows to measure on, those given stay."""
        truth = materialize(exact_knn(base, asked, k))
        cells, most = len(self.parts), self.rows.groupBy("shard").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 0
        while True:
            r = recall(materialize(self.search(asked, probes, h, k, mode)), truth, k).agg(F.avg("recall"), F.stddev_samp("recall"), F.count("*")).first()
            got = float(r[0] or 0.0)
            if not r[2] or got - 2 * float(r[1] or 0.0) / max(1, r[2]) ** 0.5 >= floor or (probes >= cells and h >= most):
                return probes, h, got
            probes, h = min(2 * probes, max(probes, cells)), min(2 * h, max(h, most))

    def search(self, queries: DataFrame, probes: int, h: int, k: int, mode: str = "disk_tier") -> DataFrame:
        rows, ask = self.asked(queries, probes)
        return beam_search(rows, ask, h, k, mode, self.quantizer)
