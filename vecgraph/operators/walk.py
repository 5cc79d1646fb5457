"""Beam search over a proximity graph.

A query keeps up to h candidates ordered by (distance, id). Each hop visits the first unvisited one, adds its
neighbours, and cuts back to h; it ends when all kept candidates are visited. The kernel advances all queries
of a batch together. Over a cluster the index lies in shards of bounded size, stored in buckets: a task loads one
shard and the queries sent to it; results of the shards asked are merged by a window. A second plan advances all queries
hop by hop with joins, for graphs that can't be cut, and as a cross-check.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from vecgraph.functions.columns import adc as adc_col
from vecgraph.functions.kernels import d2_pairs, fold, matrix
from vecgraph.session import bucketed, materialize, ship, shuffle_partitions

from .exact import top
from .quantize import Quantizer, adc

Distance = Callable[[np.ndarray, np.ndarray], np.ndarray]
#: Rows of a shard.
SHARD_ROWS = 2_000_000
#: A block of the disk tier, and the model of its cost.
BLOCK_BYTES, LATENCY_S, BANDWIDTH = 4096, 100e-6, 2e9


#: Numbers of neighbours' vectors (or places to compare them with) that a hop works on at once.
HOP_CELLS = 1 << 22


@dataclass
class Links:
    """Adjacency by place, one row of links after the other: a vertex with very many links costs no other one any room."""

    begin: np.ndarray  # n + 1
    to: np.ndarray

    def degrees(self, places: np.ndarray) -> np.ndarray:
        return self.begin[places + 1] - self.begin[places]

    def __getitem__(self, places: np.ndarray) -> np.ndarray:
        """Links of the places, as wide as the most that one of them has (one at least), -1 where there are fewer."""
        size = self.degrees(places)
        out = np.full((len(places), max(1, int(size.max(initial=0)))), -1)
        real = np.arange(out.shape[1]) < size[:, None]
        out[real] = self.to[np.repeat(self.begin[places] - np.cumsum(size) + size, size) + np.arange(size.sum())]
        return out


@dataclass
class Index:
    """One shard: vectors (or only codes), adjacency by place, entry place."""

    ids: np.ndarray
    neighbours: np.ndarray | Links  # n x degree, -1 where there are fewer
    entry: int
    codes: np.ndarray | None = None
    vectors: np.ndarray | None = None
    upper: list[np.ndarray | Links] | None = None  # neighbours on levels 1, 2, ..., by place
    allowed: np.ndarray | None = None  # which vertices a filtered walk may keep


def hop_slices(index: Index, now: np.ndarray, h: int) -> Iterator[np.ndarray]:
    """Positions in `now`, so many at a time that a hop's arrays stay within HOP_CELLS; vertices of like degree go together."""
    if not isinstance(index.neighbours, Links):
        yield np.arange(len(now))
        return
    deg, wide = np.maximum(index.neighbours.degrees(now), 1), max(h, 1 if index.vectors is None else index.vectors.shape[1])
    order, at = np.argsort(deg, kind="stable"), 0
    while at < len(order):
        n = max(1, HOP_CELLS // (wide * int(deg[order[at]])))
        last = order[min(at + n, len(order)) - 1]
        n = max(1, min(n, HOP_CELLS // (wide * int(deg[last]))))
        yield np.sort(order[at : at + n])
        at += n


def full_distance(index: Index, q: np.ndarray) -> Distance:
    def of(rows: np.ndarray, places: np.ndarray) -> np.ndarray:
        return fold((q[rows][:, None, :] - index.vectors[places]) ** 2)

    return of


def code_distance(index: Index, lut: np.ndarray) -> Distance:
    def of(rows: np.ndarray, places: np.ndarray) -> np.ndarray:
        out = np.zeros(places.shape)
        for j in range(lut.shape[1]):
            out += lut[rows[:, None], j, index.codes[places, j]]
        return out

    return of


@dataclass
class Walk:
    place: np.ndarray  # Q x h, -1 where empty
    d: np.ndarray
    hops: np.ndarray
    visits: np.ndarray  # Q x most hops, -1 after the end
    steps: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]  # per hop: queries, places, d, visited flags, next visit


def walk(index: Index, n: int, dist: Distance, h: int, trace: bool = False, allowed: np.ndarray | None = None, entry: np.ndarray | None = None) -> Walk:
    """All n queries from the entry (or each from its own). `allowed`: only these places are kept as candidates (filtered walks keep the entry)."""
    big = len(index.ids)
    place, d = np.full((n, h), big), np.full((n, h), np.inf)
    seen = np.zeros((n, h), bool)
    every = np.arange(n)
    place[:, 0] = index.entry if entry is None else entry
    d[:, 0] = dist(every, place[:, :1])[:, 0] if n else 0
    hops = np.zeros(n, int)
    visits: list[np.ndarray] = []
    steps = []
    key = np.append(index.ids, np.iinfo(np.int64).max)
    alive = every
    while len(alive):
        open_ = ~seen[alive] & (place[alive] < big)
        goes = open_.any(1)
        if trace and steps:
            q, *rest = steps[-1]
            nxt = np.full(len(q), -1)
            at = np.searchsorted(q, alive[goes])
            nxt[at] = place[alive[goes], open_[goes].argmax(1)]
            steps[-1] = (q, *rest[:-1], nxt)
        alive = alive[goes]
        if not len(alive):
            break
        col = open_[goes].argmax(1)
        now = place[alive, col]
        seen[alive, col] = True
        hops[alive] += 1
        visit = np.full(n, -1)
        visit[alive] = now
        visits.append(visit)
        for some in hop_slices(index, now, h):
            who, near = alive[some], index.neighbours[now[some]]
            ok = near >= 0
            if allowed is not None:
                ok &= allowed[near]
            ok &= ~(near[:, :, None] == place[who][:, None, :]).any(2)
            dn = np.where(ok, dist(who, np.where(near >= 0, near, 0)), np.inf)
            p = np.concatenate([place[who], np.where(ok, near, big)], 1)
            dd, ss = np.concatenate([d[who], dn], 1), np.concatenate([seen[who], np.zeros_like(ok)], 1)
            order = np.lexsort((key[p], dd))[:, :h]
            place[who], d[who], seen[who] = (np.take_along_axis(x, order, 1) for x in (p, dd, ss))
        if trace:
            steps.append((alive, place[alive].copy(), d[alive].copy(), seen[alive].copy(), np.full(len(alive), -1)))
    return Walk(np.where(place < big, place, -1), d, hops, np.stack(visits, 1) if visits else np.empty((n, 0), int), steps)


# ---- shards ----


def by_place(ids: np.ndarray, owner: np.ndarray, other: np.ndarray) -> Links:
    """Links between ids by places; links to ids that aren't here are dropped."""
    a, b = np.searchsorted(ids, owner), np.searchsorted(ids, other)
    ok = (a < len(ids)) & (b < len(ids))
    a, b, owner, other = a[ok], b[ok], owner[ok], other[ok]
    ok = (ids[a] == owner) & (ids[b] == other)
    a, b = a[ok], b[ok]
    order = np.lexsort((b, a))
    begin = np.concatenate([[0], np.cumsum(np.bincount(a, minlength=len(ids)))]).astype(np.int64)
    return Links(begin, b[order])


def in_order(col: pa.ChunkedArray, rank: np.ndarray) -> np.ndarray:
    """A list column of equal lengths as a matrix whose row rank[i] is the column's i-th; one chunk at a time is copied."""
    out, at = None, 0
    for chunk in col.chunks:
        if len(chunk):
            x = matrix(chunk)
            out = np.empty((len(rank), x.shape[1]), x.dtype) if out is None else out
            out[rank[at : at + len(chunk)]] = x
            at += len(chunk)
    return np.empty((0, 0)) if out is None else out


def assemble(rows: pa.Table) -> Index:
    """A shard from its rows (vid, vec or code, nbrs, entry): adjacency by place; links to other shards are dropped."""
    own, names = rows["vid"].to_numpy(), rows.column_names
    order = np.argsort(own, kind="stable")
    ids, rank = own[order], np.empty(len(own), np.int64)
    rank[order] = np.arange(len(own))
    links = lambda col: (np.repeat(own, pc.list_value_length(col).to_numpy()), pc.list_flatten(col))
    owner, flat = links(rows["nbrs"])
    out = by_place(ids, owner, flat.to_numpy())
    upper = None
    if "upper" in names:
        owner, flat = links(rows["upper"])
        flat = flat.combine_chunks() if isinstance(flat, pa.ChunkedArray) else flat
        level, dst = flat.field("level").to_numpy(zero_copy_only=False), flat.field("dst").to_numpy(zero_copy_only=False)
        upper = [by_place(ids, owner[level == lv], dst[level == lv]) for lv in range(1, int(level.max(initial=0)) + 1)]
    entry = int(np.flatnonzero(rows["entry"].to_numpy()[order])[0]) if len(ids) else 0
    codes = in_order(rows["code"], rank).astype(int) if "code" in names else None
    return Index(ids, out, entry, codes, in_order(rows["vec"], rank) if "vec" in names else None, upper, rows["allowed"].to_numpy()[order] if "allowed" in names else None)


def index_rows(base: DataFrame, edges: DataFrame, codes: DataFrame | None, entry: DataFrame, vectors: bool, shards: DataFrame | None = None, allowed: DataFrame | None = None) -> DataFrame:
    """(shard, vid, nbrs, entry, code?, vec?, allowed?): the table a walk reads; code-only tables never hold vectors. `entry` has (vid),
    one per shard; `allowed` has (vid) of what filtered walks may keep."""
    layered = "level" in edges.columns
    ground = edges.where("level = 0") if layered else edges
    nbrs = ground.groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))
    rows = base.select(F.col("id").alias("vid"), *(["vec"] if vectors else []))
    rows = rows.join(nbrs, rows.vid == nbrs.src, "left").drop("src").withColumn("nbrs", F.coalesce("nbrs", F.array().cast("array<long>")))
    if layered:
        above = edges.where("level > 0").groupBy(F.col("src").alias("vid")).agg(F.collect_list(F.struct("level", "dst")).alias("upper"))
        rows = rows.join(above, "vid", "left").withColumn("upper", F.coalesce("upper", F.array().cast("array<struct<level:int,dst:long>>")))
    if codes is not None:
        rows = rows.join(codes, "vid")
    rows = rows.join(entry.select("vid", F.lit(True).alias("entry")), "vid", "left").withColumn("entry", F.coalesce("entry", F.lit(False)))
    if allowed is not None:
        rows = rows.join(allowed.select("vid", F.lit(True).alias("allowed")), "vid", "left").withColumn("allowed", F.coalesce("allowed", F.lit(False)))
    return rows.join(shards, "vid") if shards is not None else rows.withColumn("shard", F.lit(0))


def keep_index(rows: DataFrame, n_shards: int = 1) -> DataFrame:
    """Write an index once, in buckets by shard: every search reads it where it lies and shuffles only queries and answers."""
    return bucketed(rows, "shard", n_shards if n_shards == 1 else 2 * n_shards)


def run_shards(index: DataFrame, queries: DataFrame, kernel: Callable[[Index, np.ndarray, np.ndarray], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """kernel(index, query ids, query vectors) over each shard's queries, in batches; shards meet their queries by grouping both sides.
    queries: (shard, id, vec), or without a shard if all shards are asked. An index from `keep_index` is not shuffled."""
    ship(index.sparkSession)
    out = to_arrow_schema(StructType.fromDDL(schema))

    def run(rows: pa.Table, ask: pa.Table) -> pa.Table:
        found = []
        if rows.num_rows and ask.num_rows:
            idx = assemble(rows)
            for i in range(0, ask.num_rows, 512):
                part = ask.slice(i, 512)
                found += kernel(idx, part["id"].to_numpy(), matrix(part["vec"]))
        return pa.Table.from_batches(found).cast(out) if found else out.empty_table()

    if "shard" not in queries.columns:
        last = index.agg(F.max("shard")).first()[0] or 0
        queries = queries.withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(int(last)))))
    ask = queries.select(F.col("shard").cast("int").alias("shard"), "id", "vec")
    return index.groupBy("shard").cogroup(ask.groupBy("shard")).applyInArrow(run, schema)


def descend(index: Index, n: int, dist: Distance) -> tuple[np.ndarray, np.ndarray]:
    """(place, hops) of each query after a greedy descent through the upper levels, from the entry on the highest."""
    at, hops = np.full(n, index.entry), np.zeros(n, int)
    every = np.arange(n)
    d = dist(every, at[:, None])[:, 0]
    for near_of in reversed(index.upper or []):
        moving = every
        while len(moving):
            near = near_of[at[moving]]
            dn = np.where(near >= 0, dist(moving, np.maximum(near, 0)), np.inf)
            hops[moving] += 1
            best = np.lexsort((np.where(near >= 0, index.ids[near], np.iinfo(np.int64).max), dn))[:, 0]
            low = dn[np.arange(len(moving)), best]
            better = low < d[moving]
            at[moving[better]] = near[np.arange(len(moving)), best][better]
            d[moving[better]] = low[better]
            moving = moving[better]
    return at, hops


RESULT = "qid long, vid long, d2 double, hops long, reads long"


def _result(index: Index, ids: np.ndarray, w: Walk, place: np.ndarray, d: np.ndarray, reads: np.ndarray, k: int, own: bool, only: np.ndarray | None) -> Iterator[pa.RecordBatch]:
    """The k first of each row, the query's own id left out unless `own`, and so what isn't in `only`."""
    vid = np.where(place >= 0, index.ids[place], -1)
    ok = (place >= 0) & (own | (vid != ids[:, None]))
    if only is not None:
        ok &= only[place]
    ok &= np.cumsum(ok, 1) <= k
    row = np.nonzero(ok)[0]
    yield pa.RecordBatch.from_arrays([pa.array(ids[row]), pa.array(vid[ok]), pa.array(d[ok]), pa.array(w.hops[row].astype(np.int64)), pa.array(reads[row].astype(np.int64))], ["qid", "vid", "d2", "hops", "reads"])


def rerank(index: Index, q: np.ndarray, w: Walk, mode: str) -> tuple[np.ndarray, np.ndarray]:
    """Visited vertices by original distance: what the disk tier fetched."""
    places = w.visits
    d = np.where(places >= 0, fold((q[:, None, :] - index.vectors[np.maximum(places, 0)]) ** 2), np.inf)
    order = np.lexsort((np.where(places >= 0, index.ids[np.maximum(places, 0)], np.iinfo(np.int64).max), d))
    return np.take_along_axis(places, order, 1), np.take_along_axis(d, order, 1)


def walk_each_hop(index: Index, q: np.ndarray, lut: np.ndarray, h: int, allowed: np.ndarray | None = None) -> Walk:
    """The next vertex is the unvisited candidate nearest by original distance, among the h nearest by code."""
    n, big = len(q), len(index.ids)
    by_code, by_vector = code_distance(index, lut), full_distance(index, q)
    place, d = np.full((n, h), big), np.full((n, h), np.inf)
    seen = np.zeros((n, h), bool)
    true = np.full((n, h), np.inf)
    place[:, 0] = index.entry
    d[:, 0] = by_code(np.arange(n), place[:, :1])[:, 0]
    true[:, 0] = by_vector(np.arange(n), place[:, :1])[:, 0]
    key = np.append(index.ids, np.iinfo(np.int64).max)
    hops, visits, alive = np.zeros(n, int), [], np.arange(n)
    while len(alive):
        open_ = ~seen[alive] & (place[alive] < big)
        alive, open_ = alive[open_.any(1)], open_[open_.any(1)]
        if not len(alive):
            break
        t = np.where(open_, true[alive], np.inf)
        col = np.lexsort((key[place[alive]], t))[:, 0]
        now = place[alive, col]
        seen[alive, col] = True
        hops[alive] += 1
        visit = np.full(n, -1)
        visit[alive] = now
        visits.append(visit)
        for some in hop_slices(index, now, h):
            who, near = alive[some], index.neighbours[now[some]]
            ok = (near >= 0) & ~(near[:, :, None] == place[who][:, None, :]).any(2)
            if allowed is not None:
                ok &= allowed[near]
            at = np.where(near >= 0, near, 0)
            p = np.concatenate([place[who], np.where(ok, near, big)], 1)
            dd = np.concatenate([d[who], np.where(ok, by_code(who, at), np.inf)], 1)
            tt = np.concatenate([true[who], np.where(ok, by_vector(who, at), np.inf)], 1)
            ss = np.concatenate([seen[who], np.zeros_like(ok)], 1)
            order = np.lexsort((key[p], dd))[:, :h]
            place[who], d[who], true[who], seen[who] = (np.take_along_axis(x, order, 1) for x in (p, dd, tt, ss))
    return Walk(np.where(place < big, place, -1), d, hops, np.stack(visits, 1) if visits else np.empty((n, 0), int), [])


Kernel = Callable[[Index, np.ndarray, np.ndarray, int], Iterator[pa.RecordBatch]]


def searcher(k: int, mode: str = "code_only", quantizer: Quantizer | None = None, rerank_at: str = "final", own: bool = False, filtered: bool = False) -> Kernel:
    """What a shard does with a batch of queries at a beam. mode: "full" (original vectors), "code_only" (codes), "disk_tier" (codes,
    then the vectors of what was visited, once at the end or at each hop). `filtered`: only vertices that the index allows are kept as
    candidates, and the entry to start from, so others aren't even passed through; the answer holds allowed ones only."""

    def kernel(idx: Index, ids: np.ndarray, q: np.ndarray, h: int) -> Iterator[pa.RecordBatch]:
        none = np.zeros(len(ids), int)
        only = idx.allowed if filtered else None
        if mode == "full":
            w = walk(idx, len(q), full_distance(idx, q), h, allowed=only)
            yield from _result(idx, ids, w, w.place, w.d, w.hops, k, own, only)
            return
        lut = quantizer.lut(q)
        if mode == "code_only":
            dist = code_distance(idx, lut)
            start, above = descend(idx, len(q), dist) if idx.upper else (None, none)
            w = walk(idx, len(q), dist, h, allowed=only, entry=start)
            w.hops = w.hops + above
            yield from _result(idx, ids, w, w.place, w.d, none, k, own, only)
            return
        w = walk(idx, len(q), code_distance(idx, lut), h, allowed=only) if rerank_at == "final" else walk_each_hop(idx, q, lut, h, only)
        yield from _result(idx, ids, w, *rerank(idx, q, w, rerank_at), w.hops, k, own, only)

    return kernel


def sweep(index: DataFrame, queries: DataFrame, kernel: Kernel, hs: tuple[int, ...], k: int) -> DataFrame:
    """(h, qid, rank, vid, d2, hops, reads, seconds): one search per beam in a single pass over the index; seconds is a query's share
    of the time its batch took in the kernel. With several shards hops, reads and seconds are the most over the shards asked."""

    def run(idx: Index, ids: np.ndarray, q: np.ndarray) -> Iterator[pa.RecordBatch]:
        for h in hs:
            begin = time.perf_counter()
            found = list(kernel(idx, ids, q, h))
            seconds = (time.perf_counter() - begin) / max(1, len(ids))
            for b in found:
                yield b.append_column("h", pa.array(np.full(b.num_rows, h, np.int32))).append_column("seconds", pa.array(np.full(b.num_rows, seconds)))

    merged = run_shards(index, queries, run, f"{RESULT}, h int, seconds double").groupBy("h", "qid", "vid").agg(F.min("d2").alias("d2"), *(F.max(c).alias(c) for c in ("hops", "reads", "seconds")))
    return top(merged, k, ["h", "qid"]).select("h", "qid", "rank", "vid", "d2", "hops", "reads", "seconds")


def beam_search(index: DataFrame, queries: DataFrame, h: int, k: int, mode: str = "code_only", quantizer: Quantizer | None = None, **options) -> DataFrame:
    """(qid, rank, vid, d2, hops, reads): `searcher` at one beam. A code-only search reads no vectors."""
    rows = index.drop("vec") if mode == "code_only" else index
    return sweep(rows, queries, searcher(k, mode, quantizer, **options), (h,), k).select("qid", "rank", "vid", "d2", "hops", "reads")


def search_flat(base: DataFrame, codes: DataFrame, queries: DataFrame, quantizer: Quantizer, k: int, candidates: int) -> DataFrame:
    """A scan of all codes without a graph, then original distances for the first `candidates`: (qid, rank, vid, d2)."""
    from .exact import in_cells

    rows = base.join(codes, base.id == codes.vid).select("id", F.concat("vec", F.transform("code", lambda c: c.cast("double"))).alias("vec"))
    m = quantizer.m
    asked = queries.select("id", F.concat("vec", F.array_repeat(F.lit(0.0), m)).alias("vec"))

    class Scan:
        def __init__(self, ids: np.ndarray, x: np.ndarray) -> None:
            self.ids, self.q = ids, x[:, :-m]
            self.lut, self.rows = quantizer.lut(self.q), []

        def add(self, ids: np.ndarray, x: np.ndarray) -> None:
            d = adc(self.lut, x[:, -m:].astype(int))
            d[self.ids[:, None] == ids[None]] = np.inf
            order = np.lexsort((np.broadcast_to(ids, d.shape), d))[:, :candidates]
            self.rows.append((np.repeat(self.ids, order.shape[1]), ids[order].ravel(), np.take_along_axis(d, order, 1).ravel(), np.take_along_axis(d2_pairs(self.q, x[:, :-m]), order, 1).ravel()))

        def out(self) -> Iterator[pa.RecordBatch]:
            for q, v, a, d in self.rows:
                ok = np.isfinite(a)
                yield pa.RecordBatch.from_arrays([pa.array(x[ok]) for x in (q, v, a, d)], ["qid", "vid", "adc", "d2"])

    near = in_cells(rows, asked, Scan, "qid long, vid long, adc double, d2 double")
    first = top(near, candidates, order=("adc", "vid")).drop("rank")
    return top(first, k).select("qid", "rank", "vid", "d2")


def beam_search_joins(codes: DataFrame, edges: DataFrame, lut: DataFrame, entry: int, h: int, k: int, own: bool = False) -> DataFrame:
    """The code-only walk hop by hop: state joined with links and their codes, all queries at once. (qid, rank, vid, d2, hops). Each
    vertex's links are stored with their ends' codes once, in buckets, so a hop is one join and shuffles the searches that go on at most."""
    ends = edges.select("src", "dst").distinct().join(codes.select(F.col("vid").alias("dst"), "code"), "dst").groupBy("src").agg(F.collect_list(F.struct("dst", "code")).alias("links"))
    every = codes.select(F.col("vid").alias("nxt")).join(ends.withColumnRenamed("src", "nxt"), "nxt", "left")
    near_of = bucketed(every, "nxt", shuffle_partitions(codes.sparkSession))
    e = codes.where(F.col("vid") == entry).select(F.col("code").alias("entry_code")).first()["entry_code"]
    start = lut.select("qid", "lut", F.array(F.struct(adc_col(F.col("lut"), F.lit(list(e)).cast("array<int>")).alias("d2"), F.lit(entry).cast("long").alias("vid"))).alias("beam"), F.array().cast("array<long>").alias("visited"))
    state, done, hop = materialize(start), None, 0
    while True:
        nxt = state.withColumn("nxt", F.get(F.filter("beam", lambda c: ~F.array_contains("visited", c["vid"])), F.lit(0))["vid"])
        ended = nxt.where("nxt is null").select("qid", "beam", F.size("visited").cast("long").alias("hops"))
        done = ended if done is None else done.unionByName(ended)
        going = nxt.where("nxt is not null")
        if going.isEmpty():
            break
        fresh = F.filter("links", lambda c: ~F.exists("beam", lambda b: b["vid"] == c["dst"]))  # array_distinct compares all pairs of structs: hubs have thousands of links
        near = F.transform(fresh, lambda c: F.struct(adc_col(F.col("lut"), c["code"]).alias("d2"), c["dst"].alias("vid")))
        grown = going.join(near_of, "nxt").withColumn("near", F.coalesce(near, F.filter("beam", lambda c: F.lit(False))))
        state = grown.select("qid", "lut", F.slice(F.array_sort(F.concat("beam", "near")), 1, h).alias("beam"), F.array_append("visited", F.col("nxt")).alias("visited"))
        state = materialize(state)
        hop += 1
    flat = done.select("qid", "hops", F.explode("beam").alias("c")).select("qid", "hops", "c.d2", "c.vid")
    return top(flat if own else flat.where("vid <> qid"), k).select("qid", "rank", "vid", "d2", "hops")
