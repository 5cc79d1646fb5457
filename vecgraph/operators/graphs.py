"""Proximity graph builders over shards of bounded size, and measures of graphs.

A shard (at most SHARD_ROWS vectors) is built in one task: a candidate pool of near rows, then pruning by
one of two rules, then reverse links, pruned again to the degree. Larger sets are cut into cells, each row in
its two nearest ones; the cells' links are united and pruned once more by the same rule. Where all vertices have
to be reachable, those not reached are attached after that, and no link made for it is cut.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecgraph.functions.kernels import d2_blas, matrix
from vecgraph.session import materialize, ship

from .exact import mean_vector, top
from .quantize import centres_over, kmeans, sample

#: Distances that pool_of holds at once; rows of a cell beyond which it is cut by hash, so that no task gets a hot cell.
POOL_CELLS, CELL_MOST = 1 << 23, 100_000
#: Numbers of candidates' vectors that are pruned in step.
PRUNE_CELLS = 1 << 19
EDGES = "src long, dst long, d2 double, level int"


def pool_of(x: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Places and distances of each row's k nearest others, ties to the smaller place, in blocks. The k-th smallest of the least of groups
    of columns is no less than the k-th smallest of all, so few places are left to sort."""
    n = len(x)
    k = min(k, n - 1)
    place, dist = np.empty((n, k), int), np.empty((n, k))
    step, g = max(1, min(1024, POOL_CELLS // max(n, 1))), max(1, min(32, n // max(1, 8 * k)))
    norm, twice, m = (x * x).sum(1), -2 * x.T, n // g
    for i in range(0, n if k > 0 else 0, step):
        d = x[i : i + step] @ twice  # as d2_blas, in place
        d += norm[i : i + step, None]
        d += norm[None]
        np.maximum(d, 0, out=d)
        d[np.arange(len(d)), np.arange(i, i + len(d))] = np.inf
        least = np.concatenate([d[:, : g * m].reshape(len(d), g, m).min(1), d[:, g * m :]], 1) if g > 1 else d
        bound = np.partition(least, k - 1, 1)[:, k - 1]
        row, col = np.divmod(np.flatnonzero(d <= bound[:, None]), n)
        near = d[row, col]
        order = np.lexsort((col, near, row))
        size = np.bincount(row, minlength=len(d))
        if size.min() < k:  # numbers that can't be compared: such places come last
            order = np.argsort(d, 1, kind="stable")[:, :k]
            place[i : i + step], dist[i : i + step] = order, np.take_along_axis(d, order, 1)
            continue
        first = order[(np.cumsum(size) - size)[:, None] + np.arange(k)]
        place[i : i + step], dist[i : i + step] = col[first], near[first]
    return place, dist


def prune(x: np.ndarray, v: int, cand: np.ndarray, degree: int, alpha: float) -> np.ndarray:
    """From the nearest on, keep a candidate unless a kept one p has alpha * d(p, c) <= d(v, c) (plain distances)."""
    d = np.sqrt(((x[cand] - x[v]) ** 2).sum(1))
    order = np.lexsort((cand, d))
    cand, d = cand[order], d[order]
    kept: list[int] = []
    open_ = np.ones(len(cand), bool)
    for i in range(len(cand)):
        if not open_[i]:
            continue
        kept.append(int(cand[i]))
        if len(kept) == degree:
            break
        between = np.sqrt(((x[cand] - x[cand[i]]) ** 2).sum(1))
        open_ &= alpha * between > d
    return np.array(kept, int)


def pruned(x: np.ndarray, vertex: np.ndarray, group: np.ndarray, cand: np.ndarray, degree: int, alpha: float) -> np.ndarray:
    """Which pairs of a group (of the vertex `vertex[group]`) and a candidate `prune` keeps, many groups in step: in each round every one of
    them keeps its first open candidate and measures its other open ones against it. Of equal pairs one is kept."""
    keep = np.zeros(len(cand), bool)
    if not len(cand):
        return keep
    by_group = np.argsort(group, kind="stable")
    size = np.bincount(group, minlength=len(vertex))
    begin = np.cumsum(size) - size
    some = np.argsort(size, kind="stable")
    some, at = some[size[some] > 0], 0
    while at < len(some):
        most = max(1, PRUNE_CELLS // (x.shape[1] * int(size[some[at]])))
        width = int(size[some[min(at + most, len(some)) - 1]])  # sizes ascend, so the last is the widest
        here = some[at : at + max(1, min(most, PRUNE_CELLS // (x.shape[1] * width)))]
        at += len(here)
        width = int(size[here[-1]])
        real = np.arange(width) < size[here][:, None]
        pair = by_group[begin[here][:, None] + np.where(real, np.arange(width), 0)]
        c = cand[pair]
        d = np.sqrt(((x[c.ravel()] - np.repeat(x[vertex[here]], width, 0)) ** 2).sum(1)).reshape(c.shape)
        order = np.lexsort((c, np.where(real, d, np.inf), ~real))
        pair, c, d, open_ = (np.take_along_axis(v, order, 1) for v in (pair, c, d, real))
        y, rows = x[c], np.arange(len(here))
        for _ in range(degree):
            rows = rows[open_[rows].any(1)]
            if not len(rows):
                break
            first = open_[rows].argmax(1)
            keep[pair[rows, first]] = True
            open_[rows, first] = False
            i, j = np.nonzero(open_[rows])
            r = rows[i]
            between = np.sqrt(((y[r, j] - y[rows, first][i]) ** 2).sum(1))
            open_[r, j] = alpha * between > d[r, j]
    return keep


def alpha_links(x: np.ndarray, degree: int, pool: int, alpha: float) -> list[np.ndarray]:
    """Two passes (alpha one, then larger), each with reverse links pruned back to the degree."""
    place, _ = pool_of(x, pool)
    n, every = len(x), np.arange(len(x))
    near = np.repeat(every, place.shape[1]), place.ravel()
    src = dst = np.empty(0, int)
    for a in (1.0, alpha) if alpha > 1 else (1.0,):
        src, dst = np.concatenate([near[0], src]), np.concatenate([near[1], dst])
        kept = pruned(x, every, src, dst, degree, a)
        src, dst = src[kept], dst[kept]
        src, dst = np.divmod(np.unique(np.concatenate([src * n + dst, dst * n + src])), n)
        many = np.bincount(src, minlength=n)[src] > degree
        kept = ~many
        kept[many] = pruned(x, every, src[many], dst[many], degree, a)
        src, dst = src[kept], dst[kept]
    return np.split(dst, np.searchsorted(src, np.arange(1, n)))


def attach_unreached(x: np.ndarray, links: list[np.ndarray], entry: int | np.ndarray) -> list[np.ndarray]:
    """Breadth first from the entry (or several); each vertex not reached gets a link from the nearest one reached."""
    n = len(x)
    reached = np.zeros(n, bool)

    def spread(front: np.ndarray) -> None:
        while len(front):
            reached[front] = True
            front = np.unique(np.concatenate([links[v] for v in front])).astype(int)
            front = front[~reached[front]]

    spread(np.atleast_1d(entry))
    while not reached.all():
        v = int(np.flatnonzero(~reached)[0])
        have = np.flatnonzero(reached)
        near = have[np.argmin(((x[have] - x[v]) ** 2).sum(1))]
        links[near] = np.append(links[near], v)
        spread(np.array([v]))
    return links


def levels_of(ids: np.ndarray, ml: float) -> np.ndarray:
    """Level of each vertex from a hash of its id: floor(-ln(u) * ml); u has 32 bits, so there are at most 22.9 * ml levels above the ground."""
    import hashlib

    u = np.array([(int(hashlib.md5(str(i).encode()).hexdigest()[:8], 16) + 0.5) / 2**32 for i in ids.tolist()])
    return np.floor(-np.log(u) * ml).astype(int)


def shard_links(kind: str, ids: np.ndarray, x: np.ndarray, degree: int, pool: int, alpha: float, ml: float, attach: bool = True) -> tuple[np.ndarray, ...]:
    """(src, dst, d2, level) of one shard."""
    level = levels_of(ids, ml) if kind == "layered" else np.zeros(len(ids), int)
    out = []
    for lv in range(level.max(initial=0) + 1):
        here = np.flatnonzero(level >= lv)
        if len(here) < 2:
            continue
        y = x[here]
        links = alpha_links(y, degree, pool, alpha if kind == "flat" else 1.0)
        entry = int(np.argmin(((y - x.mean(0)) ** 2).sum(1)))
        if kind != "flat" and attach:
            links = attach_unreached(y, links, entry)
        src = np.repeat(here, [len(r) for r in links])
        dst = here[np.concatenate(links)] if links else np.empty(0, int)
        out.append((ids[src], ids[dst], ((x[src] - x[dst]) ** 2).sum(1), np.full(len(src), lv)))
    return tuple(np.concatenate(c) for c in zip(*out, strict=True)) if out else (np.empty(0, np.int64),) * 4


def cell_tables(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """One table per cell, from batches sorted by cell."""
    at, held = None, []
    for b in batches:
        t = pa.Table.from_batches([b])
        cell = t["cell"].to_numpy()
        for c in np.unique(cell):
            if c != at and held:
                yield pa.concat_tables(held).combine_chunks()
                held = []
            at = c
            held.append(t.filter(pa.array(cell == c)))
    if held:
        yield pa.concat_tables(held).combine_chunks()


def edge_batch(src: list, dst: list, d2: list, level: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(src, pa.int64()), pa.array(dst, pa.int64()), pa.array(d2, pa.float64()), pa.array(level, pa.int32())], ["src", "dst", "d2", "level"])


def links_of(t: pa.Table, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places of both ends and the levels of the links kept in a cell's table (ids ascending); ends elsewhere are left out."""
    src = np.repeat(np.arange(len(ids)), pc.fill_null(pc.list_value_length(t["dsts"]), 0).to_numpy())
    dst, lv = pc.list_flatten(t["dsts"]).to_numpy(), pc.list_flatten(t["levels"]).to_numpy()
    to = np.minimum(np.searchsorted(ids, dst), len(ids) - 1)
    here = ids[to] == dst
    return src[here], to[here], lv[here]


def build(base: DataFrame, kind: str, degree: int = 16, pool: int = 48, alpha: float = 1.2, ml: float = 0.5, cells: int = 1) -> DataFrame:
    """(src, dst, d2, level). kind: "flat" (rule relaxed by alpha), "spread" (alpha one, all reachable), "layered" (spread per level).

    cells > 1: every row goes to its two nearest cells; links of both are united and, beyond `degree`, pruned by the rule.
    """
    ship(base.sparkSession)
    centres = None if cells == 1 else centres_over(base, cells)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x = matrix(b.column(1))
            near = np.argsort(d2_blas(x, centres), 1, kind="stable")[:, :2] if centres is not None else np.zeros((len(x), 1), int)
            level = levels_of(b.column(0).to_numpy(), ml) if kind == "layered" else np.zeros(len(x), int)
            take = pa.table(b).take(pa.array(np.repeat(np.arange(len(x)), near.shape[1])))
            take = take.append_column("cell", pa.array(near.ravel().astype(np.int32)))
            take = take.append_column("home", pa.array(np.arange(near.size) % near.shape[1] == 0))
            yield from take.append_column("level", pa.array(np.repeat(level, near.shape[1]).astype(np.int32))).combine_chunks().to_batches()

    def links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in cell_tables(batches):
            yield edge_batch(*shard_links(kind, t["id"].to_numpy(), matrix(t["vec"]), degree, pool, alpha, ml, attach=cells == 1))

    placed = base.select("id", "vec").mapInArrow(place, "id long, vec array<double>, cell int, home boolean, level int")
    if cells > 1:
        placed, cells = cut_cells(materialize(placed), cells)
    found = placed.repartitionById(max(1, cells), F.col("cell")).sortWithinPartitions("cell", "id").mapInArrow(links, EDGES)
    if cells == 1:
        return found
    united = prune_united(placed, materialize(found.select("src", "dst", "level").distinct()), cells, degree, alpha if kind == "flat" else 1.0)
    return united if kind == "flat" else attach_across(base, placed, united, cells)


def cut_cells(placed: DataFrame, cells: int) -> tuple[DataFrame, int]:
    """The rows with cells of more than CELL_MOST cut by a hash of the id, and the number of cells then."""
    size = {r.cell: r["n"] for r in placed.groupBy("cell").agg(F.count("*").alias("n")).collect()}  # as many rows as cells
    if max(size.values(), default=0) <= CELL_MOST:
        return placed, cells
    parts, at = [], 0
    for c in sorted(size):
        n = -(-size[c] // CELL_MOST)
        parts.append((c, at, n))
        at += n
    known = F.broadcast(placed.sparkSession.createDataFrame(parts, "cell int, first int, many int"))
    part = F.col("first") + F.pmod(F.xxhash64("id", F.lit(5)), F.col("many")).cast("int")
    return placed.join(known, "cell").withColumn("cell", part).select(*placed.columns), at


def knn_graph_cells(base: DataFrame, k: int, cells: int, overlap: int = 4) -> DataFrame:
    """(src, dst, d2): every row's k nearest others among the rows that share one of its `overlap` nearest cells. Work grows with the
    rows times a cell's size, not with their square; recall against exact.knn_graph is to be measured, and grows with `overlap`."""
    ship(base.sparkSession)
    centres = kmeans(sample(base, 100_000), cells, 8)[0]

    def near(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                to = np.argsort(d2_blas(matrix(b.column(1)), centres), 1, kind="stable")[:, :overlap]
                take = pa.table(b).take(pa.array(np.repeat(np.arange(b.num_rows), to.shape[1])))
                yield from take.append_column("cell", pa.array(to.ravel().astype(np.int32))).combine_chunks().to_batches()

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in cell_tables(batches):
            ids, x = t["id"].to_numpy(), matrix(t["vec"])
            if len(ids) > 1:
                place, _ = pool_of(x, k)
                src = np.repeat(np.arange(len(ids)), place.shape[1])
                dst = place.ravel()
                yield pa.RecordBatch.from_arrays([pa.array(ids[src]), pa.array(ids[dst]), pa.array(((x[src] - x[dst]) ** 2).sum(1))], ["src", "dst", "d2"])

    placed, n = cut_cells(materialize(base.select("id", "vec").mapInArrow(near, "id long, vec array<double>, cell int")), cells)
    found = placed.repartitionById(n, F.col("cell")).sortWithinPartitions("cell", "id").mapInArrow(pairs, "src long, dst long, d2 double")
    one = found.groupBy("src", "dst").agg(F.min("d2").alias("d2"))
    return top(one, k, "src", ("d2", "dst")).select("src", "dst", "d2")


def _in_cells(rows: DataFrame, edges: DataFrame, cells: int) -> DataFrame:
    """rows (cell, id, vec, own, ...) with the links of own rows, each cell in one task, ids ascending."""
    out = edges.groupBy("src").agg(F.collect_list(F.struct("dst", "level")).alias("l")).select("src", F.lit(True).alias("own"), F.col("l.dst").alias("dsts"), F.col("l.level").alias("levels"))
    joined = rows.join(out.withColumnRenamed("src", "id"), ["id", "own"], "left")
    return joined.repartitionById(cells, F.col("cell")).sortWithinPartitions("cell", "id")


def prune_united(placed: DataFrame, united: DataFrame, cells: int, degree: int, alpha: float) -> DataFrame:
    """Prune each vertex's links in its home cell; vectors of links' ends that live elsewhere are sent there once."""

    def in_cell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in cell_tables(batches):
            ids, x = t["id"].to_numpy(), matrix(t["vec"])
            src, dst, level = links_of(t, ids)
            order = np.lexsort((dst, src, level))
            src, dst, level = src[order], dst[order], level[order]
            first = np.diff(src, prepend=-1) | np.diff(level, prepend=-1) != 0
            group = np.cumsum(first) - 1
            many = np.bincount(group)[group] > degree if len(group) else first
            keep = ~many
            keep[many] = pruned(x, src[first], group[many], dst[many], degree, alpha)
            if len(keep):
                at = np.flatnonzero(keep)
                s, d = src[at], dst[at]
                yield edge_batch(ids[s], ids[d], ((x[s] - x[d]) ** 2).sum(1), level[at])

    home = placed.where("home").select("id", "vec", "cell")
    ends = united.join(home.select(F.col("id").alias("src"), "cell"), "src").select("cell", F.col("dst").alias("id")).distinct()
    away = ends.join(home.select("id", "cell"), ["id", "cell"], "left_anti").join(home.select("id", "vec"), "id")
    rows = home.withColumn("own", F.lit(True)).unionByName(away.select("id", "vec", "cell", F.lit(False).alias("own")))
    return materialize(_in_cells(rows, united, cells).mapInArrow(in_cell, EDGES))


def spread_from(edges: DataFrame, entries: DataFrame) -> DataFrame:
    """(level, vid) of all that is reachable on each level from its entry."""
    seen = front = materialize(entries.select("level", "vid"))
    step = edges.select("level", F.col("src").alias("vid"), "dst")
    while not front.isEmpty():
        ring = front.join(step, ["level", "vid"]).select("level", F.col("dst").alias("vid")).distinct()
        front = materialize(ring.join(seen, ["level", "vid"], "left_anti"))
        seen = seen.unionByName(front)
    return seen


def level_entries(base: DataFrame, members: DataFrame) -> DataFrame:
    """(level, vid): of the vertices on each level that has several, the one nearest to the mean of the base."""
    from vecgraph.functions.columns import d2

    mean = F.lit(mean_vector(base)).cast("array<double>")
    each = members.select("id", d2(F.col("vec"), mean).alias("d2"), F.explode(F.sequence(F.lit(0), "level")).alias("level"))
    return each.groupBy("level").agg(F.min(F.struct("d2", "id")).alias("b"), F.count("*").alias("n")).where("n > 1").select("level", F.col("b.id").alias("vid"))


def attach_across(base: DataFrame, placed: DataFrame, edges: DataFrame, cells: int) -> DataFrame:
    """Add links until each level is reachable from its entry, whatever the degree.

    In each home cell a vertex not reached gets a link from the nearest one reached there. A cell in which none is
    reached is attached to its first vertex, and that one to the nearest vertex reached anywhere.
    """
    home = placed.where("home").select("id", "vec", "cell", "level")
    seen = materialize(spread_from(edges, level_entries(base, home)))

    def attached(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in cell_tables(batches):
            ids, x, top = t["id"].to_numpy(), matrix(t["vec"]), t["level"].to_numpy()
            src, dst, level = links_of(t, ids)
            reached_on = [set(r or ()) for r in t["reached"].to_pylist()]
            for lv in range(top.max(initial=0) + 1):
                here = np.flatnonzero(top >= lv)
                start = np.flatnonzero([lv in reached_on[v] for v in here])
                if len(start) == len(here):
                    continue
                if not len(start):
                    start = np.zeros(1, int)
                    yield edge_batch([None], [ids[here[0]]], [None], [lv])
                on, y = level == lv, x[here]
                s, d = np.searchsorted(here, src[on]), np.searchsorted(here, dst[on])
                order = np.argsort(s, kind="stable")
                old = np.split(d[order], np.searchsorted(s[order], np.arange(1, len(here))))
                many = [len(r) for r in old]
                new = [r[n:] for r, n in zip(attach_unreached(y, old, start), many, strict=True)]
                a, b = np.repeat(np.arange(len(here)), [len(r) for r in new]), np.concatenate(new).astype(int)
                yield edge_batch(ids[here[a]], ids[here[b]], ((y[a] - y[b]) ** 2).sum(1), np.full(len(a), lv))

    rows = home.withColumn("own", F.lit(True)).join(seen.groupBy(F.col("vid").alias("id")).agg(F.collect_list("level").alias("reached")), "id", "left")
    made = materialize(_in_cells(rows, edges, cells).mapInArrow(attached, EDGES))
    roots = made.where("src is null").select("level", F.col("dst").alias("id")).join(home.select("id", "vec"), "id").collect()  # one per cell and level at most
    out = edges.unionByName(made.where("src is not null"))
    if not roots:
        return out
    r_id, r_level, r_vec = np.array([r.id for r in roots]), np.array([r.level for r in roots]), np.array([r.vec for r in roots])

    def nearest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            num, lv = b.column(0).to_numpy(), b.column(2).to_numpy()
            x = matrix(b.column(1))
            for i in range(len(r_id)):
                on = np.flatnonzero(lv == r_level[i])
                if len(on):
                    d = ((x[on] - r_vec[i]) ** 2).sum(1)
                    yield edge_batch([num[on[d.argmin()]]], [r_id[i]], [d.min()], [r_level[i]])

    reached = seen.withColumnRenamed("vid", "id").join(home.select("id", "vec"), "id").select("id", "vec", "level")
    best = reached.mapInArrow(nearest, EDGES).groupBy("dst", "level").agg(F.min(F.struct("d2", "src")).alias("b"))
    return out.unionByName(best.select("b.src", "dst", "b.d2", "level"))


def graph_stats(edges: DataFrame) -> DataFrame:
    """One row: vertices with out-links, edges, and the spread of out-degrees."""
    deg = edges.groupBy("src").agg(F.count("*").alias("deg"))
    return deg.agg(F.count("*").alias("vertices"), F.sum("deg").alias("edges"), F.min("deg").alias("min_deg"), F.max("deg").alias("max_deg"), F.round(F.avg("deg"), 6).alias("avg_deg"))


def reachable(edges: DataFrame, entry: int) -> DataFrame:
    """(vid, hops): breadth first from the entry, one join per ring; the visited set is a table, never collected."""
    spark = edges.sparkSession
    seen = materialize(spark.createDataFrame([(entry, 0)], "vid long, hops int"))
    front = seen
    hop = 0
    while not front.isEmpty():
        hop += 1
        ring = front.join(edges.select(F.col("src").alias("vid"), "dst"), "vid").select(F.col("dst").alias("vid")).distinct()
        front = materialize(ring.join(seen, "vid", "left_anti").withColumn("hops", F.lit(hop)))
        seen = seen.unionByName(front)
    return seen


def entry_vertex(base: DataFrame) -> int:
    """The id of the row nearest to the mean."""
    from vecgraph.functions.columns import d2

    mean = F.lit(mean_vector(base)).cast("array<double>")
    return base.select(F.struct(d2(F.col("vec"), mean).alias("d2"), "id").alias("b")).agg(F.min("b").alias("b")).first().b.id


def top_vertex(base: DataFrame, edges: DataFrame) -> int:
    """Where a layered walk enters: of the vertices on the highest level that has links, the smallest id."""
    best = edges.groupBy("level").agg(F.min("src").alias("src")).orderBy(F.desc("level")).first()
    return best.src if best else entry_vertex(base)
