"""SimHash near-duplicates with a Gray-order hierarchical index.

Fingerprints of two documents within `distance` bits agree on at least blocks - distance of `blocks` bit
blocks. Each different fingerprint goes, for every choice of that many blocks, to the cell of their bits;
so each pair of near fingerprints meets in some cell. In a cell the fingerprints are sorted by Gray rank and
indexed: leaves in groups of FAN, an upper node for each group with the bits all its members share; a node
holds only the shared bits its parent lacks. A search adds up the differences along the path and leaves a
group as soon as they exceed the distance, or when group and query are known to be connected already. Each
cell returns a star per connected set, never all pairs; stars are joined by contraction rounds.

The number of blocks grows with the number of fingerprints so that cells stay small; each choice is exact.

Defined cases: a null text, and one without words, has fingerprint zero and links like any other; fewer
words than a shingle: the whole sequence is the one shingle; repeated rows share a component; an empty
table gives an empty result; a null doc_id stays a row and is no component id unless all ids in it are null.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecgraph.session import materialize, ship, shuffle_partitions

from .common import ROW, column, fresh, id_text, raw, row_keys, slices, small

FAN = 16
#: Members that a cell should have on average, at most.
CELL = 4096
#: Fingerprints indexed together by a task (whole cells); pairs of query and node looked at together.
GATHER, FRONT = 200_000, 2_000_000


def fingerprint(text: bytes | None, shingle: int = 4, seed: int = 42) -> int:
    words = (text or b"").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    k = min(shingle, len(words))
    digest = xxhash.xxh64_intdigest
    h = np.fromiter((digest(joined[a:b], seed) for a, b in zip(starts[: len(words) - k + 1].tolist(), ends[k - 1 :].tolist(), strict=True)), np.uint64, len(words) - k + 1)
    ones = np.zeros(64, np.int64)
    for i in range(0, len(h), 1 << 16):
        ones += np.unpackbits(h[i : i + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.uint32)
    return int(np.packbits(2 * ones > len(h), bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, shingle: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, row, row2, fp long) of every whole text."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            fp = np.fromiter((fingerprint(t, shingle) for t in raw(b)), np.uint64, b.num_rows)
            yield pa.RecordBatch.from_arrays([*(column(b, c) for c in ("doc_id", *ROW)), pa.array(fp.view(np.int64))], ["doc_id", *ROW, "fp"])

    return id_text(docs, id_col, text_col).select("doc_id", *row_keys(), "text").mapInArrow(run, "doc_id long, row long, row2 long, fp long")


def gray_rank(x: np.ndarray) -> np.ndarray:
    """Place of a code in the reflected Gray sequence."""
    x = x.copy()
    for s in (1, 2, 4, 8, 16, 32):
        x ^= x >> np.uint64(s)
    return x


def _merge(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Smallest member of each connected set, after links a-b between members of labelled sets."""
    a, b = label[a], label[b]
    while len(a):
        low = np.minimum(a, b)
        np.minimum.at(label, a, low)
        np.minimum.at(label, b, low)
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up
        a, b = label[a], label[b]
        open_ = a != b
        a, b = a[open_], b[open_]
    return label


class GrayIndex:
    """The hierarchical index over whole cells (sorted numbers in `cell`) and its self-search."""

    def __init__(self, cell: np.ndarray, fp: np.ndarray, distance: int) -> None:
        order = np.lexsort((gray_rank(fp), cell))
        self.cell, self.fp, self.order, self.distance = cell[order], fp[order], order, distance
        self.levels: list[dict[str, np.ndarray]] = []
        group = self.cell
        lo = np.arange(len(fp))
        hi = lo + 1
        both, any_ = self.fp, self.fp
        while True:
            first = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
            place = np.arange(len(group)) - np.repeat(first, np.diff(np.append(first, len(group))))
            head = np.flatnonzero(place % FAN == 0)  # the first child of each node
            both, any_ = np.bitwise_and.reduceat(both, head), np.bitwise_or.reduceat(any_, head)
            ends = np.append(head[1:], len(group))
            lo, hi = lo[head], hi[ends - 1]
            self.levels.append({"lo": lo, "hi": hi, "child": head, "children": ends - head, "bits": both, "shared": ~(both ^ any_)})
            group = group[head]
            if len(first) == len(head):
                break
        for child, parent in zip(self.levels, self.levels[1:], strict=False):
            child["own"] = child["shared"] & ~np.repeat(parent["shared"], parent["children"])
        self.levels[-1]["own"] = self.levels[-1]["shared"]
        self.root = np.searchsorted(self.levels[-1]["lo"], np.arange(len(fp)), "right") - 1

    def _even(self, label: np.ndarray) -> None:
        """Mark the nodes all of whose leaves are known to be connected."""
        for v in self.levels:
            v["set"] = np.where(np.minimum.reduceat(label, v["lo"]) == np.maximum.reduceat(label, v["lo"]), label[v["lo"]], -1)

    def stars(self) -> np.ndarray:
        """For each fingerprint, in the order given, the place of one member of its connected set (the same for all)."""
        n = len(self.fp)
        label = np.arange(n)
        for turn in (0, 13, 26, 39, 52):  # neighbours in several Gray orders: most of a group of near copies
            x = (self.fp << np.uint64(turn)) | (self.fp >> np.uint64((64 - turn) % 64))
            o = np.lexsort((gray_rank(x), self.cell))
            near = (self.cell[o[1:]] == self.cell[o[:-1]]) & (np.bitwise_count(self.fp[o[1:]] ^ self.fp[o[:-1]]) <= self.distance)
            label = _merge(label, o[:-1][near], o[1:][near])
        begin, step = 0, 4096
        while begin < n:
            self._even(label)
            q = np.arange(begin, min(n, begin + step))
            begin += step
            label = self._search(q, label)
        out = np.empty(n, np.int64)
        out[self.order] = self.order[label]
        return out

    def _search(self, q: np.ndarray, label: np.ndarray) -> np.ndarray:
        top = len(self.levels) - 1
        todo = [(top, q, self.root[q], np.zeros(len(q), np.int64))]
        while todo:
            level, q, node, gone = todo.pop()
            v = self.levels[level]
            gone = gone + np.bitwise_count((self.fp[q] ^ v["bits"][node]) & v["own"][node])
            keep = (gone <= self.distance) & (v["hi"][node] > q + 1) & (v["set"][node] != label[q])
            q, node, gone = q[keep], node[keep], gone[keep]
            if not len(q):
                continue
            size = v["children"][node]
            for lo, hi in slices(size, FRONT):
                part = slice(lo, hi)
                s = size[part]
                child = np.repeat(v["child"][node[part]], s) + np.arange(s.sum()) - np.repeat(np.cumsum(s) - s, s)
                own = np.repeat(q[part], s)
                if level:
                    todo.append((level - 1, own, child, np.repeat(gone[part], s)))
                    continue
                hit = (child > own) & (np.bitwise_count(self.fp[own] ^ self.fp[child]) <= self.distance) & (label[own] != label[child])
                if hit.any():
                    label = _merge(label, own[hit], child[hit])
        return label


def blocks_for(n: int, distance: int) -> int:
    """Blocks so that cells keyed by blocks - distance of them have CELL random members at most."""
    b = distance + 1
    while b < 16 and n / 2.0 ** (64 * (b - distance) / b) > CELL:
        b += 1
    return b


def masks(blocks: int, distance: int) -> list[int]:
    cuts = [64 * i // blocks for i in range(blocks + 1)]
    block = [((1 << cuts[i + 1]) - 1) ^ ((1 << cuts[i]) - 1) for i in range(blocks)]
    return [sum(block[i] for i in chosen) for chosen in combinations(range(blocks), blocks - distance)]


def near_links(fps: DataFrame, distance: int = 4) -> DataFrame:
    """Different fingerprints (fp) -> stars (a, b), a > b, that connect what is connected within each cell."""
    spark = fps.sparkSession
    signed = lambda m: m - (1 << 64) if m >> 63 else m
    choice = masks(blocks_for(fps.count(), distance), distance)
    cells = fps.select("fp", F.posexplode(F.array(*[F.col("fp").bitwiseAND(F.lit(signed(m)).cast("long")) for m in choice])).alias("choice", "key"))

    def link(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(parts: list) -> Iterator[pa.RecordBatch]:
            choice, key, fp = (np.concatenate([p[i] for p in parts]) for i in range(3))
            new = np.concatenate([[True], (choice[1:] != choice[:-1]) | (key[1:] != key[:-1])])
            cell = np.cumsum(new)
            size = np.bincount(cell)[cell]
            cell, fp = cell[size > 1], fp[size > 1]
            if not len(fp):
                return
            star = GrayIndex(cell, fp.view(np.uint64), distance).stars()
            root = np.full(len(fp), np.iinfo(np.int64).max)
            np.minimum.at(root, star, fp)
            root = root[star]
            off = root != fp
            yield pa.RecordBatch.from_arrays([pa.array(fp[off]), pa.array(root[off])], ["a", "b"])

        held, n = [], 0
        for b in batches:
            arrays = tuple(column(b, c).to_numpy() for c in ("choice", "key", "fp"))
            if n >= GATHER:  # give out all cells but the last, which may go on
                choice, key, _ = arrays
                joined = [np.concatenate([p[i] for p in held]) for i in range(3)]
                last = np.flatnonzero((joined[0] != joined[0][-1]) | (joined[1] != joined[1][-1]))
                if len(last):
                    cut = last[-1] + 1
                    yield from out([tuple(x[:cut] for x in joined)])
                    held = [tuple(x[cut:] for x in joined)]
                    n = len(held[0][0])
            held.append(arrays)
            n += len(arrays[0])
        if held:
            yield from out(held)

    dealt = cells.repartition(shuffle_partitions(spark), "choice", "key").sortWithinPartitions("choice", "key")
    return dealt.mapInArrow(link, "a long, b long").distinct()


def connected(edges: DataFrame) -> DataFrame:
    """Edges (a, b) -> (node, root): the smallest node of each connected set, for nodes that have edges.

    Each round points every node at its smallest neighbour (and that one's), replaces edges' ends by what they
    point at and drops loops; a hub's edges are pre-aggregated. Rounds fall with the logarithm of the paths.
    """
    found = None
    edges = materialize(edges.where("a <> b"))
    while not edges.isEmpty():
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        point = materialize(both.groupBy("a").agg(F.min("b").alias("b")).select(F.col("a").alias("node"), F.least("a", "b").alias("up")))
        jump = point.select(F.col("node").alias("up"), F.col("up").alias("up2"))
        point = materialize(point.join(jump, "up").select("node", F.col("up2").alias("up")))
        found = point.withColumnRenamed("up", "root") if found is None else materialize(found.join(point.withColumnsRenamed({"node": "root"}), "root", "left").select("node", F.coalesce("up", "root").alias("root")))
        a = point.select(F.col("node").alias("a"), F.col("up").alias("ua"))
        b = point.select(F.col("node").alias("b"), F.col("up").alias("ub"))
        edges = materialize(edges.join(a, "a").join(b, "b").where("ua <> ub").select(F.greatest("ua", "ub").alias("a"), F.least("ua", "ub").alias("b")).distinct())
    return found if found is not None else edges.select(F.col("a").alias("node"), F.col("b").alias("root"))


def classes(prints: DataFrame, distance: int = 4) -> DataFrame:
    """prints(doc_id, fp, ...) -> (fp, root, component_id): the connected set of every different fingerprint and the smallest id in it."""
    first = materialize(prints.groupBy("fp").agg(F.min("doc_id").alias("first")))
    roots = connected(near_links(first.select("fp"), distance))
    member = first.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    least = member.groupBy("root").agg(F.min("first").alias("component_id"))
    return materialize(member.join(least, "root").select("fp", "root", "component_id"))


def near_duplicates(docs: DataFrame, shingle: int = 4, distance: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fingerprint string, component_id): one row per document row."""
    prints = materialize(fingerprints(docs, shingle, id_col, text_col).select("doc_id", "fp"))
    return prints.join(classes(prints, distance), "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def one_of_each(docs: DataFrame, shingle: int = 4, distance: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """All columns of docs: of each connected set one row, the one with the smallest id (rows without an id come last, then
    rows go by the hashes of id and text). Of rows equal in id and text one stays, so repeated rows go as well."""
    prints = materialize(fingerprints(docs, shingle, id_col, text_col))
    ranked = prints.join(classes(prints, distance), "fp").groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", *ROW)).alias("b"))
    keys, all_ = fresh(docs.columns, *ROW), fresh([], "all")[0]
    chosen = ranked.select(*(F.col(f"b.{r}").alias(k) for r, k in zip(ROW, keys, strict=True)))
    hashed = [c for c, t in docs.dtypes if "map<" not in t and "variant" not in t]
    rows = docs.select(*row_keys(id_col, text_col, keys), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias(all_), F.xxhash64(*hashed).alias("order"))
    # repeated rows meet in map tasks first, so no task gets a hot one's copies
    return rows.groupBy(*keys).agg(F.min_by(all_, "order").alias(all_)).join(chosen, keys, "left_semi").select(f"{all_}.*")
