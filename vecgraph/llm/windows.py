"""Repeated windows of a corpus: how the suffix-array and FM-index operators get the texts that concern them.

A window is W consecutive units (bytes or words) of one document. Its key is the smallest hash among its
grams of G units, so equal windows have equal keys, and consecutive windows mostly share theirs: a maximal
run of them with one key (of up to PIECE windows) is a piece. Keys are dealt to tasks; all windows that could
be equal meet under their key, wherever their documents lie. Hashes only route: whether a window starts twice
is judged by an engine (suffix array or FM-index) over the pieces' texts.

 - A key with one piece holds no repeat (unless its smallest gram recurs within the piece: "again").
 - Of all other keys each different piece (told apart by 96 bits of a digest of its text) is sent to the key's task:
   two copies of a piece that stands in several places, one of any other. An engine over whole keys finds the
   windows that occur twice among them. Its answers go back to every document that holds the piece.
 - A key with more than HOT different pieces (a passage of very many documents, each with its own surroundings)
   is first cut finer: pieces become blocks of up to BLOCKS[0] windows that lie alike around the key's gram, keyed
   by all the units these windows share; what still is hot is cut again, down to single windows. Two copies of each
   different block go to the engine under the finer key, so no task gets a hot key's pieces, and no pair is looked at.

Long texts are cut in overlapping slices of about TOGETHER units, so memory doesn't grow with a text. Rows are told apart
by two hashes of id and text; equal rows count as two places and share their answer. Counts are by aggregation, so a
key held by a third of all documents is pre-aggregated before it is dealt.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecgraph.session import materialize, ship, shuffle_partitions

from .common import ROW, column, id_text, raw, row_keys, small

#: Units hashed at once, and bytes of pieces that an engine indexes at once (whole keys; one key may exceed it).
TOGETHER, CHUNK = 1 << 18, 4 << 20
#: Windows of a piece, at most; bytes from which on a text is no longer split into a list of words.
PIECE, LONG = 4096, 1 << 20
# fixed values: odd multipliers of the two rolling hashes, and of the mixer
BASE1, BASE2, MIX = 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0xFF51AFD7ED558CCD

#: Different pieces of one key that an engine takes at once; windows in a block, from cut to cut.
HOT, BLOCKS = 512, (64, 16, 4, 1)

#: (texts, windows of each, which to judge, window) -> for each text, which of its windows start twice.
Engine = Callable[[list[bytes], np.ndarray, np.ndarray, int], list[np.ndarray]]


class Powers:
    """Powers of an odd number and of its inverse, modulo 2^64."""

    def __init__(self, base: int) -> None:
        self.base, self.inverse, self.n = base, pow(base, -1, 1 << 64), 0

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if n > self.n:
            self.n = max(n, 2 * TOGETHER)
            self.up, self.down = (np.full(self.n, b, np.uint64) for b in (self.base, self.inverse))
            for row in (self.up, self.down):
                row[0] = 1
                np.multiply.accumulate(row, out=row)
        return self.up[:n], self.down[:n]


_POWERS = Powers(BASE1), Powers(BASE2)
_BYTE = np.random.Generator(np.random.Philox(key=[3, 5])).integers(0, 1 << 64, 256, np.uint64)
_SPACE = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])
_GAP = re.compile(rb"[\x20\x09-\x0D]")


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(32))) * np.uint64(MIX)
    return h ^ (h >> np.uint64(29))


def _sums(x: np.ndarray) -> np.ndarray:
    out = np.zeros(len(x) + 1, np.uint64)
    np.cumsum(x, out=out[1:])
    return out


def _ramp(n: np.ndarray) -> np.ndarray:
    return np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)


def sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of each w consecutive elements, by running minima from both ends of blocks of w."""
    n = len(x)
    pad = np.full(-n % w, np.iinfo(x.dtype).max, x.dtype)
    blocks = np.concatenate([x, pad]).reshape(-1, w)
    ahead = np.minimum.accumulate(blocks, 1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], 1)[:, ::-1].ravel()
    return np.minimum(behind[: n - w + 1], ahead[w - 1 : n])


def pieces(units: np.ndarray, size: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, ...]:
    """Units of some slices in a row -> (slice, first unit in the row, windows, key, again) of every piece."""
    n, w = len(units), window - gram + 1
    none = np.empty(0, np.int64)
    if n < window:
        return none, none, none, none, none.astype(bool)
    up, down = _POWERS[0].get(n + 1)
    h = _sums(units * up[:n])
    g = _mixed((h[gram:] - h[: n - gram + 1]) * down[: n - gram + 1])
    low = sliding_min(g, w)
    doc = np.repeat(np.arange(len(size)), size)
    here = doc[: n - window + 1]
    real = here == doc[window - 1 :]
    change = np.concatenate([[True], (low[1:] != low[:-1]) | (here[1:] != here[:-1]) | (real[1:] != real[:-1])])
    s = np.flatnonzero(change)
    e = np.append(s[1:], len(low))
    s, e = s[real[s]], e[real[s]]
    if not len(s):
        return none, none, none, none, none.astype(bool)
    parts = -((s - e) // PIECE)
    s, e = np.repeat(s, parts) + PIECE * _ramp(parts), np.repeat(e, parts)
    e = np.minimum(s + PIECE, e)
    # grams that are the smallest of some window that holds them
    wide = np.concatenate([np.zeros(w - 1, np.uint64), low, np.zeros(w - 1, np.uint64)])
    place = np.flatnonzero(~sliding_min(~wide, w) == g)
    a, b = np.searchsorted(place, s), np.searchsorted(place, e - 1 + w)
    many = b - a
    owner = np.repeat(np.arange(len(s)), many)
    inside = place[np.repeat(a, many) + _ramp(many)]
    again = np.bincount(owner[g[inside] == low[s][owner]], minlength=len(s)) > 1
    return here[s], s, e - s, low[s].view(np.int64), again


def word_bounds(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of all words, in bytes."""
    space = np.ones(len(text) + 2, bool)
    space[1:-1] = _SPACE[np.frombuffer(text, np.uint8)]
    edge = np.flatnonzero(space[1:] != space[:-1])
    return edge[::2], edge[1::2]


class _Known(dict):
    """Hashes of words."""

    def __missing__(self, word: bytes) -> int:
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h


class Units:
    """Documents as slices of units, their hashes, and the texts of pieces."""

    def __init__(self, kind: str, most: int = TOGETHER) -> None:
        self.kind, self.gap, self.most = kind, int(kind == "words"), most
        self.known = _Known()

    def split(self, text: bytes | None):
        return (text or b"") if self.kind == "bytes" else (text or b"").split()

    def slices(self, text: bytes | None, window: int) -> Iterator[tuple[int, bytes | list[bytes]]]:
        """(first unit, units): slices that overlap by window - 1 units, so each window is in just one."""
        text = text or b""
        if self.kind == "bytes":
            for lo in range(0, max(1, len(text) - window + 1), self.most):
                yield lo, text[lo : lo + self.most + window - 1]
            return
        held: list[bytes] = []
        at = lo = 0
        while lo < len(text):
            hi = lo + 4 * self.most
            if hi < len(text):
                found = _GAP.search(text, hi)
                hi = found.start() if found else len(text)
            held += text[lo:hi].split()
            lo = hi
            yield at, held
            if lo < len(text):
                done = max(0, len(held) - window + 1)
                at, held = at + done, held[done:]

    def hashes(self, slices: list) -> tuple[np.ndarray, bytes, np.ndarray]:
        """Hashes of the units of some slices in a row, their text, and where in it each unit begins (and the end)."""
        if self.kind == "bytes":
            data = b"".join(slices)
            return _BYTE[np.frombuffer(data, np.uint8)], data, np.arange(len(data) + 1)
        if len(self.known) > 300_000:
            self.known.clear()
        flat = [x for words in slices for x in words]
        h = np.fromiter(map(self.known.__getitem__, flat), np.uint64, len(flat))
        at = np.zeros(len(flat) + 1, np.int64)
        np.cumsum(np.fromiter(map(len, flat), np.int64, len(flat)) + 1, out=at[1:])
        return h, b" ".join(flat), at

    def digests(self, data: bytes, at: np.ndarray, first: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The first 64 and the next 32 bits of the digests of units first to end (exclusive)."""
        view, digest = memoryview(data), xxhash.xxh3_128_digest
        found = b"".join([digest(view[a:z]) for a, z in zip(at[first].tolist(), (at[end] - self.gap).tolist(), strict=True)])
        both = np.frombuffer(found, np.int64).reshape(-1, 2)
        return both[:, 0].copy(), both[:, 1].astype(np.int32)

    def reader(self, text: bytes | None) -> Callable[[int, int], bytes]:
        """(start, end) in units -> text, words joined by one space."""
        text = text or b""
        if self.kind == "bytes":
            return lambda a, z: text[a:z]
        if len(text) < LONG:
            words = text.split()
            return lambda a, z: b" ".join(words[a:z])
        first, last = word_bounds(text)
        return lambda a, z: b" ".join(text[first[a] : last[z - 1]].split()) if z > a else b""


#: A piece by its key and the digest of its text.
PIECE_ID = ["m", "c", "e"]
_IDS, _IDS_SQL = (pa.int64(), pa.int64(), pa.int32()), "m long, c long, e int"
_RUNS = pa.list_(pa.struct([("lo", pa.int64()), ("hi", pa.int64())]))
_RUNS_SQL = "runs array<struct<lo:long,hi:long>>"
_TEXTS_SQL = f"{_IDS_SQL}, copy int, n long, piece binary"


def repeated_windows(docs: DataFrame, kind: str, window: int, gram: int, engine: Engine) -> DataFrame:
    """docs(row, row2, text) -> (row, row2, runs array<struct<lo,hi>>): starts of windows that also start anywhere else, as runs; a document may have several rows."""
    spark = docs.sparkSession
    ship(spark)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        units = Units(kind, TOGETHER)

        def found(held: list[tuple]) -> pa.RecordBatch:
            of, base, slices = zip(*held, strict=True)
            size = np.fromiter(map(len, slices), np.int64, len(slices))
            h, data, at = units.hashes(slices)
            d, s, n, m, again = pieces(h, size, window, gram)
            c, e = units.digests(data, at, s, s + n - 1 + window)
            start = s - (np.cumsum(size) - size)[d] + np.array(base, np.int64)[d]
            ids = np.array(of, np.int64).reshape(-1, 2)[d]
            return pa.RecordBatch.from_arrays([pa.array(x) for x in (ids[:, 0], ids[:, 1], start, n, m, c, e, again)], [*ROW, "start", "n", *PIECE_ID, "again"])

        for b in small(batches):
            rows = zip(*(column(b, r).to_pylist() for r in ROW), strict=True)
            held, size = [], 0
            for row, text in zip(rows, raw(b), strict=True):
                for lo, part in units.slices(text, window):
                    held.append((row, lo, part))
                    size += len(part)
                    if size >= TOGETHER:
                        yield found(held)
                        held, size = [], 0
            if held:
                yield found(held)

    cuts = materialize(docs.mapInArrow(cut, f"row long, row2 long, start long, n long, {_IDS_SQL}, again boolean"))
    stats = cuts.groupBy("m").agg(F.count("*").alias("pieces"), F.max("again").alias("twice")).where("pieces > 1 or twice")
    shared = materialize(cuts.drop("again").join(stats.select("m"), "m"))
    at = F.struct(*ROW, "start", "n")
    one = shared.groupBy(*PIECE_ID).agg(F.min(at).alias("a"), F.max(at).alias("b"), F.count("*").alias("places"))
    one = materialize(one)
    pair = F.when(F.col("places") > 1, F.array("a", "b")).otherwise(F.array("a"))
    asked = one.select(*PIECE_ID, F.posexplode(pair).alias("copy", "at")).select(*PIECE_ID, "copy", "at.*")
    asked = asked.groupBy(*ROW).agg(F.collect_list(F.struct(*PIECE_ID, "copy", "start", "n")).alias("asked"))

    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        units, seen = Units(kind), set()
        for b in small(batches):
            lists, texts = column(b, "asked"), raw(b)
            rows = list(zip(*(column(b, r).to_pylist() for r in ROW), strict=True))
            ends, flat = lists.offsets.to_pylist(), lists.flatten()
            start, n = flat.field("start").to_pylist(), flat.field("n").to_pylist()
            at0 = ends[0]
            out, take, held = [], [], 0
            for i, t in enumerate(texts):
                if rows[i] in seen:
                    continue
                seen.add(rows[i])
                read = units.reader(t)
                for j in range(ends[i] - at0, ends[i + 1] - at0):
                    out.append(read(start[j], start[j] + n[j] - 1 + window))
                    take.append(j)
                    held += len(out[-1])
                    if held > 8 * CHUNK:
                        yield _fetched(flat, take, out)
                        out, take, held = [], [], 0
            yield _fetched(flat, take, out)

    texts = docs.join(asked, ROW).select(*ROW, "asked", "text").mapInArrow(fetch, _TEXTS_SQL)

    def engine_runs(found: DataFrame) -> DataFrame:
        """(m, c, e, copy, n, piece) -> (m, c, e, runs): the engine over whole keys."""
        dealt = found.repartition(shuffle_partitions(spark), "m").sortWithinPartitions(*PIECE_ID, "copy")
        return dealt.mapInArrow(index, f"{_IDS_SQL}, {_RUNS_SQL}")

    def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(rows: list[tuple]) -> pa.RecordBatch:
            judged = np.array([r[3] == 0 for r in rows])
            answers, who = [], []
            for r, ask, twice in zip(rows, judged, engine([r[5] for r in rows], np.array([r[4] for r in rows]), judged, window), strict=True):
                edge = np.flatnonzero(np.diff(np.concatenate([[0], twice.astype(np.int8), [0]]))) if ask else ()
                if len(edge):
                    who.append(r[:3])
                    answers.append([{"lo": a, "hi": z} for a, z in edge.reshape(-1, 2).tolist()])
            cols = [pa.array(x, t) for x, t in zip(zip(*who, strict=True) if who else ([], [], []), _IDS, strict=True)]
            return pa.RecordBatch.from_arrays([*cols, pa.array(answers, _RUNS)], [*PIECE_ID, "runs"])

        held, size = [], 0
        for b in batches:
            for row in zip(*(column(b, x).to_pylist() for x in (*PIECE_ID, "copy", "n", "piece")), strict=True):
                if held and row[:4] == held[-1][:4]:  # a repeated row was read by several tasks
                    continue
                if size >= CHUNK and row[0] != held[-1][0]:
                    yield out(held)
                    held, size = [], 0
                held.append(row)
                size += len(row[5])
        if held:
            yield out(held)

    hot = one.groupBy("m").agg(F.count("*").alias("pieces")).where(F.col("pieces") > HOT).select("m")
    if hot.isEmpty():
        runs = engine_runs(texts)
    else:
        texts = materialize(texts)
        hot = materialize(hot)
        runs = engine_runs(texts.join(hot, "m", "left_anti")).unionByName(cut_hot(texts.join(hot, "m"), engine_runs, kind, window, gram))
    return shared.join(runs, PIECE_ID).select(*ROW, _moved("runs", F.col("start")))


def _fetched(flat: pa.StructArray, take: list[int], out: list[bytes]) -> pa.RecordBatch:
    at = pa.array(take, pa.int64())
    return pa.RecordBatch.from_arrays([*(flat.field(x).take(at) for x in (*PIECE_ID, "copy", "n")), pa.array(out, pa.binary())], [*PIECE_ID, "copy", "n", "piece"])


def _moved(runs: str, by) -> Column:
    return F.transform(runs, lambda r: F.struct((r["lo"] + by).alias("lo"), (r["hi"] + by).alias("hi"))).alias("runs")


def _joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Lists of runs with runs that touch made one."""
    for b in batches:
        runs = [[{"lo": a, "hi": z} for a, z in merged(sorted((r["lo"], r["hi"]) for r in x))] for x in column(b, "runs").to_pylist()]
        yield pa.RecordBatch.from_arrays([*(column(b, x) for x in PIECE_ID), pa.array(runs, _RUNS)], [*PIECE_ID, "runs"])


def cut_hot(texts: DataFrame, engine_runs: Callable[[DataFrame], DataFrame], kind: str, window: int, gram: int) -> DataFrame:
    """Pieces of hot keys (m, c, e, copy, n, piece) -> (m, c, e, runs) by finer keys.

    A block holds the consecutive windows of a piece whose distance to the key's gram, in units, falls in one range of
    `width`; its key k hashes what all of them share, so equal windows have equal keys at every width. (w, v) is the
    digest of a block's text.
    """

    def blocks(width: int):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            units = Units(kind)
            for b in batches:
                out: list[list[np.ndarray]] = [[] for _ in range(9)]
                for m, c, e, copy, lo, hi, piece in zip(*(column(b, x).to_pylist() for x in (*PIECE_ID, "copy", "lo", "hi", "piece")), strict=True):
                    u, data, at = units.hashes([units.split(piece)])
                    (up1, down1), (up2, down2) = (p.get(len(u) + 1) for p in _POWERS)
                    h1, h2 = _sums(u * up1[: len(u)]), _sums(u * up2[: len(u)])
                    g = _mixed((h1[gram:] - h1[: len(u) - gram + 1]) * down1[: len(u) - gram + 1])
                    place = np.flatnonzero(g.view(np.int64) == m)
                    s = np.arange(lo, hi)
                    first = place[np.searchsorted(place, s)]
                    block = (first - s) // width
                    edge = np.flatnonzero(np.concatenate([[True], (first[1:] != first[:-1]) | (block[1:] != block[:-1])]))
                    a, z = s[edge], np.append(s[edge][1:], hi)
                    # units that every window of the block's range covers, whether or not the piece holds them all
                    left = first[edge] - block[edge] * width
                    right = np.maximum(left - width + 1 + window, left)
                    key = _mixed((h2[np.minimum(right, len(u))] - h2[left]) * down2[left] + block[edge].astype(np.uint64) * np.uint64(MIX)) ^ np.int64(m).view(np.uint64)
                    same = [np.full(len(a), x) for x in (m, c, e, copy)]
                    for held, x in zip(out, (*same, a, z, key.view(np.int64), *units.digests(data, at, a, z - 1 + window)), strict=True):
                        held.append(x)
                cols = [np.concatenate(x) if x else np.empty(0, np.int64) for x in out]
                names = [*PIECE_ID, "copy", "lo", "hi", "k", "w", "v"]
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int32() if c in ("e", "copy", "v") else pa.int64()) for c, x in zip(names, cols, strict=True)], names)

        return run

    found, own = None, [*PIECE_ID, "copy"]
    todo = texts.select(*own, F.lit(0).cast("long").alias("lo"), F.col("n").alias("hi"), "piece")
    for width in (b for b in BLOCKS if b <= max(1, window // 2)):
        cut = materialize(todo.mapInArrow(blocks(width), f"{_IDS_SQL}, copy int, lo long, hi long, k long, w long, v int"))
        at = F.struct(*own, "lo", "hi")
        each = cut.groupBy("k", "w", "v").agg(F.count("*").alias("places"), F.min(at).alias("a"), F.max(at).alias("b"))
        size = each.groupBy("k").agg(F.sum("places").alias("places"), F.count("*").alias("kinds")).where("places > 1").select("k", "kinds")
        held = materialize(each.join(size, "k"))
        few = held.where(F.col("kinds") <= HOT) if width > 1 else held
        pair = F.when(F.col("places") > 1, F.array("a", "b")).otherwise(F.array("a"))
        asked = few.select("k", "w", "v", F.posexplode(pair).alias("number", "at")).select("k", "w", "v", "number", "at.*")
        asked = asked.join(texts.select(*own, "piece"), own)
        asked = asked.select(F.col("k").alias("m"), F.col("w").alias("c"), F.col("v").alias("e"), F.col("number").alias("copy"), (F.col("hi") - F.col("lo")).alias("n"), "lo", "hi", "piece")
        judged = engine_runs(asked.mapInArrow(_narrowed(kind, window), _TEXTS_SQL))
        judged = judged.select(F.col("m").alias("k"), F.col("c").alias("w"), F.col("e").alias("v"), "runs")
        placed = cut.where("copy = 0").join(judged, ["k", "w", "v"]).select(*PIECE_ID, _moved("runs", F.col("lo")))
        found = placed if found is None else found.unionByName(placed)
        if width == 1:
            break
        rest = cut.join(held.where(F.col("kinds") > HOT).select("k").distinct(), "k")
        if rest.isEmpty():
            break
        todo = rest.select(*own, "lo", "hi").join(texts.select(*own, "piece"), own).select(*own, "lo", "hi", "piece")
    whole = found.groupBy(*PIECE_ID).agg(F.flatten(F.collect_list("runs")).alias("runs"))
    return whole.mapInArrow(_joined, f"{_IDS_SQL}, {_RUNS_SQL}")


def _narrowed(kind: str, window: int):
    """Texts of blocks from their pieces' texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        units = Units(kind)
        for b in batches:
            lo, hi = column(b, "lo").to_pylist(), column(b, "hi").to_pylist()
            out = [units.reader(t)(a, z - 1 + window) for a, z, t in zip(lo, hi, raw(b, "piece"), strict=True)]
            yield pa.RecordBatch.from_arrays([*(column(b, c) for c in (*PIECE_ID, "copy", "n")), pa.array(out, pa.binary())], [*PIECE_ID, "copy", "n", "piece"])

    return run


def removed_spans(docs: DataFrame, kind: str, window: int, gram: int, engine: Engine, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text, spans array<struct<lo,hi>>): of every row, the units covered by repeated windows, as ordered runs that may touch."""
    rows = id_text(docs, id_col, text_col).select("doc_id", "text", *row_keys())
    found = repeated_windows(rows.select(*ROW, "text"), kind, window, gram, engine)
    reach = F.transform("runs", lambda r: F.struct(r["lo"].alias("lo"), (r["hi"] - 1 + window).alias("hi")))
    # a set: equal rows bring the same runs any number of times
    spans = found.groupBy(*ROW).agg(F.array_sort(F.flatten(F.collect_set(reach))).alias("spans"))
    return rows.join(spans, ROW, "left").select("doc_id", "text", "spans")


def merged(spans: list[tuple[int, int]] | None) -> list[list[int]]:
    """Ordered spans as maximal runs."""
    out: list[list[int]] = []
    for lo, hi in spans or []:
        if out and lo <= out[-1][1]:
            out[-1][1] = max(out[-1][1], hi)
        else:
            out.append([lo, hi])
    return out


def list_spans(batch: pa.RecordBatch) -> Iterator[list[tuple[int, int]]]:
    """The spans column, row by row."""
    lists = column(batch, "spans")
    ends, flat = lists.offsets.to_pylist(), lists.flatten()
    lo, hi = flat.field("lo").to_pylist(), flat.field("hi").to_pylist()
    null, at0 = lists.is_null().to_pylist(), ends[0]
    for i in range(len(lists)):
        yield [] if null[i] else list(zip(lo[ends[i] - at0 : ends[i + 1] - at0], hi[ends[i] - at0 : ends[i + 1] - at0], strict=True))
