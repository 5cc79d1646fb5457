"""Benchmark decontamination with a distributed positional inverted index.

`build_index` stores the postings of the training texts: the index is partitioned by document into segments of
SEGMENT_BYTES of text, one stored row each, with the segment's terms, how often each stands there and the
ascending positions of each term. It is built once, serves any number of test sets, and no posting is shuffled.
`matches` counts the test terms' postings over all segments, picks for every window its rarest term in the whole
corpus as anchor, and sends anchors and test items to the segments. There the anchor's list, shifted by the
anchor's offset, is intersected with the lists of the window's other terms from the anchor outward; what is left
are exact phrases. Near matches take an item's rarest terms and keep places where all of them lie within `slop`
words. Test sets larger than BLOCK_TERMS tokens run block by block, of which the driver holds one at a time.

Defined cases: null texts have no words; items without words match nothing; an item shorter than the
window is one window; repeated items each count; an item with a null item_id hits and counts, but is in no list
of ids; repeated rows get the same answer; empty tables give no hits. Long texts are numbered in blocks.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecgraph.session import materialize, ship

from .common import ROW, column, id_text, raw, row_keys, slices, small

#: Tokens of test items held by each task at once.
BLOCK_TERMS = 2_000_000
#: Words are maximal runs of ASCII letters, digits and everything outside ASCII, A-Z lower-cased.
_KEEP = bytes(c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else c + 32 if 65 <= c <= 90 else 32 for c in range(256))
#: Text of one segment (or one document), and text that is split at once.
SEGMENT_BYTES, SPLIT_BYTES = 4 << 20, 4 << 20
#: How many of an item's rarest terms have to stand together for a near match.
RAREST = 3


def words(text: bytes) -> list[bytes]:
    return text.translate(_KEEP).split()


@dataclass
class TestSet:
    """Test items as term numbers, with their place in one long array."""

    ids: list[str]
    terms: dict[bytes, int]
    tokens: np.ndarray
    start: np.ndarray  # one more than items
    window: int

    @classmethod
    def of(cls, items: list[tuple[str, bytes]], window: int) -> TestSet:
        terms: dict[bytes, int] = {}
        ids, tokens, start = [], [], [0]
        for name, text in items:
            w = words(text)
            if w:
                ids.append(name)
                tokens += [terms.setdefault(x, len(terms)) for x in w]
                start.append(len(tokens))
        return cls(ids, terms, np.array(tokens, np.int64), np.array(start, np.int64), window)


class _Numbers(dict):
    """Numbers of terms in order of appearance."""

    def __missing__(self, key: bytes) -> int:
        n = self[key] = len(self)
        return n


def _numbered(text: bytes | None, numbers: _Numbers) -> np.ndarray:
    text, parts, lo = (text or b"").translate(_KEEP), [], 0
    while lo < len(text):
        hi = text.find(b" ", lo + SPLIT_BYTES)
        w = text[lo : hi if hi >= 0 else len(text)].split()
        parts.append(np.fromiter(map(numbers.__getitem__, w), np.int32, len(w)))
        lo = hi if hi >= 0 else len(text)
    return np.concatenate(parts) if parts else np.empty(0, np.int32)


#: One segment: its documents (with the position of their first word) and its posting lists, one after the other.
INDEX = "doc_id array<long>, row array<long>, row2 array<long>, n_words array<int>, begin array<int>, terms array<binary>, counts array<int>, positions array<int>"


def segment(texts: list[bytes | None]) -> tuple[np.ndarray, np.ndarray, list[bytes], np.ndarray, np.ndarray]:
    """(n_words, begin, terms, counts, positions); between two documents one position stays free, so no phrase crosses."""
    numbers = _Numbers()
    tokens = [_numbered(t, numbers) for t in texts]
    n = np.fromiter(map(len, tokens), np.int32, len(tokens))
    begin = (np.cumsum(n + 1) - (n + 1)).astype(np.int32)
    flat = np.concatenate(tokens) if tokens else np.empty(0, np.int32)
    order = np.argsort(flat, kind="stable")
    place = (np.repeat(begin, n) + _ramp(n)).astype(np.int32)
    return n, begin, list(numbers), np.bincount(flat, minlength=len(numbers)).astype(np.int32), place[order]


def build_index(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The stored index of all words of all texts, one row per segment."""
    ship(docs.sparkSession)
    names = [c.split(" ")[0] for c in INDEX.split(", ")]
    kinds = [pa.int64()] * 3 + [pa.int32()] * 2 + [pa.binary()] + [pa.int32()] * 2

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches, "text", SEGMENT_BYTES):
            if b.num_rows:
                cols = [*(column(b, c).to_pylist() for c in ("doc_id", *ROW)), *segment(raw(b))]
                yield pa.RecordBatch.from_arrays([pa.array([c], pa.list_(t)) for c, t in zip(cols, kinds, strict=True)], names)

    rows = id_text(docs, id_col, text_col)
    return materialize(rows.select("doc_id", *row_keys(), "text").mapInArrow(run, INDEX), SEGMENT_BYTES)


def anchors(test: TestSet, rarity: np.ndarray) -> np.ndarray:
    """Places in the test set so that each window holds one: its rarest term. Windows with a term that stands nowhere need none."""
    n = len(test.tokens)
    if not n:
        return np.empty(0, np.int64)
    df = rarity[test.tokens]
    size = np.diff(test.start)
    item = np.repeat(np.arange(len(size)), size)
    off = np.arange(n) - test.start[item]
    width = np.minimum(size[item], test.window)
    starts = np.flatnonzero(off <= size[item] - width)
    best, rare = starts.copy(), df[starts].copy()
    for j in range(1, test.window):
        ok = j < width[starts]
        at = np.where(ok, starts + j, starts)
        less = df[at] < rare
        best[less], rare[less] = at[less], df[at][less]
    return np.unique(best[rare > 0])


class Segment:
    """The posting lists of the test terms in one segment, as sorted (term, position) keys."""

    def __init__(self, test: TestSet, rarity: np.ndarray, anchor: np.ndarray, begin: np.ndarray, length: int, terms: list[bytes], counts: np.ndarray, positions: np.ndarray) -> None:
        self.test, self.rarity, self.anchor, self.begin, self.length = test, rarity, anchor, begin, length
        get = test.terms.get
        number = np.fromiter((get(t, -1) for t in terms), np.int64, len(terms))
        at = np.cumsum(counts, dtype=np.int64) - counts
        known = np.flatnonzero(number >= 0)
        known = known[np.argsort(number[known], kind="stable")]
        n = counts[known].astype(np.int64)
        self.postings = np.repeat(number[known], n) * length + positions[np.repeat(at[known], n) + _ramp(n)]
        self.df = np.zeros(len(test.terms), np.int64)
        self.df[number[known]] = n
        self.first = np.concatenate([[0], np.cumsum(self.df)])

    def has(self, term: np.ndarray, pos: np.ndarray) -> np.ndarray:
        """Whether the term's list holds the position: a step of the offset-adjusted intersection."""
        ok = (pos >= 0) & (pos < self.length)
        key = term * self.length + pos
        at = np.searchsorted(self.postings, key)
        at[at == len(self.postings)] = 0
        return ok & (self.postings[at] == key) if len(self.postings) else np.zeros(len(pos), bool)

    def phrases(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(item, first position, end position) of every maximal run of test words holding a window."""
        t = self.test
        anchor = self.anchor
        lists = self.df[t.tokens[anchor]] if len(anchor) else np.empty(0, np.int64)
        found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        size = np.diff(t.start)
        for lo, hi in slices(lists, 4_000_000):
            a, n = anchor[lo:hi], lists[lo:hi]
            place = np.repeat(a, n)
            pos = self.postings[np.repeat(self.first[t.tokens[a]], n) + _ramp(n)] % self.length
            item = np.searchsorted(t.start, place, "right") - 1
            left, right = place - t.start[item], t.start[item + 1] - 1 - place
            need = np.minimum(size[item], t.window)
            # the nearest neighbour kills most candidates: one of both must match unless the window is one word
            near = np.where(need <= 1, True, False)
            near |= (left > 0) & self.has(t.tokens[np.maximum(place - 1, 0)], pos - 1)
            more = ~near & (right > 0)
            near[more] = self.has(t.tokens[place[more] + 1], pos[more] + 1)
            place, pos, item, left, right, need = (x[near] for x in (place, pos, item, left, right, need))
            run = []
            for sign, room in ((-1, left), (1, right)):
                reach = np.zeros(len(place), np.int64)
                alive = np.arange(len(place))
                for j in range(1, t.window):
                    alive = alive[room[alive] >= j]
                    alive = alive[self.has(t.tokens[place[alive] + sign * j], pos[alive] + sign * j)]
                    if not len(alive):
                        break
                    reach[alive] = j
                run.append(reach)
            whole = run[0] + run[1] + 1 >= need
            found.append((item[whole], (pos - run[0])[whole], (pos + run[1] + 1)[whole]))
        return tuple(np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.empty(0, np.int64),) * 3

    def near(self, slop: int, rarest: int = RAREST) -> tuple[np.ndarray, np.ndarray]:
        """(item, document) where the item's rarest different terms lie within slop words of the rarest one."""
        t, out = self.test, []
        for i in range(len(t.ids)):
            terms = np.unique(t.tokens[t.start[i] : t.start[i + 1]])
            terms = terms[np.argsort(self.rarity[terms], kind="stable")][:rarest]
            if not len(terms) or (self.df[terms] == 0).any():
                continue
            pos = self.postings[self.first[terms[0]] : self.first[terms[0] + 1]] % self.length
            doc = np.searchsorted(self.begin, pos, "right") - 1
            for term in terms[1:]:
                own = self.postings[self.first[term] : self.first[term + 1]] % self.length
                at = np.searchsorted(own, pos)
                ok = np.zeros(len(pos), bool)
                for side in (np.minimum(at, len(own) - 1), np.maximum(at - 1, 0)):
                    ok |= (np.abs(own[side] - pos) <= slop) & (np.searchsorted(self.begin, own[side], "right") - 1 == doc)
                pos, doc = pos[ok], doc[ok]
            out.append((np.full(len(doc), i), doc))
        return tuple(np.concatenate(x) for x in zip(*out, strict=True)) if out else (np.empty(0, np.int64),) * 2


def _ramp(n: np.ndarray) -> np.ndarray:
    return np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)


def _merged(spans: list[dict]) -> list[dict]:
    out: list[dict] = []
    for s in sorted(spans, key=lambda s: (s["start"], s["end"])):
        if out and s["start"] <= out[-1]["end"]:
            out[-1]["end"] = max(out[-1]["end"], s["end"])
        else:
            out.append(dict(s))
    return out


def test_blocks(items: DataFrame, window: int, id_col: str = "item_id", text_col: str = "text") -> Iterator[TestSet]:
    """The stated test set in blocks of bounded size, read one after the other."""
    held, size = [], 0
    for name, text in items.select(F.col(id_col).cast("string"), F.col(text_col).cast("string")).toLocalIterator():
        data = (text or "").encode()
        held.append((name, data))
        size += len(data) // 4 + 1
        if size >= BLOCK_TERMS:
            yield TestSet.of(held, window)
            held, size = [], 0
    yield TestSet.of(held, window)


_FOUND = "hits array<struct<start:long,end:long>>, items array<string>, near array<string>"
_KINDS = (pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])), pa.list_(pa.string()), pa.list_(pa.string()))


def _values(batch: pa.RecordBatch, name: str) -> Iterator[pa.Array]:
    """A list column's values, row by row."""
    lists = column(batch, name)
    ends = lists.offsets.to_numpy()
    for lo, hi in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
        yield lists.values.slice(lo, hi - lo)


def matches(index: DataFrame, items: DataFrame, window: int = 10, slop: int | None = None) -> DataFrame:
    """(row, row2, hits array<struct<start,end>>, items array<string>, near array<string>) of every different row with any match."""
    spark = index.sparkSession
    ship(spark)
    found = None

    def rarity_of(test: TestSet) -> np.ndarray:
        """How often each test term stands in the corpus; as many numbers as the block has terms."""
        known = spark.sparkContext.broadcast(test.terms)

        def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            get, total = known.value.get, np.zeros(len(known.value), np.int64)
            for b in batches:
                for terms, counts in zip(_values(b, "terms"), _values(b, "counts"), strict=True):
                    number = np.fromiter((get(t, -1) for t in terms.to_pylist()), np.int64, len(terms))
                    total[number[number >= 0]] += counts.to_numpy()[number >= 0]
            at = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["term", "n"])

        out = np.zeros(len(test.terms), np.int64)
        for r in index.select("terms", "counts").mapInArrow(count, "term long, n long").groupBy("term").agg(F.sum("n").alias("n")).collect():
            out[r.term] = r.n
        return out

    def search_of(test: TestSet, rarity: np.ndarray):
        known = spark.sparkContext.broadcast((test, rarity, anchors(test, rarity)))

        def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            test, rarity, anchor = known.value
            for b in batches:
                parts = [_values(b, c) for c in (*ROW, "n_words", "begin", "terms", "counts", "positions")]
                for row, row2, n_words, begin, terms, counts, positions in zip(*parts, strict=True):
                    first = begin.to_numpy().astype(np.int64)
                    seg = Segment(test, rarity, anchor, first, int(first[-1] + n_words[-1].as_py() + 1), terms.to_pylist(), counts.to_numpy(), positions.to_numpy())
                    spans, named, close = ({} for _ in range(3))
                    item, lo, hi = seg.phrases()
                    doc = np.searchsorted(first, lo, "right") - 1
                    for d, s, e in zip(doc.tolist(), (lo - first[doc]).tolist(), (hi - first[doc]).tolist(), strict=True):
                        spans.setdefault(d, []).append({"start": s, "end": e})
                    for d, i in np.unique(np.stack([doc, item], 1), axis=0).tolist() if len(doc) else []:
                        named.setdefault(d, []).append(test.ids[i])
                    if slop is not None:
                        for i, d in np.unique(np.stack(seg.near(slop), 1), axis=0).tolist():
                            close.setdefault(d, []).append(test.ids[i])
                    at = sorted({*spans, *close})
                    keys = [k.take(pa.array(at, pa.int64())) for k in (row, row2)]
                    lists = [pa.array([v.get(d, []) for d in at], t) for v, t in zip(({d: _merged(x) for d, x in spans.items()}, named, close), _KINDS, strict=True)]
                    yield pa.RecordBatch.from_arrays([*keys, *lists], [*ROW, "hits", "items", "near"])

        return search

    for block, test in enumerate(test_blocks(items, window)):
        scan = search_of(test, rarity_of(test))
        part = materialize(index.select(*ROW, "n_words", "begin", "terms", "counts", "positions").mapInArrow(scan, f"row long, row2 long, {_FOUND}").withColumn("block", F.lit(block)))
        found = part if found is None else found.unionByName(part)
    # a set: equal rows bring the same answer any number of times
    each = found.groupBy(*ROW).agg(F.collect_set(F.struct("block", "hits", "items", "near")).alias("all"))
    return each.select(*ROW, *(F.flatten(F.transform("all", lambda x: x[c])).alias(c) for c in ("hits", "items", "near"))).mapInArrow(_joined, f"row long, row2 long, {_FOUND}")


def _joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Hits of several blocks as maximal spans."""
    for b in batches:
        hits = pa.array([_merged(x) for x in column(b, "hits").to_pylist()], _KINDS[0])
        yield pa.RecordBatch.from_arrays([*(column(b, c) for c in ROW), hits, column(b, "items"), column(b, "near")], [*ROW, "hits", "items", "near"])


def contamination(docs: DataFrame, items: DataFrame, window: int = 10, slop: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_words, hits array<struct<start,end>>, items array<string>, near array<string>): hit words as maximal spans."""
    index = build_index(docs, id_col, text_col)
    found = matches(index, items, window, slop)
    each = index.select(F.explode(F.arrays_zip("doc_id", *ROW, "n_words")).alias("d")).select("d.doc_id", *(f"d.{c}" for c in ROW), F.col("d.n_words").cast("long").alias("n_words"))
    empty = lambda c, kind: F.coalesce(c, F.array().cast(kind)).alias(c)
    lists = [empty(c, k) for c, k in (("hits", "array<struct<start:long,end:long>>"), ("items", "array<string>"), ("near", "array<string>"))]
    return each.join(found, ROW, "left").select("doc_id", "n_words", *lists)


def contamination_digest(docs: DataFrame, items: DataFrame, window: int = 10) -> DataFrame:
    """The contract's columns from the operator's spans and items."""
    found = contamination(docs, items, window)
    n_hit = F.aggregate("hits", F.lit(0).cast("long"), lambda a, x: a + x["end"] - x["start"])
    ids = F.array_join(F.array_sort("items"), ",")
    return found.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(ids, 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"))
