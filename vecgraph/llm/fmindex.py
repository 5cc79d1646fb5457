"""Substring dedup by words with a compressed FM-index per shard.

The texts of a shard (windows.py) are numbered word by word and indexed: suffixes are sorted, the words
before them (the Burrows-Wheeler transform) go into a wavelet matrix whose bit levels have rank counts in
blocks. Documents' pieces are streamed against it: backward search from many places at once, one word at a
time after a table of short strings, while the words read still occur at two places or more. That length is the
place's matching statistic; places where it reaches the window are repeats, and so are the windows inside a longer match.
Suffixes are sorted to one word more than the longest string searched, which is all that its counts need.

Defined cases: a null text has no words; texts shorter than the window keep every word; repeated rows
remove each other's words; matches never cross documents. Kept words are joined by one space.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import column, raw
from .windows import LONG, _ramp, list_spans, merged, removed_spans, word_bounds

#: Words whose hash is the key of a window.
GRAM = 15


class Wavelet:
    """Ranks of numbers in a sequence: bits from the highest level down, zeros first on the next level."""

    def __init__(self, seq: np.ndarray, top: int) -> None:
        self.bits = max(1, int(top).bit_length())
        self.words: list[np.ndarray] = []
        self.sums: list[np.ndarray] = []
        self.zeros: list[int] = []
        self.origin: np.ndarray | None = None
        for level in range(self.bits - 1, -1, -1):
            bit = (seq >> level) & 1
            pad = np.concatenate([bit.astype(np.uint8), np.zeros(64 - len(bit) % 64, np.uint8)])
            words = np.packbits(pad, bitorder="little").view(np.uint64)
            self.words.append(words)
            self.sums.append(np.concatenate([[0], np.cumsum(np.bitwise_count(words), dtype=np.int64)]))
            self.zeros.append(int(len(bit) - bit.sum()))
            seq = np.concatenate([seq[bit == 0], seq[bit == 1]])

    def ones(self, level: int, i: np.ndarray) -> np.ndarray:
        word = i >> 6
        low = (np.uint64(1) << (i & 63).astype(np.uint64)) - np.uint64(1)
        return self.sums[level][word] + np.bitwise_count(self.words[level][word] & low)

    def follow(self, x: np.ndarray, i: np.ndarray) -> np.ndarray:
        """Where place i of the sequence is led to by the bits of x."""
        for level in range(self.bits):
            bit = (x >> (self.bits - 1 - level)) & 1 == 1
            one = self.ones(level, i)
            i = np.where(bit, self.zeros[level] + one, i - one)
        return i

    def rank(self, x: np.ndarray, i: np.ndarray) -> np.ndarray:
        """How often each x stands before place i. Where a number's place 0 leads is the same for all its ranks and kept."""
        if self.origin is None:
            every = np.arange(1 << self.bits)
            self.origin = self.follow(every, np.zeros(len(every), np.int64))
        return self.follow(x, i) - self.origin[x]


class FMIndex:
    """Counts of strings by backward search. Strings of 1, 2, 4, ... words that stand at a place of the indexed sequence have
    their intervals in tables (a by-product of sorting), where a search begins."""

    def __init__(self, seq: np.ndarray, depth: int, longest: int = 64) -> None:
        """seq: numbers from 1; 0 ends each text."""
        self.seq = seq
        order, self.seeds = sorted_suffixes(seq, depth, longest)
        before = seq[order - 1]  # the last text's end precedes the first
        self.tree = Wavelet(before, int(seq.max(initial=1)))
        self.first = np.searchsorted(np.sort(seq), np.arange(int(seq.max(initial=1)) + 2))
        self.n = len(seq)

    def matching(self, ends: np.ndarray, most: np.ndarray | int, least: int = 2) -> np.ndarray:
        """For each end in the sequence: the longest string of up to `most` words ending there that occurs at `least` places."""
        most = np.broadcast_to(most, len(ends))
        length, lo, hi = (np.zeros(len(ends), np.int64) for _ in range(3))
        for size, start, end in self.seeds:
            fits = np.flatnonzero(most >= size)
            at = ends[fits] - size + 1
            # a longer string occurs no more often than the shorter one that ends it
            often = (end[at] - start[at] >= least) & (self.seq[ends[fits]] > 0)
            fits, at = fits[often], at[often]
            length[fits], lo[fits], hi[fits] = size, start[at], end[at]
        alive = np.flatnonzero((length > 0) & (length < most))
        lo, hi = lo[alive], hi[alive]
        while len(alive):
            x = self.seq[ends[alive] - length[alive]]
            both = self.tree.rank(np.concatenate([x, x]), np.concatenate([lo, hi]))
            lo, hi = self.first[x] + both[: len(x)], self.first[x] + both[len(x) :]
            keep = (hi - lo >= least) & (x > 0)
            alive, lo, hi = alive[keep], lo[keep], hi[keep]
            length[alive] += 1
            on = length[alive] < most[alive]
            alive, lo, hi = alive[on], lo[on], hi[on]
        return length


def sorted_suffixes(seq: np.ndarray, depth: int, longest: int = 0) -> tuple[np.ndarray, list[tuple[int, np.ndarray, np.ndarray]]]:
    """Places in order of the `depth` or more numbers from there on (then by place), by doubling; and for 1, 2, 4, ... up to
    `longest` numbers the interval of that order which the string at each place has."""
    n = len(seq)
    rank = seq.astype(np.int64)
    order = np.argsort(rank, kind="stable")
    known, seeds = 1, []
    while True:
        sorted_ = rank[order]
        new = np.concatenate([[True], sorted_[1:] != sorted_[:-1]])[:n]
        head = np.flatnonzero(new)
        start, end = np.empty(n, np.int64), np.empty(n, np.int64)
        size = np.diff(np.append(head, n))
        start[order], end[order] = np.repeat(head, size), np.repeat(head + size, size)
        if known <= longest:
            seeds.append((known, start, end))
        if known >= depth or len(head) == n:
            return order, seeds
        rank = start * (n + 1)
        rank[: n - known] += start[known:] + 1
        order = np.argsort(rank, kind="stable")
        known *= 2


class _Numbers(dict):
    """Numbers of words in order of appearance."""

    def __missing__(self, word: bytes) -> int:
        n = self[word] = len(self)
        return n


def repeats(texts: list[bytes], n: np.ndarray, judged: np.ndarray, window: int) -> list[np.ndarray]:
    """For each judged text, which of its first n words begin a window that starts elsewhere too."""
    numbers = _Numbers({None: 0})
    flat: list[bytes | None] = []
    begin = []
    for t in texts:
        begin.append(len(flat))
        flat += t.split()
        flat.append(None)
    seq = np.fromiter(map(numbers.__getitem__, flat), np.int64, len(flat))
    index = FMIndex(seq, int(n.max(initial=1)) + window)
    begin, first = np.array(begin, np.int64), np.cumsum(n) - n
    twice = np.zeros(int(n.sum()), bool)
    # windows lo to hi (exclusive) are open: by turns a text is searched from the last one's end, where a match of more
    # words than the window settles those before as well, and from the first one's, where a match of fewer tells that
    # no window that holds it and the word before repeats
    lo, hi = np.zeros(len(n), np.int64), np.where(judged, n, 0)
    todo = np.flatnonzero(hi > 0)
    from_end = True
    while len(todo):
        at = hi[todo] - 1 if from_end else lo[todo]
        got = index.matching(begin[todo] + at + window - 1, at + window if from_end else window)
        hit = got >= window
        if from_end:
            done = np.minimum(np.where(hit, got - window + 1, 0), hi[todo] - lo[todo])
            place = np.repeat(first[todo] + at, done) - _ramp(done)
            twice[place] = True
            hi[todo] -= np.maximum(done, 1)
        else:
            twice[first[todo[hit]] + at[hit]] = True
            lo[todo] += np.where(hit, 1, window - got)
        todo = todo[lo[todo] < hi[todo]]
        from_end = not from_end
    return np.split(twice, np.cumsum(n)[:-1])


def word_spans(docs: DataFrame, window: int = 35, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text, spans): words covered by windows whose words also start anywhere else."""
    return removed_spans(docs, "words", window, min(GRAM, window), repeats, id_col, text_col)


def kept_words(text: bytes, runs: list[list[int]]) -> tuple[int, int, str]:
    """(words, words within the runs, digest of the others joined by one space), in bounded memory for long texts."""
    gone = sum(z - a for a, z in runs)
    if len(text) < LONG:
        words = text.split()
        cuts = [0, *(x for r in runs for x in r), len(words)]
        kept = [w for a, z in zip(cuts[::2], cuts[1::2], strict=True) for w in words[a:z]]
        return len(words), gone, hashlib.sha256(b" ".join(kept)).hexdigest()
    first, last = word_bounds(text)
    cuts = [0, *(x for r in runs for x in r), len(first)]
    found, gap = hashlib.sha256(), b""
    for a, z in zip(cuts[::2], cuts[1::2], strict=True):
        for lo in range(a, z, LONG):
            hi = min(lo + LONG, z)
            found.update(gap + b" ".join(text[first[lo] : last[hi - 1]].split()))
            gap = b" "
    return len(first), gone, found.hexdigest()


def kept_digest(docs: DataFrame, window: int = 35) -> DataFrame:
    """The contract's columns from the operator's spans."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for doc, text, spans in zip(column(b, "doc_id").to_pylist(), raw(b), list_spans(b), strict=True):
                rows.append((doc, *kept_words(text or b"", merged(spans))))
            cols = list(zip(*rows, strict=True)) or [[]] * 4
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, [pa.int64()] * 3 + [pa.string()], strict=True)], ["doc_id", "n_words", "n_removed", "kept_sha256"])

    return word_spans(docs, window).mapInArrow(run, "doc_id long, n_words long, n_removed long, kept_sha256 string")
