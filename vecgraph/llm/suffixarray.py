"""Exact substring dedup by bytes with suffix arrays, sorted in two stages.

Of a shard's suffixes only those smaller than their successor are sorted directly; every other suffix is
its first byte before a suffix that is smaller than itself, so one scan over the buckets of first bytes, in
ascending order, puts it in its place. Neighbours in the finished array with a common prefix of `window`
bytes are repeats. Suffixes are ordered by `window` bytes: what follows doesn't matter. Which texts a shard
holds, and why no repeat is lost, is told in windows.py. Only starts of whole windows are in the array, and
after each text's last of them the few suffixes up to the next directly sorted one.

Defined cases: a null text counts as empty; texts shorter than the window keep every byte; repeated rows
remove each other's bytes; matches never cross documents; bytes may be cut within a character.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import column, raw
from .windows import _ramp, list_spans, merged, removed_spans

#: Bytes whose hash is the key of a window (windows.py): texts that share fewer never meet.
GRAM = 256


def ascending(data: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Whether each suffix (to the end of its text) is smaller than its successor."""
    n = len(data)
    after = np.append(data[1:], 0).astype(np.int16)
    after[end - 1] = -1  # the empty suffix is the smallest
    differs = data != after
    at = np.where(differs, np.arange(n), n)
    following = np.minimum.accumulate(at[::-1])[::-1]
    return data[following] < after[following]


def suffix_order(data: bytes, end: np.ndarray, wanted: np.ndarray, depth: int) -> np.ndarray:
    """The wanted suffixes of some texts in a row (ends given), in order of their first `depth` bytes."""
    text = np.frombuffer(data, np.uint8)
    direct = ascending(text, end)
    owner_end = end[np.searchsorted(end, np.arange(len(text)), "right")]
    # from each start without its successor on, go to the first directly sorted suffix or the text's end
    held = wanted.copy()
    stop = np.where(direct, np.arange(len(text)), len(text))
    stop = np.minimum(np.minimum.accumulate(stop[::-1])[::-1], owner_end - 1)
    tail = np.flatnonzero(wanted & ~np.append(wanted[1:], False))
    size = stop[tail] - tail + 1
    held[np.repeat(tail, size) + np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)] = True

    first = np.flatnonzero(held & direct)
    keys = [data[i : min(i + depth, e)] for i, e in zip(first.tolist(), owner_end[first].tolist(), strict=True)]
    first = first[np.array(sorted(range(len(first)), key=keys.__getitem__), np.int64)] if len(first) else first
    by_byte = np.searchsorted(text[first], np.arange(257)) if len(first) else np.zeros(257, np.int64)

    given: list[list[np.ndarray]] = [[] for _ in range(256)]

    def induce(scanned: np.ndarray, least: int) -> np.ndarray:
        """Give the suffixes before these to the buckets of their bytes; those of bucket `least` are returned."""
        before = scanned - 1
        ok = before >= 0
        before = before[ok]
        keep = held[before] & ~direct[before] & (owner_end[before] > scanned[ok])
        before = before[keep]
        byte = text[before]
        own = before[byte == least]
        if len(rest := before[byte != least]):
            byte = text[rest]
            order = np.argsort(byte, kind="stable")
            rest, byte = rest[order], byte[order]
            cut = np.flatnonzero(np.diff(byte)) + 1
            for part in np.split(rest, cut):
                given[text[part[0]]].append(part)
        return own

    lasts = end[(end > 0)] - 1
    lasts = lasts[held[lasts] & ~direct[lasts]]  # suffixes of one byte stand first in their buckets
    for b in np.unique(text[lasts]):
        given[b].append(lasts[text[lasts] == b])
    out = []
    for byte in range(256):
        wave = np.concatenate(given[byte]) if given[byte] else np.empty(0, np.int64)
        while len(wave):  # runs of one byte: the bucket grows while it is scanned
            out.append(wave)
            wave = induce(wave, byte)
        if len(direct_part := first[by_byte[byte] : by_byte[byte + 1]]):
            out.append(direct_part)
            induce(direct_part, -1)
    order = np.concatenate(out) if out else np.empty(0, np.int64)
    return order[wanted[order]]


def repeats(texts: list[bytes], n: np.ndarray, judged: np.ndarray, window: int) -> list[np.ndarray]:
    """For each text, which of its first n starts begin a window that starts elsewhere too."""
    data = b"".join(texts)
    end = np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)))
    begin = end - np.fromiter(map(len, texts), np.int64, len(texts))
    wanted = np.zeros(len(data), bool)
    wanted[np.repeat(begin, n) + _ramp(n)] = True
    order = suffix_order(data, end, wanted, window).tolist()
    twice = np.zeros(len(data), bool)
    before, last = None, -1
    for i in order:  # adjacent common prefixes, as far as the window
        now = data[i : i + window]
        if now == before:
            twice[i] = twice[last] = True
        before, last = now, i
    return [twice[b : b + k] for b, k in zip(begin.tolist(), n.tolist(), strict=True)]


def substring_spans(docs: DataFrame, window: int = 400, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text, spans): bytes covered by strings of `window` bytes that also start anywhere else."""
    return removed_spans(docs, "bytes", window, min(GRAM, window), repeats, id_col, text_col)


def kept_digest(docs: DataFrame, window: int = 400) -> DataFrame:
    """The contract's columns from the operator's spans."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for doc, text, spans in zip(column(b, "doc_id").to_pylist(), raw(b), list_spans(b), strict=True):
                text, runs = text or b"", merged(spans)
                cuts = [0, *(x for r in runs for x in r), len(text)]
                kept = b"".join(text[a:z] for a, z in zip(cuts[::2], cuts[1::2], strict=True))
                rows.append((doc, len(text), len(text) - len(kept), len(runs), hashlib.sha256(kept).hexdigest()))
            cols = list(zip(*rows, strict=True)) or [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, [pa.int64()] * 4 + [pa.string()], strict=True)], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    return substring_spans(docs, window).mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
