"""BPE encoding and decoding with a contiguous rank array.

A short word is an array of parts and, beside it, an array of the ranks of adjacent pairs. The smallest
rank is found by a scan, its pair becomes one part, one boundary goes and the two neighbouring ranks are
looked up anew. Words longer than SHORT parts use a heap of pairs over a linked list instead, with the
same order (smallest rank, then leftmost). Word results are kept in a bounded table in each worker.

The vocabulary's file (some megabytes, whatever the corpus) is read on the driver and broadcast, so workers need no
copy of it. It is that of a public tokenizer: NFC, white space as separator, lower case, words by
pattern, byte letters, word-end suffix. Decoding joins the tokens of the ids by spaces, as that file's
library does where the file names no decoder.

Defined cases: a null text counts as empty: no ids, empty decoded text. Special tokens' strings in a text
become their ids. Repeated rows stay; empty tables give empty results.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import struct
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from vecgraph.session import ship

from .common import column, id_text, kept, small, strings

#: Parts up to which a scan of the rank array is used.
SHORT = 256
#: Entries of a worker's tables (of chunks, of words) before their older half goes.
TABLE, WORDS = 100_000, 300_000
NONE = 1 << 40


class Recent:
    """A table of bounded size: entries not asked for while `size` others came go."""

    def __init__(self, size: int) -> None:
        self.size, self.new, self.old = size, {}, {}

    def get(self, key: str):
        if (x := self.new.get(key)) is None and (x := self.old.get(key)) is not None:
            self.put(key, x)
        return x

    def put(self, key: str, value) -> None:
        if len(self.new) >= self.size:
            self.new, self.old = {}, self.new
        self.new[key] = value


class Vocabulary:
    def __init__(self, content: bytes) -> None:
        spec = json.loads(content)
        model = spec["model"]
        self.ids: dict[str, int] = model["vocab"]
        self.suffix = model["end_of_word_suffix"] or ""
        self.pairs: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, pair in enumerate(model["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            self.pairs.setdefault((self.ids[a], self.ids[b]), (rank, self.ids[a + b]))
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.text = {i: t for t, i in {**self.ids, **self.special}.items()}
        split = next(p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")["pattern"]["Regex"]
        self.word = regex.compile(split.replace(r"\s", r"\p{White_Space}"))
        self.space = regex.compile(r"\p{White_Space}+")
        self.cut = regex.compile("|".join(regex.escape(s) for s in sorted(self.special, key=len, reverse=True)))
        # byte letters: printable Latin-1 stands for itself, the rest for U+0100 onward in order
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        rest = iter(range(256, 512))
        self.letter = [chr(b) if b in plain else chr(next(rest)) for b in range(256)]
        self.table, self.words = Recent(TABLE // 2), Recent(WORDS // 2)

    def parts(self, word: str) -> list[int]:
        letters = [self.letter[b] for b in word.encode()]
        letters[-1] += self.suffix
        return [self.ids[x] for x in letters]

    def merge(self, parts: list[int]) -> list[int]:
        if len(parts) > SHORT:
            return self.merge_long(parts)
        pairs, none = self.pairs, (NONE, 0)
        ranks = [pairs.get(p, none)[0] for p in zip(parts, parts[1:], strict=False)]
        while ranks:
            low = min(ranks)
            if low == NONE:
                break
            i = ranks.index(low)
            parts[i] = pairs[parts[i], parts[i + 1]][1]
            del parts[i + 1], ranks[i]
            if i < len(ranks):
                ranks[i] = pairs.get((parts[i], parts[i + 1]), none)[0]
            if i:
                ranks[i - 1] = pairs.get((parts[i - 1], parts[i]), none)[0]
        return parts

    def merge_long(self, parts: list[int]) -> list[int]:
        n, pairs = len(parts), self.pairs
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        alive = [True] * n
        heap = [(pairs[p][0], i, p) for i, p in enumerate(zip(parts, parts[1:], strict=False)) if p in pairs]
        heapq.heapify(heap)
        while heap:
            _, i, pair = heapq.heappop(heap)
            j = after[i]
            if not alive[i] or j >= n or (parts[i], parts[j]) != pair:
                continue
            parts[i] = pairs[pair][1]
            alive[j] = False
            after[i] = k = after[j]
            if k < n:
                before[k] = i
                if (p := (parts[i], parts[k])) in pairs:
                    heapq.heappush(heap, (pairs[p][0], i, p))
            if (h := before[i]) >= 0 and (p := (parts[h], parts[i])) in pairs:
                heapq.heappush(heap, (pairs[p][0], h, p))
        return [x for x, a in zip(parts, alive, strict=True) if a]

    def one(self, word: str) -> tuple[bytes, str]:
        if (known := self.words.get(word)) is None:
            ids = self.merge(self.parts(word))
            known = struct.pack(f"<{len(ids)}I", *ids), " ".join(map(self.text.__getitem__, ids))
            if len(word) <= 40:
                self.words.put(word, known)
        return known

    def chunk(self, text: str) -> tuple[bytes, str]:
        """Ids (as unsigned 32-bit little-endian) and token texts of a piece without white space."""
        if (known := self.table.get(text)) is not None:
            return known
        plain = (text if text.isascii() else unicodedata.normalize("NFC", text).replace("Σ", "σ")).lower()
        if plain.isascii() and plain.isalpha():
            out = self.one(plain)
        else:
            found = [self.one(word) for word in self.word.findall(plain)]
            out = b"".join([f[0] for f in found]), " ".join([f[1] for f in found])
        if len(text) <= 64:
            self.table.put(text, out)
        return out

    def chunks(self, text: str) -> list[str]:
        """Pieces between white space. split() also parts at four control characters that are no white space here."""
        if any(c in text for c in "\x1c\x1d\x1e\x1f"):
            return [c for c in self.space.split(text) if c]
        return text.split()

    def encode(self, text: str) -> tuple[bytes, str]:
        """Ids and the decoded text."""
        if "<|" in text and self.cut.search(text):
            found, at = [], 0
            for m in self.cut.finditer(text):
                found += [self.encode(text[at : m.start()]), (np.array([self.special[m[0]]], "<u4").tobytes(), m[0])]
                at = m.end()
            found = [f for f in [*found, self.encode(text[at:])] if f[0]]
        else:
            known = self.table.new.get
            found = [known(c) or self.chunk(c) for c in self.chunks(text)]
        return b"".join([f[0] for f in found]), " ".join([f[1] for f in found if f[0]])

    def decode(self, ids: list[int]) -> str:
        return " ".join(self.text[i] for i in ids if i in self.text)


def vocabulary(content: bytes) -> Vocabulary:
    return kept("bpe", content, lambda: Vocabulary(content))


def content_of(path: str) -> bytes:
    with open(path, "rb") as f:
        return f.read()


def _map(docs: DataFrame, vocab_path: str, schema: str, row, id_col: str, text_col: str) -> DataFrame:
    ship(docs.sparkSession)
    content = docs.sparkSession.sparkContext.broadcast(content_of(vocab_path))
    names = [c.split(" ")[0] for c in schema.split(", ")]
    kinds = {"long": pa.int64(), "string": pa.string(), "array<int>": pa.list_(pa.int32())}
    types = [kinds[c.split(" ")[1]] for c in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = vocabulary(content.value)
        for b in small(batches, operator="bpe"):
            cols: list[list] = [[] for _ in names]
            for doc, text in zip(column(b, "doc_id").to_pylist(), strings(b), strict=True):
                for c, x in zip(cols, (doc, *row(*v.encode(text or ""))), strict=True):
                    c.append(x)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names)

    return id_text(docs, id_col, text_col).mapInArrow(run, schema)


def encode(docs: DataFrame, vocab_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids array<int>, decoded string) of every whole text."""
    return _map(docs, vocab_path, "doc_id long, ids array<int>, decoded string", lambda ids, decoded: (np.frombuffer(ids, "<i4"), decoded), id_col, text_col)


def encode_digest(docs: DataFrame, vocab_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256): the same encoding, digested where it is made."""

    def row(ids: bytes, decoded: str) -> tuple[int, str, str]:
        return len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(decoded.encode()).hexdigest()

    return _map(docs, vocab_path, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string", row, id_col, text_col)
