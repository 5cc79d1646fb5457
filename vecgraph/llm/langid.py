"""Language identification with hyperdimensional profiles.

Every letter (by code point) has a pseudo-random vector of +1 and -1. A trigram's vector binds its letters'
vectors, each permuted by its place, by multiplication. A text's vector bundles (adds) the vectors of all
its trigrams; a language's prototype bundles its training texts, each text weighing the same. A text gets
the language whose prototype has the largest cosine with it. White space and other non-letters bound words.

Defined cases: `und` and score 0 for null texts, texts without letters and when nothing was learned; ties go
to the language first in order; labels that are null teach nothing; repeated rows stay (and teach twice).
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecgraph.session import ship

from .common import column, kept, small, strings

#: Components of a hypervector.
DIMS = 1024
#: Trigram vectors kept by a worker before it starts anew.
TABLE = 40_000
UND = "und"


@lru_cache(maxsize=1)
def _is_letter() -> np.ndarray:
    return np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)


def trigrams(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Sorted different trigrams (three code points of 21 bits; 32 bounds a word) and their counts."""
    code = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    letter = _is_letter()[code]
    if not letter.any():
        return np.empty(0, np.int64), np.empty(0, np.int64)
    code[~letter] = 32
    edge = np.concatenate([[True], letter[:-1] | letter[1:]]) if len(letter) > 1 else np.array([True])
    code = np.concatenate([[32], code[edge], [32]])  # runs of non-letters count once
    keep = np.concatenate([[True], (code[1:] != 32) | (code[:-1] != 32)])
    code = code[keep]
    gram = (code[:-2] << 42) | (code[1:-1] << 21) | code[2:]
    gram.sort()
    first = np.flatnonzero(np.concatenate([[True], gram[1:] != gram[:-1]]))
    return gram[first], np.diff(np.append(first, len(gram)))


class Space:
    """The random vectors: letters by seed and code point, trigrams bound from them and kept in a bounded table."""

    def __init__(self, dims: int = DIMS, seed: int = 17) -> None:
        self.dims, self.seed = dims, seed
        self.letters: dict[int, np.ndarray] = {}
        self.clear()

    def clear(self) -> None:
        self.known = np.empty(0, np.int64)
        self.row = np.empty(0, np.int64)
        self.vectors = np.empty((1024, self.dims), np.int8)  # the first len(known) rows are in use

    def letter(self, code: int) -> np.ndarray:
        if (v := self.letters.get(code)) is None:
            bits = np.random.Generator(np.random.Philox(key=[self.seed, code])).integers(0, 2, self.dims, np.int8)
            if len(self.letters) > 20_000:
                self.letters.clear()
            v = self.letters[code] = bits * 2 - 1
        return v

    def bind(self, gram: int) -> np.ndarray:
        a, b, c = gram >> 42, gram >> 21 & 0x1FFFFF, gram & 0x1FFFFF
        return np.roll(self.letter(a), 2) * np.roll(self.letter(b), 1) * self.letter(c)

    def rows(self, grams: np.ndarray) -> np.ndarray:
        """Rows of self.vectors for sorted different trigrams."""
        at = np.searchsorted(self.known, grams)
        at[at == len(self.known)] = 0
        new = grams[self.known[at] != grams] if len(self.known) else grams
        if len(new):
            if len(self.known) + len(new) > TABLE:
                self.clear()
                new = grams
            used = len(self.known)
            if used + len(new) > len(self.vectors):
                self.vectors = np.concatenate([self.vectors, np.empty((max(len(new), len(self.vectors)), self.dims), np.int8)])
            for i, g in enumerate(new.tolist()):
                self.vectors[used + i] = self.bind(g)
            self.row = np.concatenate([self.row, np.arange(len(new)) + used])
            self.known = np.concatenate([self.known, new])
            order = np.argsort(self.known, kind="stable")
            self.known, self.row = self.known[order], self.row[order]
            at = np.searchsorted(self.known, grams)
        return self.row[at]

    def bundle(self, grams: np.ndarray, weights: np.ndarray) -> np.ndarray:
        out = np.zeros(self.dims, np.float32)
        for i in range(0, len(grams), 8192):
            g = grams[i : i + 8192]
            rows = self.rows(g)
            out += weights[i : i + 8192].astype(np.float32) @ self.vectors[rows].astype(np.float32)
        return out


def space(dims: int = DIMS) -> Space:
    return kept("langid", dims, lambda: Space(dims))


def fit(labelled: DataFrame, dims: int = DIMS, lang_col: str = "lang", text_col: str = "text") -> dict[str, np.ndarray]:
    """Prototype of every language, from all labelled rows: partial bundles per partition, then one sum per language."""
    ship(labelled.sparkSession)

    def bundle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weight: dict[str, dict[int, float]] = {}
        bundles: dict[str, np.ndarray] = {}

        def flush() -> None:
            for lang, grams in weight.items():
                key = np.fromiter(grams.keys(), np.int64, len(grams))
                order = np.argsort(key)
                v = space(dims).bundle(key[order], np.fromiter(grams.values(), np.float64, len(grams))[order])
                bundles[lang] = bundles.get(lang, 0) + v.astype(np.float64)
            weight.clear()

        for b in small(batches, operator="langid"):
            held: dict[str, list] = {}
            for lang, text in zip(column(b, "lang").to_pylist(), strings(b), strict=True):
                grams, n = trigrams(text or "")
                if len(grams):
                    held.setdefault(lang, []).append((grams, n / n.sum()))
            for lang, pairs in held.items():
                keys, inverse = np.unique(np.concatenate([p[0] for p in pairs]), return_inverse=True)
                total = np.bincount(inverse, np.concatenate([p[1] for p in pairs]))
                own = weight.setdefault(lang, {})
                for g, w in zip(keys.tolist(), total.tolist(), strict=True):
                    own[g] = own.get(g, 0.0) + w
            if sum(map(len, weight.values())) > TABLE:
                flush()
        flush()
        if bundles:
            yield pa.RecordBatch.from_arrays([pa.array(list(bundles), pa.string()), pa.array([v.tolist() for v in bundles.values()], pa.list_(pa.float64()))], ["lang", "bundle"])

    rows = labelled.select(F.col(lang_col).cast("string").alias("lang"), F.col(text_col).cast("string").alias("text")).where("lang is not null and text is not null")
    partial = rows.mapInArrow(bundle, "lang string, bundle array<double>")
    cells = partial.select("lang", F.posexplode("bundle").alias("i", "x")).groupBy("lang", "i").agg(F.sum("x").alias("x"))
    total = cells.groupBy("lang").agg(F.array_sort(F.collect_list(F.struct("i", "x"))).alias("v"))
    return {r["lang"]: np.array([p["x"] for p in r["v"]]) for r in total.orderBy("lang").collect()}


def predict(docs: DataFrame, prototypes: dict[str, np.ndarray], text_col: str = "text", out: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """All columns of docs and those named in `out`, which replace columns of docs with these names: one row per row."""
    ship(docs.sparkSession)
    names = sorted(prototypes)
    dims = len(prototypes[names[0]]) if names else DIMS
    matrix = np.stack([prototypes[n] / (np.linalg.norm(prototypes[n]) or 1) for n in names]).astype(np.float32) if names else None

    def label(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches, text_col, operator="langid"):
            langs, scores = [], []
            for text in strings(b, text_col):
                grams, n = trigrams(text or "")
                if matrix is None or not len(grams):
                    langs.append(UND)
                    scores.append(0.0)
                    continue
                v = space(dims).bundle(grams, n)
                cos = matrix @ (v / (np.linalg.norm(v) or 1))
                best = int(np.argmax(cos))
                langs.append(names[best])
                scores.append(float(min(1.0, max(0.0, cos[best]))))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(langs, pa.string()), pa.array(scores, pa.float64())], [*b.schema.names, *out])

    from pyspark.sql.types import DoubleType, StringType, StructField, StructType

    kept = docs.drop(*out)
    schema = StructType([*kept.schema.fields, StructField(out[0], StringType()), StructField(out[1], DoubleType())])
    return kept.mapInArrow(label, schema)


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % 4 == 2, F.lit(False))
