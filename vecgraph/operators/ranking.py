"""Order of candidates by the terms of the comparison identity.

For candidates x, y and a query q: d2(x,q) - d2(y,q) = 2 |y-x| |q-mid(x,y)| cos(angle). With all three terms, summed
over a list's members, the order is that of distance; without the angle only the neighbour and query distances remain.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecgraph.functions.columns import d2
from vecgraph.functions.kernels import d2_pairs

from .exact import top
from .quantize import Quantizer
from .walk import Index, Kernel


def rank_candidates(lists: DataFrame, decoded: DataFrame, queries: DataFrame, mode: str, k: int) -> DataFrame:
    """lists(qid, vid), decoded(vid, vec), queries(qid, qvec) -> (qid, rank, vid). Lists are short: pairs are within one list."""
    x = lists.join(decoded, "vid").join(queries, "qid").select("qid", F.col("vid"), F.col("vec").alias("x"), "qvec")
    y = x.select("qid", F.col("vid").alias("other"), F.col("x").alias("y"))
    mid = F.zip_with("x", "y", lambda a, b: (a + b) / 2)
    two = F.sqrt(d2(F.col("x"), F.col("y"))) * F.sqrt(d2(F.col("qvec"), mid))
    three = d2(F.col("x"), F.col("qvec")) - d2(F.col("y"), F.col("qvec"))
    score = x.join(y, "qid").groupBy("qid", "vid").agg(F.sum(two if mode == "two_terms" else three).alias("d2"))
    return top(score, k).select("qid", "rank", "vid")


def term_scores(x: np.ndarray, q: np.ndarray, mode: str) -> np.ndarray:
    """Scores of a list's members, smaller being better."""
    far = d2_pairs(x, q[None])[:, 0]
    if mode == "three_terms":
        return len(x) * far - far.sum()
    # |q - mid|^2 by the parallelogram rule
    pair = d2_pairs(x, x)
    mid = np.maximum((far[:, None] + far[None]) / 2 - pair / 4, 0)
    return (np.sqrt(pair) * np.sqrt(mid)).sum(1)


def terms_searcher(k: int, quantizer: Quantizer, mode: str) -> Kernel:
    """Code-only walks whose candidate list is kept in order of the terms, over the list itself, after every hop."""

    def kernel(idx: Index, ids: np.ndarray, q: np.ndarray, h: int) -> Iterator[pa.RecordBatch]:
        out: list[list[np.ndarray]] = [[] for _ in range(5)]
        for qid, turned in zip(ids, quantizer.turned(q), strict=True):
            beam, seen, hops = np.array([idx.entry]), set(), 0
            score = np.zeros(1)
            while (now := next((int(p) for p in beam if int(p) not in seen), None)) is not None:
                seen.add(now)
                hops += 1
                near = idx.neighbours[now]
                beam = np.union1d(beam, near[near >= 0])
                score = term_scores(quantizer.decode(idx.codes[beam]), turned, mode)
                order = np.lexsort((idx.ids[beam], score))[:h]
                beam, score = beam[order], score[order]
            ok = idx.ids[beam] != qid
            found = idx.ids[beam][ok][:k]
            for cell, v in zip(out, (np.full(len(found), qid), found, score[ok][:k], np.full(len(found), hops), np.zeros(len(found), np.int64)), strict=True):
                cell.append(v)
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in out], ["qid", "vid", "d2", "hops", "reads"])

    return kernel
