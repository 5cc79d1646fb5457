"""Product quantization: codebooks, codes, lookup tables, distances, and their measures.

A model is a rotation (or none) and M books of K codewords. It is small (K * D + D * D numbers) and travels
with the tasks; training passes send one row of partial sums per partition and round to the driver.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecgraph.functions.columns import hash_share
from vecgraph.functions.kernels import d2_blas, d2_pairs, fold, lists, matrix
from vecgraph.session import ship


#: Numbers that a pass over many rows works on at once.
BLOCK_CELLS = 1 << 22


def row_blocks(n: int, width: int) -> Iterator[slice]:
    """n rows in blocks of BLOCK_CELLS numbers, at `width` numbers a row."""
    step = max(1, BLOCK_CELLS // max(1, width))
    return (slice(i, i + step) for i in range(0, n, step))


@dataclass(frozen=True)
class Quantizer:
    name: str
    books: np.ndarray  # M x K x width
    rotation: np.ndarray | None = None  # rows of x are rotated as x @ rotation.T
    transform: Callable[[np.ndarray], np.ndarray] | None = None  # a learned map before the books, if any

    @property
    def m(self) -> int:
        return self.books.shape[0]

    @property
    def k(self) -> int:
        return self.books.shape[1]

    def turned(self, x: np.ndarray) -> np.ndarray:
        x = self.transform(x) if self.transform else x
        x = x if self.rotation is None else x @ self.rotation.T
        pad = self.m * self.books.shape[2] - x.shape[1]
        return np.pad(x, ((0, 0), (0, pad))) if pad else x

    def encode(self, x: np.ndarray) -> np.ndarray:
        """Nearest codeword of every chunk, ties to the smaller number; in blocks of rows."""
        w, out = self.books.shape[2], np.empty((len(x), self.m), np.intp)
        for at in row_blocks(len(x), self.k * w):
            y = self.turned(x[at])
            for j in range(self.m):
                out[at, j] = d2_pairs(y[:, j * w : (j + 1) * w], self.books[j]).argmin(1)
        return out

    def decode(self, codes: np.ndarray) -> np.ndarray:
        """Codewords in a row, in the rotated space."""
        return np.concatenate([self.books[j][codes[:, j]] for j in range(self.m)], 1)

    def lut(self, q: np.ndarray) -> np.ndarray:
        """Q x M x K squared distances of the queries' chunks to the codewords."""
        y, w = self.turned(q), self.books.shape[2]
        return np.stack([d2_pairs(y[:, j * w : (j + 1) * w], self.books[j]) for j in range(self.m)], 1)

    def model_bytes(self) -> int:
        d = self.m * self.books.shape[2]
        return 4 * ((d * (d - 1) // 2 if self.rotation is not None else 0) + self.k * d)


def code_bits(m: int, k: int) -> int:
    return m * int(np.ceil(np.log2(k)))


def books_of(x: np.ndarray, m: int) -> np.ndarray:
    """K whole vectors as M books of chunks."""
    return np.ascontiguousarray(x.reshape(len(x), m, -1).transpose(1, 0, 2))


def seeded_books(base: DataFrame, m: int, k: int) -> Quantizer:
    """The chunks of the k rows with the smallest ids: a model without training."""
    return Quantizer("seeded", books_of(np.array([r.vec for r in base.orderBy("id").limit(k).collect()]), m))


def encode(base: DataFrame, q: Quantizer) -> DataFrame:
    """(vid, code array<int>): one pass over the vectors."""
    ship(base.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), lists(q.encode(matrix(b.column(1))).astype(np.int32))], ["vid", "code"])

    return base.select("id", "vec").mapInArrow(run, "vid long, code array<int>")


def decode(codes: DataFrame, q: Quantizer) -> DataFrame:
    ship(codes.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), lists(q.decode(matrix(b.column(1)).astype(int)))], ["vid", "vec"])

    return codes.select("vid", "code").mapInArrow(run, "vid long, vec array<double>")


def build_lut(queries: DataFrame, q: Quantizer) -> DataFrame:
    """(qid, lut array<array<double>>): one table per query, before any walk."""
    ship(queries.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                t = q.lut(matrix(b.column(1)))
                inner = lists(t.reshape(-1, t.shape[2]))
                yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(pa.array(np.arange(len(t) + 1, dtype=np.int32) * q.m), inner)], ["qid", "lut"])

    return queries.select("id", "vec").mapInArrow(run, "qid long, lut array<array<double>>")


def adc(lut: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """Q x n distances: table entries added in chunk order, all queries' entries of a code fetched together."""
    out = np.zeros((len(codes), len(lut)))
    for j in range(lut.shape[1]):
        out += np.ascontiguousarray(lut[:, j].T)[codes[:, j]]
    return np.ascontiguousarray(out.T)


def sdc_tables(q: Quantizer) -> np.ndarray:
    """M x K x K distances between codewords."""
    return np.stack([d2_pairs(b, b) for b in q.books])


def sdc(table: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return fold(np.stack([table[j][a[:, j, None], b[None, :, j]] for j in range(len(table))], -1))


# ---- training ----


def partial_sums(base: DataFrame, kernel: Callable[[np.ndarray], np.ndarray], size: int) -> np.ndarray:
    """Sum of kernel(batch of vectors) over all rows: one row per partition reaches the driver."""
    ship(base.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = np.zeros(size)
        for b in batches:
            if b.num_rows:
                out += kernel(matrix(b.column(0))).ravel()
        yield pa.RecordBatch.from_arrays([lists(out[None])], ["s"])

    # partitions meet in a sum per place, so the driver gets `size` numbers however many there are
    parts = base.select("vec").mapInArrow(run, "s array<double>")
    cells = parts.select(F.posexplode("s").alias("i", "x")).groupBy("i").agg(F.sum("x").alias("x")).orderBy("i").collect()
    return np.array([r.x for r in cells])


def _lloyd_kernel(q: Quantizer) -> Callable[[np.ndarray], np.ndarray]:
    m, k, w = q.books.shape

    def kernel(x: np.ndarray) -> np.ndarray:
        y, code = q.turned(x), q.encode(x)
        out = np.zeros((m, k, w + 2))
        for j in range(m):
            part = y[:, j * w : (j + 1) * w]
            np.add.at(out[j, :, :w], code[:, j], part)
            out[j, :, w] = np.bincount(code[:, j], minlength=k)
            out[j, 0, w + 1] = ((part - q.books[j][code[:, j]]) ** 2).sum()
        return out

    return kernel


def lloyd(base: DataFrame, q: Quantizer, rounds: int, tolerance: float = 0.0) -> tuple[Quantizer, list[float]]:
    """k-means in every chunk at once: one job per round. Empty codewords stay. Returns the errors before each round."""
    m, k, w = q.books.shape
    errors: list[float] = []
    for _ in range(rounds):
        s = partial_sums(base, _lloyd_kernel(q), m * k * (w + 2)).reshape(m, k, w + 2)
        n = s[:, :, w : w + 1]
        q = Quantizer(q.name, np.where(n > 0, s[:, :, :w] / np.maximum(n, 1), q.books), q.rotation, q.transform)
        errors.append(float(s[:, 0, w + 1].sum() / max(1.0, n[0].sum())))
        if len(errors) > 1 and errors[-2] - errors[-1] <= tolerance * errors[-2]:
            break
    return q, errors


#: Training rows held on the driver: what a quantizer is fitted on is a hash sample of bounded size; encoding covers every row.
TRAIN_ROWS = 500_000


def sample(base: DataFrame, rows: int = TRAIN_ROWS) -> np.ndarray:
    """Up to `rows` rows in hash order. Rows beyond the hash that about twice as many pass are left out before the sort."""
    total = base.count()
    some = base.where(hash_share("id") < 2 * rows / total) if total > 4 * rows else base
    picked = some.orderBy(hash_share("id"), "id").limit(rows).select("vec")
    t = picked.toArrow()
    return matrix(t["vec"])


def moved(x: np.ndarray, c: np.ndarray, rounds: int) -> np.ndarray:
    """Codewords after rounds of k-means. Sums are in the order of the rows, as np.add.at's, which is slower."""
    k = len(c)
    for _ in range(rounds):
        code = d2_blas(x, c).argmin(1)
        n = np.bincount(code, minlength=k)
        s = np.stack([np.bincount(code, x[:, i], k) for i in range(x.shape[1])], 1)
        c = np.where(n[:, None] > 0, s / np.maximum(n, 1)[:, None], c)
    return c


def kmeans(x: np.ndarray, k: int, rounds: int, start: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    c = moved(x, x[:k].copy() if start is None else start, rounds)
    return c, d2_blas(x, c).argmin(1)


def plusplus(x: np.ndarray, k: int, seed: int = 1) -> np.ndarray:
    """Starting codewords drawn with chances in proportion to the squared distance from those chosen."""
    r = np.random.default_rng(seed)
    chosen = [x[r.integers(len(x))]]
    far = d2_blas(x, chosen[0][None])[:, 0]
    while len(chosen) < k:
        total = far.sum()
        chosen.append(x[r.choice(len(x), p=far / total)] if total > 0 else x[r.integers(len(x))])
        far = np.minimum(far, d2_blas(x, chosen[-1][None])[:, 0])
    return np.array(chosen)


def fit_books(y: np.ndarray, m: int, k: int, rounds: int, books: np.ndarray | None = None, init: str = "plusplus") -> np.ndarray:
    w = y.shape[1] // m
    out = []
    for j in range(m):
        part = y[:, j * w : (j + 1) * w]
        start = books[j] if books is not None else plusplus(part, k, seed=j) if init == "plusplus" else part[:k].copy()
        out.append(moved(part, start, rounds))
    return np.array(out)


def train_pq(base: DataFrame, m: int, k: int, rounds: int = 25, init: str = "plusplus", rows: int = TRAIN_ROWS) -> Quantizer:
    return Quantizer("pq", fit_books(sample(base, rows), m, k, rounds, init=init))


def even_axes(cov: np.ndarray, m: int) -> np.ndarray:
    """A start of a rotation: principal axes dealt to chunks so that the chunks' products of variances are even."""
    value, vector = np.linalg.eigh(cov)
    d = len(cov)
    load, room, place = np.zeros(m), np.full(m, d // m), [[] for _ in range(m)]
    for i in np.argsort(-value):
        j = min((c for c in range(m) if room[c]), key=lambda c: load[c])
        place[j].append(i)
        load[j] += np.log(max(value[i], 1e-12))
        room[j] -= 1
    return vector[:, [i for p in place for i in p]].T


def opq_of(x: np.ndarray, m: int, k: int, outer: int = 60, tolerance: float = 1e-4) -> tuple[Quantizer, list[float]]:
    """Books and rotation in turns: k-means rounds, then the rotation nearest to mapping x on its decoded form (an SVD),
    until the relative fall of the error over ten rounds is under the tolerance."""
    d = x.shape[1]
    rotation = even_axes(np.cov(x.T), m)
    books, errors = None, []
    for _ in range(outer):
        y = x @ rotation.T
        books = fit_books(y, m, k, 1 if books is not None else 8, books)
        q = Quantizer("opq", books, rotation)
        error, cross = 0.0, np.zeros((d, d))
        for at in row_blocks(len(x), d):
            z = q.decode(np.stack([d2_blas(y[at, j * (d // m) : (j + 1) * (d // m)], books[j]).argmin(1) for j in range(m)], 1))
            error += ((y[at] - z) ** 2).sum(1).sum()
            cross += z.T @ x[at]
        errors.append(float(error / len(x)))
        u, _, vt = np.linalg.svd(cross)
        rotation = u @ vt
        if len(errors) > 30 and errors[-11] - errors[-1] < tolerance * errors[-11]:
            break
    return Quantizer("opq", fit_books(x @ rotation.T, m, k, 4, books), rotation), errors


def train_opq(base: DataFrame, m: int, k: int, outer: int = 60, rows: int = TRAIN_ROWS) -> Quantizer:
    return opq_of(sample(base, rows), m, k, outer)[0]


# ---- training on all rows: models and sums travel, rows stay ----


def covariance(base: DataFrame, d: int) -> np.ndarray:
    """Of all rows, as np.cov."""
    s = partial_sums(base, lambda x: np.concatenate([(x.T @ x).ravel(), x.sum(0), [len(x)]]), d * d + d + 1)
    n, mean = s[-1], s[d * d : -1] / max(1.0, s[-1])
    return (s[: d * d].reshape(d, d) - n * np.outer(mean, mean)) / max(1.0, n - 1)


def _of_codes(x: np.ndarray, code: np.ndarray, k: int) -> np.ndarray:
    """K x (D + 1): sums of the rows of each code, and their number."""
    one = (code[:, None] == np.arange(k)).astype(float)
    return np.concatenate([one.T @ x, one.sum(0)[:, None]], 1)


def centres_over(base: DataFrame, n: int, rounds: int = 8) -> np.ndarray:
    """k-means over all rows, from the first n in hash order; one job a round."""
    c = np.array([r.vec for r in base.orderBy(hash_share("id"), "id").limit(n).collect()])
    for _ in range(rounds):
        s = partial_sums(base, lambda x, c=c: _of_codes(x, d2_blas(x, c).argmin(1), len(c)), c.size + len(c)).reshape(len(c), -1)
        c = np.where(s[:, -1:] > 0, s[:, :-1] / np.maximum(s[:, -1:], 1), c)
    return c


def _drawn(base: DataFrame, rotation: np.ndarray, books: list[np.ndarray], m: int, seed: int) -> np.ndarray:
    """M x width: for every chunk one row of all, with chances in proportion to the squared distance from the codewords that it has: the
    row whose hash, as an exponential waiting time at that rate, comes first."""
    from vecgraph.train.loss import uniform

    ship(base.sparkSession)
    w = len(rotation) // m

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            ids, y = b.column(0).to_numpy(), matrix(b.column(1)) @ rotation.T
            parts = [y[:, j * w : (j + 1) * w] for j in range(m)]
            best = []
            for j, part in enumerate(parts):
                rate = d2_blas(part, books[j]).min(1) if books else np.ones(len(part))
                u = uniform(seed * 1024 + j, 0, ids, 1, 1)[:, 0, 0]
                wait = np.where(rate > 0, -np.log(u) / np.where(rate > 0, rate, 1.0), np.inf)
                best.append(np.lexsort((ids, wait))[0])
                parts[j] = (part[best[-1]], wait[best[-1]])
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(m, dtype=np.int32)), pa.array([t for _, t in parts]), pa.array(ids[best]), lists(np.array([v for v, _ in parts]))], ["j", "wait", "id", "vec"])

    got = base.select("id", "vec").mapInArrow(run, "j int, wait double, id long, vec array<double>").groupBy("j").agg(F.min(F.struct("wait", "id", "vec")).alias("b"))
    return np.array([r.b.vec for r in got.orderBy("j").collect()])


def opq_over(base: DataFrame, m: int, k: int, outer: int = 60, tolerance: float = 1e-4, seed: int = 1) -> tuple[Quantizer, list[float]]:
    """As opq_of, over all rows of the base: a round is one job that adds up rows by code, from which books, rotation and error follow."""
    first = base.select("vec").first()
    d = len(first.vec)
    w, rotation = d // m, even_axes(covariance(base, d), m)
    chosen: list[np.ndarray] = []
    for i in range(k):
        books = [np.array([c[j] for c in chosen]) for j in range(m)] if chosen else []
        chosen.append(_drawn(base, rotation, books, m, seed + i))
    books, errors = np.stack(chosen, 1), []

    def summed() -> tuple[np.ndarray, float]:
        def kernel(x: np.ndarray) -> np.ndarray:
            y, out, error = x @ rotation.T, [], 0.0
            for j in range(m):
                far = d2_blas(y[:, j * w : (j + 1) * w], books[j])
                out.append(_of_codes(x, far.argmin(1), k).ravel())
                error += far.min(1).sum()
            return np.concatenate([*out, [error]])

        s = partial_sums(base, kernel, m * k * (d + 1) + 1)
        return s[:-1].reshape(m, k, d + 1), float(s[-1])

    def means(s: np.ndarray) -> np.ndarray:
        turned = np.stack([s[j, :, :-1] @ rotation[j * w : (j + 1) * w].T for j in range(m)])
        return np.where(s[:, :, -1:] > 0, turned / np.maximum(s[:, :, -1:], 1), books)

    for _ in range(7):
        books = means(summed()[0])
    for _ in range(outer):
        s, error = summed()
        books = means(s)
        errors.append(error / max(1.0, s[0, :, -1].sum()))
        u, _, vt = np.linalg.svd(np.concatenate([books[j].T @ s[j, :, :-1] for j in range(m)]))
        rotation = u @ vt
        if len(errors) > 30 and errors[-11] - errors[-1] < tolerance * errors[-11]:
            break
    for _ in range(4):
        books = means(summed()[0])
    return Quantizer("opq", books, rotation), errors


# ---- measures ----


def distortion(base: DataFrame, q: Quantizer) -> float:
    """Mean squared distance between vectors (rotated) and what their codes stand for."""

    def kernel(x: np.ndarray) -> np.ndarray:
        return np.array([((q.turned(x) - q.decode(q.encode(x))) ** 2).sum(), len(x)])

    s = partial_sums(base, kernel, 2)
    return float(s[0] / max(1.0, s[1]))
