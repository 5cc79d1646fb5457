"""Joint training of rotation and codebooks with Adam and a one-cycle rate.

Features (triplet scopes, routing traces) come from distributed plans over the graph. A step's batch is chosen by a hash of
seed, step and row, so it is the same wherever the rows lie; its gradient sums come either from arrays on the driver
(`Features`: a bounded, documented sample of TRAIN_ROWS anchors and TRACE_QUERIES searches) or, for samples of any size, from
tables in the cluster (`Tables`), one row of partial sums per partition and loss. Both give the same sums.

Rates, temperatures and margins are in units of the data: of its root mean square and of the start's error per chunk.
"""

from __future__ import annotations

import copy
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecgraph.functions.columns import hash_share
from vecgraph.functions.kernels import lists, matrix, whole
from vecgraph.operators.features import label_traces, n_hop, routing_traces, scopes
from vecgraph.operators.quantize import Quantizer, distortion, opq_of, partial_sums, row_blocks, sample
from vecgraph.operators.rotation import exp_adjoint, positive, rotation, skew_log, skew_of
from vecgraph.operators.sharded import stored_index
from vecgraph.operators.soft import gumbel
from vecgraph.session import materialize, ship

from . import loss as L

#: Anchors and searches that a fit uses, at most; searches it uses unless told otherwise.
TRAIN_ROWS, TRACE_QUERIES, SEARCHES = 500_000, 100_000, 200


class Adam:
    def __init__(self, rate: float) -> None:
        self.rate, self.n = rate, 0
        self.m: dict[str, np.ndarray] = {}
        self.v: dict[str, np.ndarray] = {}

    def step(self, name: str, x: np.ndarray, g: np.ndarray, rate: float) -> np.ndarray:
        m = self.m[name] = 0.9 * self.m.get(name, np.zeros_like(g)) + 0.1 * g
        v = self.v[name] = 0.999 * self.v.get(name, np.zeros_like(g)) + 0.001 * g * g
        return x - rate * (m / (1 - 0.9**self.n)) / (np.sqrt(v / (1 - 0.999**self.n)) + 1e-8)


def one_cycle(step: int, steps: int, peak: float, decay: float = 0.2, warm: float = 0.1) -> float:
    """Rises to the peak over the first tenth, then falls along a cosine to decay * peak."""
    up = max(1, int(warm * steps))
    if step < up:
        return peak * (step + 1) / up
    return peak * (decay + (1 - decay) * 0.5 * (1 + np.cos(np.pi * (step - up) / max(1, steps - up))))


@dataclass(frozen=True)
class Step:
    """What the losses of one step need besides the model: hashes' seed, share of the rows of each loss, and scales."""

    seed: int
    step: int
    temperature: float
    tau: float
    margin: float
    noise: bool
    straight: bool

    def chance(self, ids: np.ndarray, what: int) -> np.ndarray:
        """A number in (0, 1) of each id, the same in any partitioning."""
        return L.uniform(self.seed * 31 + what, self.step, ids, 1, 1)[:, 0, 0]

    def gumbel(self, ids: np.ndarray, books: np.ndarray) -> np.ndarray | None:
        return gumbel(L.uniform(self.seed, self.step, ids, *books.shape[:2])) if self.noise else None


def share_of(rows: int, size: int) -> float:
    return min(1.0, size / max(1, rows))


def nbr_pick(at: Step, share: float, anchors: np.ndarray, n_pos: int, n_neg: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows of the batch, and which member of either scope each draws."""
    rows = np.flatnonzero(at.chance(anchors, 1) < share)
    return rows, (at.chance(anchors[rows], 2) * n_pos).astype(int), (at.chance(anchors[rows], 3) * n_neg).astype(int)


def nbr_sums(at: Step, r: np.ndarray, books: np.ndarray, ids: tuple, x: tuple) -> L.Sums:
    noise = tuple(at.gumbel(i, books) for i in ids) if at.noise else None
    return L.neighbour(r, books, x, noise, at.temperature, at.margin, at.straight)


def trace_key(qid: np.ndarray, step: np.ndarray) -> np.ndarray:
    return qid * 1024 + step


def route_sums(at: Step, r: np.ndarray, books: np.ndarray, q: np.ndarray, cand: np.ndarray, x: np.ndarray, row: np.ndarray, target: np.ndarray) -> L.Sums:
    return L.routing(r, books, q, x, row, target, at.gumbel(cand, books), at.temperature, at.tau, at.straight)


def recon_sums(at: Step, r: np.ndarray, books: np.ndarray, ids: np.ndarray, x: np.ndarray) -> L.Sums:
    return L.reconstruction(r, books, x, at.gumbel(ids, books), at.temperature, at.straight)


def in_blocks(n: int, width: int, none: L.Sums, sums: Callable[[slice], L.Sums]) -> L.Sums:
    """What the losses of n rows add up to, from `none`, so many rows at a time that soft codes of bounded size are held."""
    total = none
    for at in row_blocks(n, width):
        total = total.add(sums(at))
    return total


@dataclass
class Features:
    """A bounded sample of training features with the vectors they name."""

    ids: np.ndarray
    x: np.ndarray
    anchors: np.ndarray = field(default_factory=lambda: np.empty(0, int))  # places in x
    pos: np.ndarray = field(default_factory=lambda: np.empty((0, 0), int))
    neg: np.ndarray = field(default_factory=lambda: np.empty((0, 0), int))
    q: np.ndarray = field(default_factory=lambda: np.empty(0, int))  # of each trace row
    hop: np.ndarray = field(default_factory=lambda: np.empty(0, int))
    cand: np.ndarray = field(default_factory=lambda: np.empty(0, int))
    row: np.ndarray = field(default_factory=lambda: np.empty(0, int))
    target: np.ndarray = field(default_factory=lambda: np.empty(0))
    n_anchors: int | None = None  # of which `anchors` are those that some step draws
    units: tuple[float, float] | None = None  # scales of all rows, where x holds some only

    def scales(self, start: Quantizer) -> tuple[float, float]:
        """(root mean square of a component, the start's mean error)."""
        if self.units:
            return self.units
        square, error = 0.0, 0.0
        for at in row_blocks(len(self.x), self.x.shape[1]):
            x = self.x[at]
            square += (x**2).sum()
            error += ((start.turned(x) - start.decode(start.encode(x))) ** 2).sum(1).sum()
        return float(np.sqrt(square / self.x.size)), float(error / len(self.x))

    def sums(self, kinds: str, at: Step, size: int, r: np.ndarray, books: np.ndarray) -> dict[str, L.Sums]:
        out, width = {}, books.shape[0] * books.shape[1] + len(r)
        none = lambda name: L.Sums(np.zeros_like(r), np.zeros_like(books), {name: 0.0}, {name: 0})
        if "N" in kinds and len(self.anchors):
            rows, p, n = nbr_pick(at, share_of(self.n_anchors or len(self.anchors), size), self.ids[self.anchors], self.pos.shape[1], self.neg.shape[1])
            named = self.anchors[rows], self.pos[rows, p], self.neg[rows, n]

            def nbr(some: slice) -> L.Sums:
                places = [i[some] for i in named]
                return nbr_sums(at, r, books, tuple(self.ids[i] for i in places), tuple(self.x[i] for i in places))

            out["nbr"] = in_blocks(len(rows), 3 * width, none("nbr"), nbr)
        if "R" in kinds and len(self.q):
            picked = np.flatnonzero(at.chance(trace_key(self.ids[self.q], self.hop), 4) < share_of(len(self.q), size // 4))
            begin, end = np.searchsorted(self.row, picked), np.searchsorted(self.row, picked, "right")

            def route(some: slice) -> L.Sums:
                rows, first, n = picked[some], begin[some], (end - begin)[some]
                places = np.repeat(first, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                cand = self.cand[places]
                return route_sums(at, r, books, self.x[self.q[rows]], self.ids[cand], self.x[cand], np.repeat(np.arange(len(rows)), n), self.target[places])

            out["route"] = in_blocks(len(picked), width * max(1, int((end - begin).max(initial=0))), none("route"), route)
        if "C" in kinds:
            rows = np.flatnonzero(at.chance(self.ids, 5) < share_of(len(self.ids), size))
            out["recon"] = in_blocks(len(rows), width, none("recon"), lambda some: recon_sums(at, r, books, self.ids[rows[some]], self.x[rows[some]]))
        return out


@dataclass
class Tables:
    """Training features as tables of whole rows, each with the vectors it names; nothing but sums comes to the driver.

    base(id, vec); nbr(anchor, ids, vecs): the anchor, its positive and its negative scope; route(qid, step, vec, label, cand, vecs).
    """

    base: DataFrame
    n_base: int
    nbr: DataFrame | None = None
    n_nbr: int = 0
    n_pos: int = 0
    route: DataFrame | None = None
    n_route: int = 0

    def scales(self, start: Quantizer) -> tuple[float, float]:
        s = partial_sums(self.base, lambda x: np.array([(x**2).sum(), x.size]), 2)
        return float(np.sqrt(s[0] / max(1.0, s[1]))), distortion(self.base, start)

    def sums(self, kinds: str, at: Step, size: int, r: np.ndarray, books: np.ndarray) -> dict[str, L.Sums]:
        d, n_pos, out = len(r), self.n_pos, {}

        def nbr(t: pa.Table, share: float) -> L.Sums | None:
            anchors, members = t["anchor"].to_numpy(), whole(t["ids"])
            rows, p, n = nbr_pick(at, share, anchors, n_pos, members.shape[1] - 1 - n_pos)
            if not len(rows):
                return None
            x = matrix(t["vecs"].take(pa.array(rows))).reshape(len(rows), members.shape[1], d)
            cols, every = (np.zeros(len(rows), int), 1 + p, 1 + n_pos + n), np.arange(len(rows))
            return nbr_sums(at, r, books, tuple(members[rows, c] for c in cols), tuple(x[every, c] for c in cols))

        def route(t: pa.Table, share: float) -> L.Sums | None:
            t = t.take(pa.array(np.flatnonzero(at.chance(trace_key(t["qid"].to_numpy(), t["step"].to_numpy().astype(np.int64)), 4) < share)))
            if not t.num_rows:
                return None
            cand = t["cand"].combine_chunks()
            row = np.repeat(np.arange(t.num_rows), cand.value_lengths().to_numpy())
            ids = cand.flatten().to_numpy()
            x = t["vecs"].combine_chunks().flatten().to_numpy().reshape(len(ids), d)
            return route_sums(at, r, books, matrix(t["vec"]), ids, x, row, (ids == t["label"].to_numpy()[row]).astype(float))

        def recon(t: pa.Table, share: float) -> L.Sums | None:
            rows = np.flatnonzero(at.chance(t["id"].to_numpy(), 5) < share)
            return recon_sums(at, r, books, t["id"].to_numpy()[rows], matrix(t["vec"])[rows]) if len(rows) else None

        for kind, name, rows, share, kernel in (
            ("N", "nbr", self.nbr, share_of(self.n_nbr, size), nbr),
            ("R", "route", self.route, share_of(self.n_route, size // 4), route),
            ("C", "recon", self.base, share_of(self.n_base, size), recon),
        ):
            if kind in kinds and rows is not None:
                out[name] = _summed(rows, name, share, kernel, r, books)
        return out


def _summed(rows: DataFrame, name: str, share: float, kernel: Callable, r: np.ndarray, books: np.ndarray) -> L.Sums:
    """One row of partial sums per partition, added place by place; as many numbers as the model has reach the driver."""
    ship(rows.sparkSession)
    size = r.size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size + books.size + 2)
        for b in batches:
            s = kernel(pa.table(b), share) if b.num_rows else None
            if s is not None:
                total += np.concatenate([s.rotation.ravel(), s.books.ravel(), [s.loss[name], s.count[name]]])
        yield pa.RecordBatch.from_arrays([lists(total[None])], ["s"])

    cells = rows.mapInArrow(run, "s array<double>").select(F.posexplode("s").alias("i", "x")).groupBy("i").agg(F.sum("x").alias("x")).orderBy("i").collect()
    v = np.array([c.x for c in cells]) if cells else np.zeros(size + books.size + 2)
    return L.Sums(v[:size].reshape(r.shape), v[size:-2].reshape(books.shape), {name: v[-2]}, {name: int(v[-1])})


def scope_rows(base: DataFrame, edges: DataFrame, n: int, k_pos: int, k_neg: int, rows: int | None) -> DataFrame:
    """(anchor, vids): the ranked scopes of all anchors, or of about `rows` of them, picked by hash before any hop is taken."""
    anchors = base.select(F.col("id").alias("anchor"))
    if rows is not None:
        total = base.count()
        if total > rows:
            anchors = anchors.where(hash_share("anchor") < rows / total)
    return ranked_scopes(base, edges, n, k_pos, k_neg, anchors)


def ranked_scopes(base: DataFrame, edges: DataFrame, n: int, k_pos: int, k_neg: int, anchors: DataFrame) -> DataFrame:
    """(anchor, vids): the members of both scopes, the nearest first."""
    got = scopes(n_hop(edges, n, anchors=anchors), base, k_pos, k_neg)
    return got.groupBy("anchor").agg(F.sort_array(F.collect_list(F.struct("rank", "vid"))).alias("s")).select("anchor", F.transform("s", lambda p: p["vid"]).alias("vids"))


def collect_neighbourhood(base: DataFrame, edges: DataFrame, n: int, k_pos: int, k_neg: int, rows: int = TRAIN_ROWS) -> Features:
    """Scopes of about `rows` anchors, and the vectors they name."""
    return _features(base, scope_rows(base, edges, n, k_pos, k_neg, rows), k_pos)


def collect_drawn(base: DataFrame, edges: DataFrame, n: int, k_pos: int, k_neg: int, start: Quantizer, steps: int, size: int, seed: int = 1) -> Features:
    """Scopes of the anchors, of all rows, that the steps of a fit on neighbourhoods draw for their batches: its sums are those of the scopes of
    all rows (the share of a batch is of all rows, also of those whose scopes turn out too small), and its scales are of all rows."""
    ship(base.sparkSession)
    total = base.count()
    share = share_of(total, size)

    def drawn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = b.column(0).to_numpy()
            some = np.zeros(len(ids), bool)
            for step in range(steps if len(ids) else 0):
                some |= Step(seed, step, 0.0, 0.0, 0.0, False, False).chance(ids, 1) < share
            yield pa.RecordBatch.from_arrays([pa.array(ids[some])], ["anchor"])

    anchors = materialize(base.select("id").mapInArrow(drawn, "anchor long"))
    f = _features(base, ranked_scopes(base, edges, n, k_pos, k_neg, anchors), k_pos)
    f.n_anchors, f.units = total, Tables(base, total).scales(start)
    return f


def _features(base: DataFrame, ranked: DataFrame, k_pos: int) -> Features:
    t = ranked.orderBy("anchor").toArrow()
    anchors = t["anchor"].to_numpy()
    members = whole(t["vids"]).reshape(len(anchors), -1)
    named = np.unique(np.concatenate([anchors, members.ravel()]))
    wanted = base.sparkSession.createDataFrame(pa.table({"id": named}))
    t = base.join(wanted, "id", "left_semi").select("id", "vec").orderBy("id").toArrow()
    ids, x = t["id"].to_numpy(), matrix(t["vec"])
    at = lambda v: np.searchsorted(ids, v)
    return Features(ids, x, at(anchors), at(members[:, :k_pos]), at(members[:, k_pos:]))


def labelled_traces(base: DataFrame, edges: DataFrame, entry: int, q: Quantizer, queries: DataFrame, h: int, teacher: str) -> DataFrame:
    """(qid, step, label, open): the searches' lists with the current quantizer, unvisited candidates only, and the teacher's choice."""
    from vecgraph.operators.quantize import encode

    index = stored_index(base, edges, encode(base, q), False, base.sparkSession.createDataFrame([(entry,)], "vid long"))
    traces = materialize(routing_traces(index, queries, q, h))
    labels = label_traces(traces, base, queries, teacher, edges)
    open_ = F.transform(F.filter("cands", lambda c: ~c["seen"]), lambda c: c["vid"])
    return traces.where("next_vid is not null").join(labels, ["qid", "step"]).select("qid", "step", "label", open_.alias("open"))


def collect_routing(features: Features, base: DataFrame, edges: DataFrame, entry: int, q: Quantizer, queries: DataFrame, h: int, teacher: str) -> None:
    """Walk the sampled queries with the current quantizer and keep labelled lists and the vectors they name."""
    spark = base.sparkSession
    t = labelled_traces(base, edges, entry, q, queries, h, teacher).orderBy("qid", "step").toArrow()
    lists_ = t["open"].combine_chunks()
    size = np.diff(lists_.offsets.to_numpy())
    cand, qid, label = lists_.flatten().to_numpy(), t["qid"].to_numpy(), t["label"].to_numpy()
    row = np.repeat(np.arange(len(qid)), size)
    named = np.unique(np.concatenate([cand, qid]))
    new = np.setdiff1d(named, features.ids)
    if len(new):
        more = base.join(spark.createDataFrame(pa.table({"id": new})), "id", "left_semi").select("id", "vec").toArrow()
        ids, x = np.concatenate([features.ids, more["id"].to_numpy()]), np.concatenate([features.x, matrix(more["vec"])])
        order = np.argsort(ids)
        back = np.empty(len(ids), int)
        back[order] = np.arange(len(ids))
        features.ids, features.x = ids[order], x[order]
        features.anchors, features.pos, features.neg = back[features.anchors], back[features.pos], back[features.neg]
    features.q, features.cand, features.row = np.searchsorted(features.ids, qid), np.searchsorted(features.ids, cand), row
    features.hop = t["step"].to_numpy().astype(np.int64)
    features.target = (cand == label[row]).astype(float)


def _with_vectors(rows: DataFrame, base: DataFrame, key: list[str], members: str) -> DataFrame:
    """The rows and `vecs`: the vectors of the ids in `members`, in order, one after the other."""
    each = rows.select(*key, F.posexplode(members).alias("at", "id")).join(base.select("id", "vec"), "id")
    vecs = each.groupBy(*key).agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("at", "vec"))), lambda p: p["vec"])).alias("vecs"))
    return rows.join(vecs, key)


def neighbourhood_tables(base: DataFrame, edges: DataFrame, n: int, k_pos: int, k_neg: int, rows: int | None = None) -> Tables:
    """The same features as tables, of all anchors unless `rows` are asked for."""
    got = scope_rows(base, edges, n, k_pos, k_neg, rows).select("anchor", F.concat(F.array("anchor"), "vids").alias("ids"))
    nbr = materialize(_with_vectors(materialize(got), base, ["anchor"], "ids"))
    return Tables(base, base.count(), nbr, nbr.count(), k_pos)


def routing_tables(tables: Tables, base: DataFrame, edges: DataFrame, entry: int, q: Quantizer, queries: DataFrame, h: int, teacher: str) -> None:
    got = materialize(labelled_traces(base, edges, entry, q, queries, h, teacher).withColumnRenamed("open", "cand"))
    rows = _with_vectors(got, base, ["qid", "step"], "cand")
    tables.route = materialize(rows.join(queries.select(F.col("id").alias("qid"), "vec"), "qid"))
    tables.n_route = tables.route.count()


@dataclass
class Fitted:
    """The model kept, and what became of the others: the step it was kept at (0: the start), the last model, the validation scores."""

    quantizer: Quantizer
    theta: np.ndarray
    losses: list[dict[str, float]]
    start_distortion: float
    steps: int
    step_kept: int
    start: Quantizer
    last: Quantizer
    scores: list[tuple[int, float]]


def fit(f: Features | Tables, m: int, k: int, kinds: str = "NR", start: str | Quantizer = "opq", steps: int = 200, peak: float = 1e-3, size: int = 256, margin: float = 1.0, tau: float = 1.0, temperature: tuple[float, float] = (0.3, 0.1), seed: int = 1, noise: bool = True, straight: bool = False, alpha: float | None = None, refresh: Callable[[Quantizer], None] | None = None, every: int = 50, check: Callable[[Quantizer], float] | None = None, refresh_every: int | None = None) -> Fitted:
    """kinds: N neighbourhood, R routing, NR both, C reconstruction only (control). alpha None: learned, exp(-s) * N + R + s.

    start "opq" or "pq" (for Features), or a model to go on from. The margin is in the start's mean errors, tau and the temperatures,
    which fall from the first to the second, in errors per chunk. `check` scores a model (higher is better) before the first step and
    every `every` steps; the best is kept, and without it the last. Traces are refreshed every `refresh_every` steps (as often, unless
    told otherwise). Codes are always hard, by argmin.
    """
    if isinstance(start, Quantizer):
        begin = start
    else:
        begin = opq_of(f.x, m, k)[0] if start == "opq" else Quantizer("pq", _pq_books(f.x, m, k))
    d = m * begin.books.shape[2]
    r0 = positive(begin.rotation) if begin.rotation is not None else np.eye(d)
    theta = skew_log(r0)[np.triu_indices(d, 1)]
    books, s = begin.books.copy(), np.zeros(1)
    if begin.rotation is not None and r0 is not begin.rotation and not np.allclose(r0, begin.rotation):
        books[0, :, 0] = -books[0, :, 0]  # the first rotated component was turned around
    model = lambda: Quantizer("gaq", books.copy(), rotation(skew_of(theta, d)))
    rms, error = f.scales(begin)
    unit = max(error, 1e-12) / m
    adam, losses = Adam(peak), []
    first = model()
    best, scores = (0, first, theta.copy()), [(0, check(first))] if check else []
    for step in range(steps):
        t = unit * temperature[0] * (temperature[1] / temperature[0]) ** (step / max(1, steps - 1))
        a = skew_of(theta, d)
        r = rotation(a)
        sums = f.sums(kinds, Step(seed, step, t, tau * unit, margin * error, noise, straight), size, r, books)
        gr, gb, seen = np.zeros((d, d)), np.zeros_like(books), {}
        for name, x in sums.items():
            n = max(1, x.count[name])
            scale = 1.0 if name == "route" else 1 / max(error, 1e-12)  # squared distances in the start's mean errors
            weight = scale * ((np.exp(-s[0]) if alpha is None else alpha) if name == "nbr" else 1.0)
            gr, gb = gr + weight * x.rotation / n, gb + weight * x.books / n
            seen[name] = scale * x.loss[name] / n
        adam.n = step + 1
        rate = one_cycle(step, steps, peak)
        theta = adam.step("theta", theta, exp_adjoint(a, gr), rate)
        books = adam.step("books", books, gb, rate * rms)
        if alpha is None and "nbr" in seen and "route" in seen:
            s = adam.step("s", s, np.array([1 - np.exp(-s[0]) * seen["nbr"]]), rate)
        losses.append(seen)
        if refresh and (step + 1) % (refresh_every or every) == 0 and step + 1 < steps:
            refresh(model())
        if check and ((step + 1) % every == 0 or step + 1 == steps):
            scores.append((step + 1, check(model())))
            if scores[-1][1] > max(v for _, v in scores[:-1]):
                best = (step + 1, model(), theta.copy())
    last = model()
    kept, done, angle = best if check else (steps, last, theta)
    return Fitted(done, angle, losses, error, steps, kept, first, last, scores)


def _pq_books(x: np.ndarray, m: int, k: int) -> np.ndarray:
    from vecgraph.operators.quantize import fit_books

    return fit_books(x, m, k, 25)


def train(base: DataFrame, edges: DataFrame, entry: int, m: int, k: int, kinds: str = "NR", n: int = 2, k_pos: int = 4, k_neg: int = 12, h: int = 16, teacher: str = "exact", queries: DataFrame | None = None, searches: int = SEARCHES, validation: DataFrame | None = None, spread: bool = False, features: Features | None = None, **options) -> Fitted:
    """The whole loop: scopes once, traces with the current quantizer and again at each refresh, then the fit. The model kept is
    the best by `check`: recall of a scan by codes for `validation` rows, which should not be in the base (without them, for some of the
    sample's own rows). Without `queries`, about `searches` rows picked by hash, at most TRACE_QUERIES, are searched for traces.
    `spread`: features stay in the cluster and each step adds up partial sums there; then all anchors are used. `features`: scopes that
    were collected before, and the start's traces if it has any."""
    f = copy.copy(features) if features is not None else neighbourhood_tables(base, edges, n, k_pos, k_neg) if spread else collect_neighbourhood(base, edges, n, k_pos, k_neg)
    seen = sample(base) if spread else f.x
    if not spread and not len(f.anchors):
        f = Features(*_all(base))
        seen = f.x
    start = options.get("start", "opq")
    if not isinstance(start, Quantizer):
        start = opq_of(seen, m, k)[0] if start == "opq" else Quantizer("pq", _pq_books(seen, m, k))
    options["start"] = start
    if "check" not in options:
        options["check"] = code_recall(seen, sample(validation, VALIDATION) if validation is not None else None)
    if "R" in kinds:
        asked = materialize(queries.select("id", "vec") if queries is not None else searched(base, searches))
        collect = routing_tables if spread else collect_routing
        if spread or not len(f.q):
            collect(f, base, edges, entry, start, asked, h, teacher)
        options.setdefault("refresh", lambda q: collect(f, base, edges, entry, q, asked, h, teacher))
    return fit(f, m, k, kinds, **options)


def searched(base: DataFrame, searches: int = SEARCHES) -> DataFrame:
    """(id, vec) of the rows that are searched for traces."""
    return base.orderBy(hash_share("id"), "id").limit(min(TRACE_QUERIES, searches)).select("id", "vec")


#: Validation rows of a fit, and distances that its score holds at once.
VALIDATION, SCAN_CELLS = 1000, 1 << 20


def code_recall(x: np.ndarray, queries: np.ndarray | None = None, k: int = 10, rows: int = 256, seed: int = 11) -> Callable[[Quantizer], float]:
    """A validation score: recall@k of a scan by codes against exact neighbours among x, for the queries (or for some rows of x)."""
    from vecgraph.operators.quantize import adc

    own = np.sort(np.random.default_rng(seed).permutation(len(x))[:rows]) if queries is None or not len(queries) else None
    q = x[own] if own is not None else queries
    k = min(k, len(x) - (own is not None))
    cuts = [slice(i, i + max(1, SCAN_CELLS // max(1, len(x)))) for i in range(0, len(q), max(1, SCAN_CELLS // max(1, len(x))))]

    def nearest(distances: Callable[[slice], np.ndarray]) -> np.ndarray:
        """Places of the k nearest, ties to the first: of the places up to the k-th distance only, in blocks of queries."""
        out = np.empty((len(q), k), int)
        for at in cuts if k else ():
            d = distances(at)
            if own is not None:
                d[np.arange(len(d)), own[at]] = np.inf
            far = np.partition(d, k - 1, 1)[:, k - 1]
            for i, row in enumerate(d):
                close = np.flatnonzero(row <= far[i])
                out[at.start + i] = close[np.argsort(row[close], kind="stable")[:k]]
        return out

    norm = np.concatenate([(x[at] * x[at]).sum(1) for at in row_blocks(len(x), x.shape[1])]) if len(x) else np.empty(0)
    # as d2_blas, whose product of x with itself would be as large as x
    true = nearest(lambda at: np.maximum((q[at] * q[at]).sum(1)[:, None] - 2 * (q[at] @ x.T) + norm[None], 0))

    def score(model: Quantizer) -> float:
        codes = model.encode(x)
        return float((nearest(lambda at: adc(model.lut(q[at]), codes))[:, :, None] == true[:, None, :]).any(2).mean())

    return score


def _all(base: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    t = base.orderBy(hash_share("id"), "id").limit(TRAIN_ROWS).select("id", "vec").orderBy("id").toArrow()
    return t["id"].to_numpy(), matrix(t["vec"])
