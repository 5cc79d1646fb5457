"""The experiments: thirteen configurations, ablations, parameter sweeps, scale series and set statistics.

Folds: queries are the rows whose id is divisible by 50, models are fitted on rows of neither this fold nor the validation fold
(last digit nine) over a graph of their own, and chosen by the validation fold; searches run over all rows. Every comparison gives
each learned or fitted quantizer the same training rows and a stopping rule of its own, and reports it beside two controls: the
start the learned quantizer came from, and the same loop trained on reconstruction error alone.
"""

from __future__ import annotations

import copy
import time
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecgraph import measures
from vecgraph.functions.columns import hash_share
from vecgraph.operators import exact, graphs, quantize
from vecgraph.operators.sharded import ShardedIndex
from vecgraph.operators.walk import BANDWIDTH, BLOCK_BYTES, LATENCY_S, SHARD_ROWS, Index, Kernel, searcher, sweep
from vecgraph.session import CACHES, materialize
from vecgraph.sources import sets
from vecgraph.train import linkreg, loop, neural

#: number, mode, graph, quantizer
CONFIGS = [
    *[(i + 1, "disk_tier", "flat", q) for i, q in enumerate(("pq", "opq", "neural", "gaq"))],
    *[(i + 5, "code_only", "layered", q) for i, q in enumerate(("pq", "linkreg", "opq", "neural", "gaq"))],
    *[(i + 10, "code_only", "spread", q) for i, q in enumerate(("pq", "opq", "neural", "gaq"))],
]
BEAMS = (10, 16, 32, 64, 128)
#: Recall floors of the two modes on each set, as far as it reaches them.
FLOORS = {"disk_tier": 0.95, "code_only": 0.7}
#: What the learned quantizer and its ablations are trained on: kinds of features, teacher.
VARIANTS = {"gaq": ("NR", "exact"), "gaq_n": ("N", "exact"), "gaq_r": ("R", "exact"), "gaq_hop": ("R", "hop_oracle"), "recon": ("C", "exact")}

#: Rows that one task builds a graph over, about.
CELL_ROWS = 20_000

_LABS: dict = {}
CACHES.append(_LABS)


def lab(spark: SparkSession, sf_dir: str, name: str = "iso", m: int = 8, k: int = 16, steps: int = 60) -> Lab:
    """The session's lab of these settings; those of one set share its base, truth and graphs."""
    app = spark.sparkContext.applicationId
    key = (app, sf_dir, name, m, k, steps)
    if key not in _LABS:
        shared = _LABS.setdefault((app, sf_dir, name), {})
        _LABS[key] = Lab(spark, sf_dir, name, m, k, steps=steps, shared=shared)
    return _LABS[key]


@dataclass
class Lab:
    """One set with its graphs and quantizers, made when first asked for."""

    spark: SparkSession
    sf_dir: str
    name: str = "iso"
    m: int = 8
    k: int = 16
    degree: int = 16
    steps: int = 60
    kept: dict = field(default_factory=dict)
    shared: dict = field(default_factory=dict)

    def get(self, key: str, make, shared: bool = False):
        at = self.shared if shared else self.kept
        if key not in at:
            begin = time.perf_counter()
            at[key] = make()
            at[f"seconds:{key}"] = time.perf_counter() - begin
        return at[key]

    @property
    def base(self) -> DataFrame:
        return self.get("base", lambda: materialize(sets.SETS[self.name](self.spark, self.sf_dir)), True)

    @property
    def rows(self) -> int:
        return self.get("rows", self.base.count, True)

    @property
    def queries(self) -> DataFrame:
        return sets.queries_of(self.base)

    @property
    def training(self) -> DataFrame:
        return self.get("training", lambda: materialize(sets.training_of(self.base)), True)

    @property
    def truth(self) -> DataFrame:
        return self.get("truth", lambda: materialize(exact.exact_knn(self.base, self.queries, 10)), True)

    @property
    def training_graph(self) -> DataFrame:
        """The flat graph over the training rows alone: features never see a query or a validation row."""
        return self.get("training_graph", lambda: materialize(graphs.build(self.training, "flat", self.degree, cells=max(1, self.rows // CELL_ROWS)).where("level = 0").drop("level")), True)

    @property
    def features(self) -> loop.Features:
        return self.get("features", lambda: loop.collect_neighbourhood(self.training, self.training_graph, 2, 4, 12), True)

    def quantizer(self, name: str) -> quantize.Quantizer:
        def make() -> quantize.Quantizer:
            if name == "pq":
                return quantize.train_pq(self.training, self.m, self.k)
            if name == "opq":
                return quantize.train_opq(self.training, self.m, self.k)
            if name == "neural":
                f = self.features
                d_out = -(-40 // self.m) * self.m  # forty outputs, up to a whole number of chunks
                return neural.train_neural(f.x, (f.anchors, f.pos, f.neg), self.m, self.k, d_out=d_out)[0]
            return self.fitted(*VARIANTS[name]).quantizer

        return self.get(f"quantizer:{name}", make)

    def fitted(self, kinds: str, teacher: str = "exact", seed: int = 1, **options) -> loop.Fitted:
        """Trained from the converged rotation-optimized start on the training fold, chosen by the validation fold."""
        n, pos, neg = (options.pop(k, v) for k, v in (("n", 2), ("k_pos", 4), ("k_neg", 12)))
        options.setdefault("start", self.quantizer("opq"))

        def scoped() -> loop.Features:
            return self.features if (n, pos, neg) == (2, 4, 12) else loop.collect_neighbourhood(self.training, self.training_graph, n, pos, neg)

        def traced(entry: int) -> loop.Features:
            f = copy.copy(self.get(f"scopes:{n}:{pos}:{neg}", scoped, True))
            loop.collect_routing(f, self.training, self.training_graph, entry, options["start"], materialize(loop.searched(self.training)), 16, teacher)
            return f

        def make() -> loop.Fitted:
            entry = self.get("entry:training", lambda: graphs.entry_vertex(self.training), True)
            seen = self.get(f"traced:{teacher}:{n}:{pos}:{neg}", lambda: traced(entry)) if "R" in kinds else self.get(f"scopes:{n}:{pos}:{neg}", scoped, True)
            if len(seen.anchors):  # fits on the same vectors have one score: its true neighbours are found once
                key = f"check:{teacher if 'R' in kinds else ''}:{n}:{pos}:{neg}"
                options.setdefault("check", self.get(key, lambda: loop.code_recall(seen.x, quantize.sample(sets.validation_of(self.base), loop.VALIDATION))))
            return loop.train(self.training, self.training_graph, entry, self.m, self.k, kinds, n, pos, neg, teacher=teacher, steps=self.steps, every=max(1, self.steps // 4), refresh_every=max(1, self.steps // 2), size=128, seed=seed, validation=sets.validation_of(self.base), features=seen, **options)

        return self.get(f"fitted:{kinds}:{teacher}:{seed}:{n}:{pos}:{neg}", make)

    def fitted_over(self) -> loop.Fitted:
        """Both kinds of features, the start and its scales of all training rows: no sample of them is taken, and the last model is kept."""

        def make() -> loop.Fitted:
            rows, links, every = self.training, self.training_graph, max(1, self.steps // 2)
            entry = self.get("entry:training", lambda: graphs.entry_vertex(rows), True)
            start = self.get("start:over", lambda: quantize.opq_over(rows, self.m, self.k)[0])
            seen = self.get("drawn:over", lambda: loop.collect_drawn(rows, links, 2, 4, 12, start, self.steps, 128))
            return loop.train(rows, links, entry, self.m, self.k, "NR", 2, 4, 12, steps=self.steps, refresh_every=every, size=128, seed=1, start=start, features=seen, check=None)

        return self.get("fitted:over", make)

    def _asked(self, kind: str, q: quantize.Quantizer, vectors: bool, key: str) -> tuple[DataFrame, DataFrame]:
        """(index rows, queries): shards of about CELL_ROWS rows, however many rows there are, each with a graph of its own. All queries ask
        all shards, so every row can be found."""
        cells, most = max(1, self.rows // CELL_ROWS), min(SHARD_ROWS, 2 * CELL_ROWS)
        whole = self.get(f"sharded:{kind}", lambda: ShardedIndex.build(self.base, q, cells, kind, self.degree, pool=48, most=most), True)
        return self.get(f"index:{kind}:{key}:{vectors}", lambda: whole.recode(q, vectors).rows), self.queries

    def curve(self, mode: str, kind: str, name: str, hs: tuple[int, ...] = (16,), q: quantize.Quantizer | None = None, key: str | None = None) -> DataFrame:
        """(h, qid, rank, vid, d2, hops, reads, seconds) of one configuration at several beams."""
        if name == "linkreg":
            model = self.quantizer("pq")
            rows, ask = self._asked(kind, model, False, "pq")
            kernel: Kernel = linkreg.linkreg_searcher(model, self.get(f"weights:{kind}", lambda: self._weights(model, kind)))
        else:
            model = q or self.quantizer(name)
            rows, ask = self._asked(kind, model, mode != "code_only", key or name)
            kernel = searcher(10, mode, model)
        return sweep(rows, ask, kernel, hs, 10)

    def compared(self, kind: str, models: list[quantize.Quantizer], h: int) -> list[dict]:
        """Recall, hops and distortion of code-only walks with several models of one shape, in one pass over index and base each:
        codes are made where the vectors lie."""
        rows, ask = self._asked(kind, models[0], True, "compared")

        def kernel(idx: Index, ids: np.ndarray, q: np.ndarray, i: int):
            return searcher(10, "code_only", models[i])(replace(idx, codes=models[i].encode(idx.vectors)), ids, q, h)

        got = {s["h"]: s for s in self.scores(sweep(rows, ask, kernel, tuple(range(len(models))), 10), "code_only")}
        error = lambda x: np.array([((m.turned(x) - m.decode(m.encode(x))) ** 2).sum() for m in models])
        far = quantize.partial_sums(self.base, error, len(models)) / max(1, self.rows)
        return [{"recall": got[i]["recall"], "hops": got[i]["hops"], "distortion": float(far[i])} for i in range(len(models))]

    def run(self, mode: str, kind: str, name: str, h: int = 16) -> DataFrame:
        return self.curve(mode, kind, name, (h,)).drop("h", "seconds")

    def _weights(self, model: quantize.Quantizer, kind: str) -> np.ndarray:
        """Fitted on the links and codes of all training rows in the graphs that are searched."""
        rows, _ = self._asked(kind, model, True, "pq")
        return linkreg.weights_over(rows, model, lambda ids: (ids % 10 != 9) & (ids % sets.QUERY_STEP != 0), links=8)

    def scores(self, found: DataFrame, mode: str, truth: DataFrame | None = None) -> list[dict]:
        """Per beam (against the truth of the lab's queries, or another): recall, hops, reads, modelled I/O seconds a query, and queries per second of one thread (I/O included)."""
        found = materialize(found)
        truth = self.truth if truth is None else truth
        true = truth.count()
        hit = found.join(truth.select("qid", "vid"), ["qid", "vid"], "left_semi").groupBy("h").agg(F.count("*").alias("hit"))
        per = found.groupBy("h", "qid").agg(*(F.max(c).alias(c) for c in ("hops", "reads", "seconds")))
        total = per.groupBy("h").agg(F.avg("hops").alias("hops"), F.avg("reads").alias("reads"), F.avg("seconds").alias("seconds"))
        out = []
        for r in total.join(hit, "h", "left").orderBy("h").collect():
            io = r.reads * (LATENCY_S + BLOCK_BYTES / BANDWIDTH) if mode == "disk_tier" else 0.0
            out.append({"h": r.h, "recall": (r.hit or 0) / max(1, true), "hops": r.hops, "reads": r.reads, "io_s": io, "qps": 1 / (r.seconds + io)})
        return out


def config_matrix(lab: Lab, hs: tuple[int, ...] = BEAMS) -> DataFrame:
    rows = []
    for no, mode, kind, name in CONFIGS:
        for s in lab.scores(lab.curve(mode, kind, name, hs), mode):
            rows.append((lab.name, no, mode, kind, name, s["h"], round(s["recall"], 6), round(s["hops"], 6), round(s["reads"], 6), round(s["io_s"], 9), s["qps"]))
    return lab.spark.createDataFrame(rows, "name string, no int, mode string, graph string, quantizer string, h int, recall double, hops double, reads double, io_s double, qps double")


def at_floor(points: list[dict], floor: float, what: str) -> float | None:
    """The measure at a recall floor, on a straight line between the beams around it; None where no beam reaches it."""
    before = None
    for p in points:
        if p["recall"] >= floor:
            if before is None:
                return p[what]
            share = (floor - before["recall"]) / (p["recall"] - before["recall"])
            return before[what] + share * (p[what] - before[what])
        before = p
    return None


def ablation(lab: Lab, mode: str = "code_only", kind: str = "spread", hs: tuple[int, ...] = BEAMS, floor: float | None = None) -> DataFrame:
    """Both features, each alone, routing with the hop-oracle teacher, and the two controls: recall at the widest beam, and hops and
    queries per second at the recall floor (null where a variant doesn't reach it)."""
    rows, floor = [], FLOORS[mode] if floor is None else floor
    for name in (*VARIANTS, "opq", "pq"):
        points = lab.scores(lab.curve(mode, kind, name, hs), mode)
        rows.append((lab.name, name, floor, round(points[-1]["recall"], 6), *(x if x is None else round(x, 4) for x in (at_floor(points, floor, "hops"), at_floor(points, floor, "qps"))), round(quantize.distortion(lab.base, lab.quantizer(name)), 6)))
    return lab.spark.createDataFrame(rows, "name string, variant string, floor double, ceiling double, hops double, qps double, distortion double")


def learning(lab: Lab, seeds: tuple[int, ...] = (1, 2, 3), kind: str = "spread", h: int = 16) -> DataFrame:
    """What training does to its start: for every variant and seed the start, the last model and the one kept, the step it was kept
    at, its validation score, and recall, hops and distortion on the query fold (code-only walks)."""
    told, models = [], []
    for variant in ("gaq", "gaq_n", "gaq_r", "recon"):
        for seed in seeds:
            f = lab.fitted(*VARIANTS[variant], seed=seed)
            score = dict(f.scores)
            for which, step, q in (("start", 0, f.start), ("last", f.steps, f.last), ("kept", f.step_kept, f.quantizer)):
                told.append((lab.name, variant, seed, which, step, round(score[step], 6)))
                models.append(q)
    rows = [(*t, round(g["recall"], 6), round(g["hops"], 6), round(g["distortion"], 6)) for t, g in zip(told, lab.compared(kind, models, h), strict=True)]
    return lab.spark.createDataFrame(rows, "name string, variant string, seed int, model string, step int, validation double, recall double, hops double, distortion double")


def ratio_sweep(lab: Lab, ratios: tuple[float, ...] = (0.1, 0.2, 0.3, 0.5, 1.0, 2.0), total: int = 22, kind: str = "spread", h: int = 16) -> DataFrame:
    """k_pos / k_neg with their sum fixed, both losses; the last model is measured as well, as the one kept may be the start. Hops stand
    for time: queries per second differ from call to call by more than ratios do."""
    told, models = [], []
    for ratio in ratios:
        pos = max(1, round(total * ratio / (1 + ratio)))
        f = lab.fitted("NR", k_pos=pos, k_neg=total - pos)
        for which, step, q in (("kept", f.step_kept, f.quantizer), ("last", f.steps, f.last)):
            told.append((ratio, pos, total - pos, which, step, round(dict(f.scores)[step], 6)))
            models.append(q)
    rows = [(*t, round(g["recall"], 6), round(g["hops"], 6)) for t, g in zip(told, lab.compared(kind, models, h), strict=True)]
    return lab.spark.createDataFrame(rows, "ratio double, k_pos int, k_neg int, model string, step int, validation double, recall double, hops double")


def size_grid(spark: SparkSession, sf_dir: str, name: str, ms: tuple[int, ...] = (4, 8, 16), ks: tuple[int, ...] = (16, 64, 256), mode: str = "code_only", quantizers: tuple[str, ...] = ("opq", "gaq"), hs: tuple[int, ...] = (16, 32, 128), steps: int = 24) -> DataFrame:
    """Best recall over beams, and queries per second at the floor, for every number of chunks and codewords; a number of codewords
    needs at least four training rows each, so small sets leave the largest books out."""
    rows, kind = [], "flat" if mode == "disk_tier" else "spread"
    most = lab(spark, sf_dir, name).training.count() // 4
    for m in ms:
        for k in (k for k in ks if k <= most):
            own = lab(spark, sf_dir, name, m, k, steps)
            for q in quantizers:
                points = own.scores(own.curve(mode, kind, q, hs), mode)
                qps = at_floor(points, FLOORS[mode], "qps")
                rows.append((q, m, k, quantize.code_bits(m, k), round(max(p["recall"] for p in points), 6), qps and round(qps, 2)))
    return spark.createDataFrame(rows, "quantizer string, m int, k int, bits int, ceiling double, qps double")


def set_statistics(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("iso", "skew", "text", "page", "profile")) -> DataFrame:
    rows = []
    for name in names:
        base = materialize(sets.SETS[name](spark, sf_dir))
        near = exact.exact_knn(base, sets.queries_of(base), 20)
        lid = measures.lid(near.where("d2 > 0")).agg(F.percentile("lid", 0.5)).first()[0]
        one = base.agg(F.count("*"), F.max(F.size("vec"))).first()
        rows.append((name, one[1], one[0], sets.queries_of(base).count(), round(float(lid), 4) if lid is not None else None))
    return spark.createDataFrame(rows, "name string, dims int, base long, queries long, lid double")


def training_cost(lab: Lab) -> DataFrame:
    """Seconds and bytes of the two learned quantizers; features and the start are made before the clock starts."""
    lab.features, lab.quantizer("opq")
    rows = []
    for name in ("neural", "gaq"):
        q = lab.quantizer(name)
        size = neural.network_bytes(q.transform) + q.model_bytes() if name == "neural" else q.model_bytes()
        rows.append((name, lab.kept[f"seconds:quantizer:{name}"], size))
    return lab.spark.createDataFrame(rows, "quantizer string, seconds double, bytes long")


def subset_training(lab: Lab, shares: tuple[float, ...] = (0.5, 1.0)) -> DataFrame:
    """Recall and distortion when the quantizers are fitted on a share of the training fold, picked by hash."""
    rows = []
    for share in shares:
        part = materialize(lab.training.where(hash_share("id") < share))
        start = quantize.train_opq(part, lab.m, lab.k)
        edges = materialize(graphs.build(part, "flat", lab.degree, cells=max(1, int(lab.rows * share) // CELL_ROWS)).where("level = 0").drop("level"))
        f = loop.train(part, edges, graphs.entry_vertex(part), lab.m, lab.k, "NR", steps=lab.steps, every=max(1, lab.steps // 4), size=128, start=start, validation=sets.validation_of(lab.base))
        for name, q in (("opq", start), ("gaq", f.quantizer), ("gaq_last", f.last)):
            s = lab.scores(lab.curve("code_only", "spread", "gaq", (16,), q, f"share:{share}:{name}"), "code_only")[0]
            rows.append((share, name, round(s["recall"], 6), round(quantize.distortion(lab.base, q), 6)))
    return lab.spark.createDataFrame(rows, "share double, quantizer string, recall double, distortion double")


def balance_case(lab: Lab) -> DataFrame:
    """Variance per chunk before and after the learned rotation (the last model's), of all training rows."""
    from vecgraph.operators.rotation import chunk_values

    last = lab.fitted_over().last
    cov = quantize.covariance(lab.training, len(last.rotation))
    after = chunk_values(cov, last.rotation, lab.m)
    rows = [(j, float(a), float(b)) for j, (a, b) in enumerate(zip(chunk_values(cov, None, lab.m), after, strict=True))]
    return lab.spark.createDataFrame(rows, "chunk int, before double, after double")


#: Rows that the scale series fits its quantizers on, at most.
SERIES_ROWS = 4_000


def scale_series(spark: SparkSession, dirs: list[str], name: str = "rowvec", cells_of=lambda n: max(1, n // CELL_ROWS), quantizers: tuple[str, ...] = ("pq", "opq", "gaq"), h: int = 32, steps: int = 24, m: int = 4, k: int = 16) -> DataFrame:
    """The same searches on growing bases in both modes: graphs built in cells, walked shard by shard, answers merged. Quantizers are
    fitted on SERIES_ROWS rows outside the query and validation folds."""
    rows = []
    for d in dirs:
        base = materialize(sets.SETS[name](spark, d))
        n, asked = base.count(), sets.queries_of(base)
        train = sets.training_of(base)
        part = materialize(train.where(hash_share("id") < SERIES_ROWS / max(1, train.count())))
        opq = quantize.train_opq(part, m, k)
        made = {"pq": lambda p=part: quantize.train_pq(p, m, k), "opq": lambda q=opq: q}
        made["gaq"] = lambda p=part, q=opq, b=base: _series_fit(p, q, b, steps, m, k)
        truth = materialize(exact.exact_knn(base, asked, 10))
        index, many = ShardedIndex.build(base, opq, cells_of(n)), asked.count()
        for name_ in quantizers:
            own = index.recode(made[name_]())
            for mode in ("code_only", "disk_tier"):
                begin = time.perf_counter()
                found = materialize(own.search(asked, probes=2, h=h, k=10, mode=mode))
                seconds = time.perf_counter() - begin
                r = measures.recall(found, truth, 10).agg(F.avg("recall")).first()[0]
                rows.append((d.rstrip("/").split("/")[-1], n, mode, name_, round(float(r or 0), 6), many / seconds))
    return spark.createDataFrame(rows, "sf string, base long, mode string, quantizer string, recall double, qps double")


def _series_fit(part: DataFrame, start: quantize.Quantizer, base: DataFrame, steps: int, m: int, k: int) -> quantize.Quantizer:
    edges = materialize(graphs.build(part, "flat", 16).where("level = 0").drop("level"))
    options = {"steps": steps, "every": max(1, steps // 2), "size": 128, "start": start, "validation": sets.validation_of(base)}
    return loop.train(part, edges, graphs.entry_vertex(part), m, k, "NR", **options).quantizer


def term_ablation(lab: Lab, hs: tuple[int, ...] = (16, 32)) -> DataFrame:
    """Recall of code-only walks that keep their candidates by two or by all three terms of the comparison, at two beams."""
    from vecgraph.operators.ranking import terms_searcher

    rows, model = [], lab.quantizer("opq")
    at, ask = lab._asked("spread", model, False, "opq")
    for mode in ("two_terms", "three_terms"):
        for s in lab.scores(sweep(at, ask, terms_searcher(10, model, mode), hs, 10), "code_only"):
            rows.append((lab.name, mode, s["h"], round(s["recall"], 6), round(s["hops"], 6)))
    return lab.spark.createDataFrame(rows, "name string, terms string, h int, recall double, hops double")
