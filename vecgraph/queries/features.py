"""Rank terms, neighbourhood and routing features, and the losses at a fixed model."""

from __future__ import annotations

from pyspark.sql import functions as F

from vecgraph.functions.columns import d2, softmax
from vecgraph.measures import recall
from vecgraph.operators import exact, quantize
from vecgraph.operators import features as X
from vecgraph.operators.ranking import rank_candidates
from vecgraph.operators.walk import search_flat
from vecgraph.session import materialize

from .common import ADC, BOOK, CODES, ENTRY, GRAPH, ISO, LUT, TOP, TRUE_DIST, TTRUTH, H, Q, Setting, beam, query, r6, sql
from .common import d2 as d2_sql
from .quantizers import DECODED

LIST = 32
CODED = (ISO, Q, BOOK, CODES, LUT, ADC)
LISTS = f"l AS MATERIALIZED (SELECT * FROM (SELECT qid, vid, row_number() OVER (PARTITION BY qid ORDER BY d, vid) AS r FROM dist WHERE vid <> qid) WHERE r <= {LIST})"


def _ranked(mode: str) -> str:
    pair = f"sqrt({d2_sql('a.dvec', 'b.dvec')}) * sqrt({d2_sql('q.qvec', 'list_transform(list_zip(a.dvec, b.dvec), lambda p: (p[1] + p[2]) / 2)')})" if mode == "two_terms" else f"{d2_sql('a.dvec', 'q.qvec')} - {d2_sql('b.dvec', 'q.qvec')}"
    return sql(*CODED, DECODED, LISTS, TRUE_DIST, TTRUTH, f"""
ld AS MATERIALIZED (SELECT qid, l.vid, dvec FROM l JOIN dec ON dec.vid = l.vid),
sc AS (SELECT a.qid, a.vid, sum({pair}) AS s FROM ld a JOIN ld b ON a.qid = b.qid JOIN q ON q.qid = a.qid GROUP BY a.qid, a.vid),
rk AS (SELECT qid, vid, row_number() OVER (PARTITION BY qid ORDER BY s, vid) AS r FROM sc)""", "SELECT truth.qid, round(count(rk.vid) / 10, 6) AS recall FROM truth LEFT JOIN rk ON rk.qid = truth.qid AND rk.vid = truth.vid AND rk.r <= 10 GROUP BY truth.qid")


def _rank(spark, d, mode):
    s = Setting(spark, d)
    lists = search_flat(s.base, s.codes(), s.queries, s.model, LIST, LIST).select("qid", "vid")
    decoded = quantize.decode(s.codes(), s.model)
    got = rank_candidates(materialize(lists), decoded, s.queries.select(F.col("id").alias("qid"), F.col("vec").alias("qvec")), mode, TOP)
    return recall(got, exact.exact_knn(s.base, s.queries, TOP), TOP).select("qid", r6("recall"))


@query(_ranked("two_terms"))
def rank_two_terms(spark, d):
    return _rank(spark, d, "two_terms")


@query(_ranked("three_terms"))
def rank_three_terms(spark, d):
    return _rank(spark, d, "three_terms")


def _pop(rings: int) -> str:
    parts = ["h1 AS MATERIALIZED (SELECT DISTINCT src AS anchor, dst AS vid FROM graph)"]
    for i in range(2, rings + 1):
        parts.append(f"h{i} AS MATERIALIZED (SELECT anchor, vid FROM h{i - 1} UNION SELECT h.anchor, g.dst FROM h{i - 1} h JOIN graph g ON g.src = h.vid)")
    return ", ".join(parts) + f", pop AS MATERIALIZED (SELECT * FROM h{rings} WHERE anchor <> vid)"


@query(sql(ISO, GRAPH, _pop(2), "SELECT anchor, vid FROM pop"))
def nhop_pop(spark, d):
    return X.n_hop(Setting(spark, d).edges(), 2)


@query(sql(ISO, GRAPH, _pop(3), "SELECT anchor, vid FROM pop"))
def nhop_pop_extra_ring(spark, d):
    return X.n_hop(Setting(spark, d).edges(), 2, expansion="extra_ring")


SCOPES = f"""sr AS MATERIALIZED (SELECT anchor, vid, row_number() OVER (PARTITION BY anchor ORDER BY d, vid)::INT AS rank, count(*) OVER (PARTITION BY anchor) AS n
  FROM (SELECT anchor, vid, {d2_sql('a.vec', 'b.vec')} AS d FROM pop JOIN iso a ON a.id = anchor JOIN iso b ON b.id = vid)),
sc AS MATERIALIZED (SELECT anchor, vid, rank, CASE WHEN rank <= 4 THEN 'pos' ELSE 'neg' END AS scope FROM sr WHERE rank <= 16 AND n >= 16)"""


def _scopes(s: Setting, edges):
    return X.scopes(X.n_hop(edges, 2), s.base, 4, 12)


@query(sql(ISO, GRAPH, _pop(2), SCOPES, "SELECT anchor, vid, rank, scope FROM sc"))
def scopes(spark, d):
    s = Setting(spark, d)
    return _scopes(s, s.edges())


TRIPLETS = """dr AS (SELECT anchor, scope, arg_min(vid, md5(concat_ws(':', 1, 0, anchor, scope, vid))) AS vid FROM sc GROUP BY anchor, scope),
tri AS MATERIALIZED (SELECT anchor, max(vid) FILTER (scope = 'pos') AS pos, max(vid) FILTER (scope = 'neg') AS neg FROM dr GROUP BY anchor)"""


@query(sql(ISO, GRAPH, _pop(2), SCOPES, TRIPLETS, "SELECT anchor, pos, neg, 0 AS epoch FROM tri"))
def triplets(spark, d):
    s = Setting(spark, d)
    return X.triplets(_scopes(s, s.edges()), epoch=0, seed=1)


NUMBER = "('0x' || substr({}, 1, 8))::BIGINT % 1024"


@query(sql(ISO, GRAPH, f"""
p AS (SELECT src AS anchor, arg_min(dst, md5(concat_ws(':', 1, 0, src, dst))) AS pos FROM graph GROUP BY src),
dn AS (SELECT {NUMBER.format('md5(id::VARCHAR)')} AS bucket, arg_min(id, md5(concat_ws(':', 1, 0, id))) AS neg FROM iso GROUP BY 1),
tr AS (SELECT id AS anchor, t, {NUMBER.format("md5(concat_ws(':', 1, 0, id, t))")} AS bucket FROM iso, range(8) r(t)),
ok AS (SELECT tr.anchor, t, neg FROM tr JOIN dn ON dn.bucket = tr.bucket WHERE neg <> tr.anchor AND NOT EXISTS (SELECT 1 FROM graph g WHERE g.src = tr.anchor AND g.dst = neg)),
ng AS MATERIALIZED (SELECT anchor, arg_min(neg, t) AS neg FROM ok GROUP BY anchor),
vo AS MATERIALIZED (SELECT id, row_number() OVER (ORDER BY md5(concat_ws(':', 1, 0, id)), id) AS r FROM iso),
rest AS (SELECT p.anchor, arg_min(vo.id, vo.r) AS neg FROM p, vo WHERE p.anchor NOT IN (SELECT anchor FROM ng) AND vo.id <> p.anchor AND NOT EXISTS (SELECT 1 FROM graph g WHERE g.src = p.anchor AND g.dst = vo.id) GROUP BY p.anchor),
al AS (SELECT * FROM ng UNION ALL SELECT * FROM rest)""", "SELECT p.anchor, pos, neg, 0 AS epoch FROM p JOIN al ON al.anchor = p.anchor"))
def triplets_naive(spark, d):
    s = Setting(spark, d)
    return X.naive_triplets(s.base, s.edges(), epoch=0, seed=1)


@query(sql(ISO, "SELECT id FROM iso ORDER BY md5(concat_ws(':', 7, id)), id LIMIT 50"))
def query_sample(spark, d):
    return X.sample_queries(Setting(spark, d).base, 50, 7).select("id")


WALK = (*CODED, GRAPH, ENTRY, beam())
TRACES = "tr AS MATERIALIZED (SELECT qid, (step - 1)::INT AS step, beam, visited, nxt FROM w WHERE step > 0)"


def _traces(s: Setting, edges):
    return materialize(X.routing_traces(s.index(vectors=False, edges=edges), s.queries, s.model, H))


@query(sql(*WALK, TRACES, "SELECT qid, step, array_to_string(list_transform(beam, lambda c: c.vid), ',') AS cands, round(beam[1].d, 6) AS first, nxt AS next_vid FROM tr"))
def routing_traces(spark, d):
    s = Setting(spark, d)
    t = _traces(s, s.edges())
    return t.select("qid", "step", F.array_join(F.transform("cands", lambda c: c["vid"].cast("string")), ",").alias("cands"), F.round(F.get("cands", F.lit(0))["d2"], 6).alias("first"), "next_vid")


OPEN = "op AS MATERIALIZED (SELECT qid, step, c.vid AS vid, c.d AS d FROM (SELECT qid, step, unnest(list_filter(beam, lambda c: NOT list_contains(visited, c.vid))) AS c FROM tr WHERE nxt IS NOT NULL))"
EXACT = "lb AS MATERIALIZED (SELECT op.qid, step, arg_min(op.vid, {'d': tdist.d, 'v': op.vid}) AS label FROM op JOIN tdist ON tdist.qid = op.qid AND tdist.vid = op.vid GROUP BY op.qid, step)"


@query(sql(*WALK, TRACES, OPEN, TRUE_DIST, EXACT, "SELECT qid, step, label FROM lb"))
def trace_teacher_exact(spark, d):
    s = Setting(spark, d)
    return X.label_traces(_traces(s, s.edges()), s.base, s.queries, "exact")


@query(sql(*WALK, TRACES, "SELECT qid, step, nxt AS label FROM tr WHERE nxt IS NOT NULL"))
def trace_teacher_selected(spark, d):
    s = Setting(spark, d)
    return X.label_traces(_traces(s, s.edges()), s.base, s.queries, "selected")


BACK = """goal AS MATERIALIZED (SELECT qid, arg_min(vid, {'d': d, 'v': vid}) AS vid FROM tdist WHERE vid <> qid GROUP BY qid),
bk AS (SELECT qid, vid, 0 AS hops FROM goal UNION SELECT bk.qid, g.src, hops + 1 FROM bk JOIN graph g ON g.dst = bk.vid WHERE hops < 10),
far AS MATERIALIZED (SELECT qid, vid, min(hops) AS hops FROM bk GROUP BY qid, vid)"""


@query(sql(*WALK, TRACES, OPEN, TRUE_DIST, BACK, "SELECT op.qid, op.step, arg_min(op.vid, {'h': coalesce(far.hops, 1048576), 'd': tdist.d, 'v': op.vid}) AS label FROM op JOIN tdist ON tdist.qid = op.qid AND tdist.vid = op.vid LEFT JOIN far ON far.qid = op.qid AND far.vid = op.vid GROUP BY op.qid, op.step"))
def trace_teacher_hop_oracle(spark, d):
    s = Setting(spark, d)
    edges = s.edges()
    return X.label_traces(_traces(s, edges), s.base, s.queries, "hop_oracle", edges)


MARGIN, TAU, S = 0.05, 0.1, 0.1
NBR = f"""n AS (SELECT avg(greatest(0, {MARGIN} + {d2_sql('a.dvec', 'p.dvec')} - {d2_sql('a.dvec', 'g.dvec')})) AS v, count(*) AS c
  FROM tri JOIN dec a ON a.vid = anchor JOIN dec p ON p.vid = pos JOIN dec g ON g.vid = neg)"""


def _loss_nbr(s: Setting, edges):
    t = X.triplets(_scopes(s, edges), epoch=0, seed=1)
    dec = materialize(quantize.decode(s.codes(), s.model))
    for c in ("anchor", "pos", "neg"):
        t = t.join(dec.select(F.col("vid").alias(c), F.col("vec").alias(f"v_{c}")), c)
    hinge = F.greatest(F.lit(0.0), F.lit(MARGIN) + d2(F.col("v_anchor"), F.col("v_pos")) - d2(F.col("v_anchor"), F.col("v_neg")))
    return t.agg(F.avg(hinge).alias("v"), F.count("*").alias("c"))


NBR_PARTS = (ISO, BOOK, CODES, DECODED, GRAPH, _pop(2), SCOPES, TRIPLETS, NBR)


@query(sql(*NBR_PARTS, "SELECT round(v, 6) AS loss, c AS triplets FROM n"))
def loss_neighbour(spark, d):
    s = Setting(spark, d)
    return _loss_nbr(s, s.edges()).select(r6("v", "loss"), F.col("c").alias("triplets"))


HOP = f"hp AS MATERIALIZED (SELECT qid, step, vid, e / sum(e) OVER (PARTITION BY qid, step) AS p FROM (SELECT qid, step, vid, exp(-(d - min(d) OVER (PARTITION BY qid, step)) / {TAU}) AS e FROM op))"


def _hop(t):
    cand = t.where("next_vid is not null").select("qid", "step", F.filter("cands", lambda c: ~c["seen"]).alias("c"))
    p = softmax(F.transform("c", lambda c: -c["d2"] / TAU))
    both = cand.select("qid", "step", F.explode(F.arrays_zip(F.transform("c", lambda c: c["vid"]).alias("vid"), p.alias("p"))).alias("h"))
    return both.select("qid", "step", F.col("h.vid").alias("vid"), F.col("h.p").alias("p"))


@query(sql(*WALK, TRACES, OPEN, HOP, "SELECT qid, step, vid, round(p, 6) AS p FROM hp"))
def hop_prob(spark, d):
    s = Setting(spark, d)
    return _hop(_traces(s, s.edges())).select("qid", "step", "vid", r6("p"))


ROUTE = "r AS (SELECT avg(-ln(p)) AS v, count(*) AS c FROM hp JOIN lb ON lb.qid = hp.qid AND lb.step = hp.step AND lb.label = hp.vid)"


def _loss_route(s: Setting, edges):
    t = _traces(s, edges)
    label = X.label_traces(t, s.base, s.queries, "exact").select("qid", "step", F.col("label").alias("vid"))
    return _hop(t).join(label, ["qid", "step", "vid"]).agg(F.avg(-F.log("p")).alias("v"), F.count("*").alias("c"))


@query(sql(*WALK, TRACES, OPEN, HOP, TRUE_DIST, EXACT, ROUTE, "SELECT round(v, 6) AS loss, c AS lists FROM r"))
def loss_routing(spark, d):
    s = Setting(spark, d)
    return _loss_route(s, s.edges()).select(r6("v", "loss"), F.col("c").alias("lists"))


@query(sql(*WALK, TRACES, OPEN, HOP, TRUE_DIST, EXACT, ROUTE, DECODED, _pop(2), SCOPES, TRIPLETS, NBR, f"SELECT round(exp(-{S}) * n.v + r.v + {S}, 6) AS loss FROM n, r"))
def loss_joint(spark, d):
    s = Setting(spark, d)
    edges = s.edges()
    n, r = _loss_nbr(s, edges).first().v, _loss_route(s, edges).first().v
    import math

    return spark.createDataFrame([(round(math.exp(-S) * n + r + S, 6),)], "loss double")
