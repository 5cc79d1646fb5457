"""Searches in all modes, their variants and measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from vecgraph import measures
from vecgraph.operators import exact, quantize
from vecgraph.operators.fresh import FreshIndex
from vecgraph.operators.graphs import entry_vertex
from vecgraph.operators.walk import beam_search, beam_search_joins
from vecgraph.session import materialize
from vecgraph.sources import sets

from .common import ADC, BEAM_RESULT, BOOK, CODES, ENTRY, FULL, GRAPH, ISO, LUT, TEXT, TOP, TRUE_DIST, TTRUTH, H, K, M, Q, Setting, beam, hashed, query, r6, sql
from .common import d2 as d2_sql

RANKED = "SELECT qid, rank, vid, round(d2, 6) AS d2, hops FROM ranked WHERE rank <= 10"
CODE_WALK = (ISO, Q, BOOK, CODES, LUT, ADC, GRAPH, ENTRY, beam())


def _cols(df, *more):
    return df.select("qid", "rank", "vid", r6("d2"), "hops", *more)


@query(sql(ISO, Q, FULL, GRAPH, ENTRY, beam(), BEAM_RESULT, RANKED))
def beam_full(spark, d):
    s = Setting(spark, d)
    return _cols(beam_search(s.index(vectors=True, codes=False), s.queries, H, TOP, "full"))


@query(sql(*CODE_WALK, BEAM_RESULT, RANKED))
def beam_code_only(spark, d):
    s = Setting(spark, d)
    return _cols(beam_search(s.index(vectors=False), s.queries, H, TOP, "code_only", s.model))


@query(sql(*CODE_WALK, BEAM_RESULT, RANKED))
def beam_by_joins(spark, d):
    s = Setting(spark, d)
    return _cols(beam_search_joins(materialize(s.codes()), s.edges(), materialize(quantize.build_lut(s.queries, s.model)), entry_vertex(s.base), H, TOP))


DISK = """v AS (SELECT qid, hops, unnest(visited) AS vid FROM ended),
ranked AS (SELECT v.qid, row_number() OVER (PARTITION BY v.qid ORDER BY t.d, v.vid)::INT AS rank, v.vid, t.d AS d2, hops::BIGINT AS hops FROM v JOIN tdist t ON t.qid = v.qid AND t.vid = v.vid WHERE v.vid <> v.qid)"""
DISK_END = "SELECT qid, rank, vid, round(d2, 6) AS d2, hops, hops AS reads FROM ranked WHERE rank <= 10"


@query(sql(*CODE_WALK, TRUE_DIST, DISK, DISK_END))
def beam_disk_final(spark, d):
    s = Setting(spark, d)
    return _cols(beam_search(s.index(vectors=True), s.queries, H, TOP, "disk_tier", s.model, rerank_at="final"), "reads")


EACH = f"""cand AS MATERIALIZED (SELECT a.qid, src, list({{'d': a.d, 'vid': dst, 't': t.d}}) AS near FROM graph JOIN dist a ON a.vid = graph.dst JOIN tdist t ON t.qid = a.qid AND t.vid = graph.dst GROUP BY a.qid, src),
w AS (
  SELECT a.qid, [{{'d': a.d, 'vid': a.vid, 't': t.d}}] AS beam, []::BIGINT[] AS visited, a.vid AS nxt FROM dist a JOIN entry ON entry.vid = a.vid JOIN tdist t ON t.qid = a.qid AND t.vid = a.vid
  UNION ALL
  SELECT qid, beam, visited, list_sort(list_transform(list_filter(beam, lambda c: NOT list_contains(visited, c.vid)), lambda c: {{'t': c.t, 'vid': c.vid}}))[1].vid FROM (
    SELECT w.qid, list_append(visited, nxt) AS visited, list_sort(list_distinct(list_concat(beam, near)))[1:{H}] AS beam
    FROM w JOIN cand ON cand.qid = w.qid AND cand.src = w.nxt WHERE nxt IS NOT NULL)),
ended AS MATERIALIZED (SELECT qid, len(visited) AS hops, visited FROM w WHERE nxt IS NULL)"""


@query(sql(ISO, Q, BOOK, CODES, LUT, ADC, GRAPH, ENTRY, TRUE_DIST, EACH, DISK, DISK_END))
def beam_disk_each_hop(spark, d):
    s = Setting(spark, d)
    return _cols(beam_search(s.index(vectors=True), s.queries, H, TOP, "disk_tier", s.model, rerank_at="each_hop"), "reads")


@query(sql(*CODE_WALK, BEAM_RESULT, "SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY rank)::INT AS rank, ranked.vid, round(d2, 6) AS d2 FROM ranked JOIN embeddings e ON e.vec_id = ranked.vid WHERE e.label < 5"))
def filtered_search(spark, d):
    """Labels below five: the walk's whole list, filtered afterwards."""
    s = Setting(spark, d)
    found = beam_search(s.index(vectors=False), s.queries, H, H, "code_only", s.model)
    keep = sets.table(spark, d, "embeddings").where("label < 5").select(F.col("vec_id").alias("vid"))
    return exact.top(found.join(keep, "vid", "left_semi"), H).select("qid", "rank", "vid", r6("d2"))


@query(sql(ISO, Q, BOOK, CODES, LUT, ADC, GRAPH, ENTRY, "open AS MATERIALIZED (SELECT src, dst FROM graph JOIN embeddings e ON e.vec_id = dst WHERE e.label < 5)", beam(links="open"), "found AS (SELECT qid, hops, unnest(list_filter(beam, lambda c: c.vid <> qid)) AS c FROM ended), ranked AS (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY c.d, c.vid)::INT AS rank, c.vid AS vid, c.d AS d2, hops::BIGINT AS hops FROM found JOIN embeddings e ON e.vec_id = c.vid WHERE e.label < 5)", RANKED))
def filtered_walk(spark, d):
    """Labels below five: vertices of other labels are neither kept nor passed through."""
    s = Setting(spark, d)
    keep = sets.table(spark, d, "embeddings").where("label < 5").select(F.col("vec_id").alias("vid"))
    return _cols(beam_search(s.index(vectors=False, allowed=keep), s.queries, H, TOP, "code_only", s.model, filtered=True))


OOD_Q = f"o AS MATERIALIZED {hashed('benchmark', 'item_id', 'text')}, q AS MATERIALIZED (SELECT id AS qid, vec AS qvec FROM o)"


@query(sql(TEXT, OOD_Q, FULL, GRAPH, ENTRY, beam(), BEAM_RESULT.replace("list_filter(beam, lambda c: c.vid <> qid)", "beam"), RANKED))
def ood_walk(spark, d):
    """Walks for passages of the benchmark over the graph of the documents."""
    s = Setting(spark, d, "text")
    return _cols(beam_search(s.index(vectors=True, codes=False), sets.ood(spark, d), H, TOP, "full", own=True))


@query(sql(TEXT, f"o AS MATERIALIZED {hashed('benchmark', 'item_id', 'text')}", f"s AS (SELECT o.id AS qid, iso.id AS vid, {d2_sql('o.vec', 'iso.vec')} AS d2 FROM o, iso)", "SELECT * FROM (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY d2, vid)::INT AS rank, vid, round(d2, 6) AS d2 FROM s) WHERE rank <= 10"))
def ood_search(spark, d):
    return exact.exact_knn(sets.text(spark, d), sets.ood(spark, d), TOP, own=True).select("qid", "rank", "vid", r6("d2"))


@query(sql(ISO, Q, FULL, "SELECT * FROM (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY d, vid)::INT AS rank, vid, round(d, 6) AS d2 FROM dist JOIN embeddings e ON e.vec_id = vid WHERE vid <> qid AND e.label <> 0) WHERE rank <= 10"))
def fresh_insert_delete(spark, d):
    """Rows of label nine arrive later, those of label zero are deleted; the large index is exact here, so the answer is too."""
    labels = sets.table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), "label")
    base = sets.iso(spark, d)
    rows = base.join(labels, "id")
    old, new = rows.where("label <> 9").select("id", "vec"), rows.where("label = 9").select("id", "vec")
    gone = labels.where("label = 0").select(F.col("id").alias("vid"))
    build = lambda b: lambda q, k: exact.exact_knn(b, q, k)
    empty = spark.createDataFrame([], "vid long")
    index = FreshIndex(old, build(old), old.limit(0), empty, build).insert(new).delete(gone)
    return index.search(sets.queries_of(base), TOP, slack=old.count()).select("qid", "rank", "vid", r6("d2"))


@query(sql(ISO, Q, FULL, "SELECT * FROM (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY d, vid)::INT AS rank, vid, round(d, 6) AS d2 FROM dist JOIN embeddings e ON e.vec_id = vid WHERE vid <> qid AND e.label <> 0) WHERE rank <= 10"))
def fresh_merge(spark, d):
    """The same after a merge of delta and deletes."""
    labels = sets.table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), "label")
    base = sets.iso(spark, d)
    rows = base.join(labels, "id")
    old, new = rows.where("label <> 9").select("id", "vec"), rows.where("label = 9").select("id", "vec")
    build = lambda b: lambda q, k: exact.exact_knn(b, q, k)
    index = FreshIndex(old, build(old), old.limit(0), spark.createDataFrame([], "vid long"), build)
    merged = index.insert(new).delete(labels.where("label = 0").select(F.col("id").alias("vid"))).merge()
    return merged.search(sets.queries_of(base), TOP, slack=0).select("qid", "rank", "vid", r6("d2"))


# ---- measures ----


def _code_only(s: Setting):
    return materialize(beam_search(s.index(vectors=False), s.queries, H, TOP, "code_only", s.model))


@query(sql(*CODE_WALK, BEAM_RESULT, TRUE_DIST, TTRUTH, "SELECT truth.qid, round(count(ranked.vid) / 10, 6) AS recall FROM truth LEFT JOIN ranked ON ranked.qid = truth.qid AND ranked.vid = truth.vid AND ranked.rank <= 10 GROUP BY truth.qid"))
def recall_at_k(spark, d):
    s = Setting(spark, d)
    return measures.recall(_code_only(s), exact.exact_knn(s.base, s.queries, TOP), TOP).select("qid", r6("recall"))


@query(sql(*CODE_WALK, "SELECT count(*) AS queries, min(hops)::BIGINT AS least, max(hops)::BIGINT AS most, round(avg(hops), 6) AS mean FROM ended"))
def hops(spark, d):
    per = _code_only(Setting(spark, d)).groupBy("qid").agg(F.max("hops").alias("hops"))
    return per.agg(F.count("*").alias("queries"), F.min("hops").alias("least"), F.max("hops").alias("most"), F.round(F.avg("hops"), 6).alias("mean"))


@query(sql(*CODE_WALK, "SELECT qid, hops::BIGINT AS reads, hops::BIGINT AS blocks, hops::BIGINT * 4096 AS bytes, round(hops * 100e-6 + hops * 4096 / 2e9, 9) AS io_s FROM ended"))
def block_reads(spark, d):
    s = Setting(spark, d)
    found = beam_search(s.index(vectors=True), s.queries, H, TOP, "disk_tier", s.model)
    return measures.block_reads(found, 64 * 4).select("qid", "reads", "blocks", "bytes", F.round("io_s", 9).alias("io_s"))


@query(sql(ISO, Q, BOOK, CODES, LUT, ADC, TRUE_DIST, TTRUTH, "SELECT count(*) AS pairs, round(sum(dist.d), 6) AS objective FROM truth JOIN dist ON dist.qid = truth.qid AND dist.vid = truth.vid"))
def result_objective(spark, d):
    s = Setting(spark, d)
    got = measures.result_objective(exact.exact_knn(s.base, s.queries, TOP), s.codes(), quantize.build_lut(s.queries, s.model))
    return got.select("pairs", r6("objective"))


@query(sql(ISO, Q, TRUE_DIST, TTRUTH, "SELECT qid, round(-1.0 / avg(0.5 * ln(d2 / far)), 6) AS lid FROM (SELECT qid, d2, max(d2) OVER (PARTITION BY qid) AS far FROM truth) WHERE d2 > 0 GROUP BY qid"))
def lid(spark, d):
    """Of equally far neighbours there is no estimate; SQL's quotient is minus infinity there."""
    base = sets.iso(spark, d)
    found = measures.lid(exact.exact_knn(base, sets.queries_of(base), TOP))
    return found.select("qid", F.round(F.coalesce("lid", F.lit(float("-inf"))), 6).alias("lid"))


@query("""WITH s AS (SELECT count(*) AS n, max(len(embedding)) AS d FROM embeddings),
b AS (SELECT setting, n, d, floor(f * n * (4 * d + 4 * 22))::BIGINT AS bytes FROM s, (VALUES ('a 32nd', 0.03125::DOUBLE), ('a half', 0.5)) t(setting, f))
SELECT setting, bytes, greatest(0, (bytes - 4 * 256 * d) // n)::INT AS chunks FROM b""")
def memory_budget(spark, d):
    """A 32nd and a half of the table's vectors and a graph of 22 four-byte links per vertex, and the one-byte chunks that it leaves."""
    s = sets.iso(spark, d).agg(F.count("*").alias("n"), F.max(F.size("vec")).alias("d")).first()
    rows = [(name, *measures.plan_budget(s.n, s.d, 22, f)) for name, f in (("a 32nd", 1 / 32), ("a half", 1 / 2))]
    return spark.createDataFrame(rows, "setting string, bytes long, chunks int")


@query("SELECT kind, dims, (4 * (CASE kind WHEN 'rotated' THEN dims * (dims - 1) // 2 ELSE 0 END + k * dims))::INT AS bytes FROM (SELECT max(len(embedding))::INT AS dims FROM embeddings), (VALUES ('rotated', 256), ('plain', 256), ('seeded', 16)) t(kind, k)")
def model_bytes(spark, d):
    """Models of the table's vectors: with and without a rotation at 256 codewords, and the frozen one of the other queries."""
    import numpy as np

    base = sets.iso(spark, d)
    n, seeded = base.agg(F.max(F.size("vec"))).first()[0], quantize.seeded_books(base, M, K)
    models = {kind: quantize.Quantizer("m", np.zeros((16, 256, n // 16)), np.eye(n) if kind == "rotated" else None) for kind in ("rotated", "plain")} | {"seeded": seeded}
    return spark.createDataFrame([(kind, n, q.model_bytes()) for kind, q in models.items()], "kind string, dims int, bytes int")


@query(sql(*CODE_WALK, TRUE_DIST, "tr AS MATERIALIZED (SELECT qid, step, beam, visited, nxt FROM w WHERE step > 0 AND nxt IS NOT NULL)", "op AS MATERIALIZED (SELECT qid, step, nxt, unnest(list_filter(beam, lambda c: NOT list_contains(visited, c.vid))).vid AS vid FROM tr)", "best AS (SELECT op.qid, step, nxt, arg_min(op.vid, {'d': t.d, 'v': op.vid}) AS label FROM op JOIN tdist t ON t.qid = op.qid AND t.vid = op.vid GROUP BY ALL)", "SELECT count(*) AS steps, round(avg((label = nxt)::INT), 6) AS accuracy FROM best"))
def hop_accuracy(spark, d):
    from vecgraph.operators import features as X

    s = Setting(spark, d)
    t = materialize(X.routing_traces(s.index(vectors=False), s.queries, s.model, H))
    label = X.label_traces(t, s.base, s.queries, "exact")
    return t.where("next_vid is not null").join(label, ["qid", "step"]).agg(F.count("*").alias("steps"), F.round(F.avg((F.col("label") == F.col("next_vid")).cast("int")), 6).alias("accuracy"))
