"""Sets, distances, exact neighbours and graphs defined by distance."""

from __future__ import annotations

from pyspark.sql import functions as F

from vecgraph.functions.columns import chunk, dot
from vecgraph.operators import exact, graphs
from vecgraph.sources import sets

from .common import ENTRY, FULL, GRAPH, ISO, KNN, M, NEAR, SKEW, TEXT, TOP, TRUTH, Q, Setting, d2, hashed, query, r6, sql
from .common import dot as dot_sql

THETA = 1.2


@query(sql(ISO, f"SELECT id, round(sqrt({dot_sql('vec', 'vec')}), 6) AS norm, len(vec) AS dims FROM iso"))
def vec_norms(spark, d):
    return sets.iso(spark, d).select("id", F.round(F.sqrt(dot(F.col("vec"), F.col("vec"))), 6).alias("norm"), F.size("vec").cast("long").alias("dims"))


@query(sql(SKEW, "SELECT id, j::INT AS chunk, round(list_sum(vec[j * 8 + 1:(j + 1) * 8]), 6) AS total FROM iso, range(8) t(j)"))
def vec_split(spark, d):
    v = sets.skew(spark, d)
    parts = F.posexplode(F.array(*[F.aggregate(chunk(F.col("vec"), j, 8), F.lit(0.0), lambda a, x: a + x) for j in range(M)]))
    return v.select("id", parts.alias("chunk", "total")).select("id", "chunk", r6("total"))


@query(sql(ISO, Q, FULL, "SELECT qid, vid, round(d, 6) AS d2 FROM dist WHERE vid <> qid"))
def vec_d2_pairs(spark, d):
    base = sets.iso(spark, d)
    got = exact.in_cells(base, sets.queries_of(base), lambda i, x: exact.Within(i, x, float("inf")), "src long, dst long, d2 double")
    return got.select(F.col("src").alias("qid"), F.col("dst").alias("vid"), r6("d2"))


@query(sql(ISO, ENTRY, "SELECT vid, round(d2, 6) AS d2 FROM entry"))
def vec_mean_medoid(spark, d):
    return exact.medoid(sets.iso(spark, d)).select("vid", r6("d2"))


for _name, _set in (("iso", ISO), ("skew", SKEW), ("text", TEXT)):

    def _knn(spark, d, name=_name):
        base = sets.SETS[name](spark, d)
        return exact.exact_knn(base, sets.queries_of(base), TOP).select("qid", "rank", "vid", r6("d2"))

    _knn.__name__ = f"exact_knn_{_name}"
    query(sql(_set, Q, FULL, TRUTH, "SELECT qid, rank, vid, round(d2, 6) AS d2 FROM truth"))(_knn)


@query(f"WITH RECURSIVE v AS MATERIALIZED {hashed('pages', 'page_id', 'html_text')} SELECT id, round(list_sum(vec), 6) AS total, len(vec) AS dims FROM v".replace("FROM pages WHERE html_text", "FROM (SELECT page_id, regexp_replace(html, '<[^>]*>', ' ', 'g') AS html_text FROM pages) WHERE html_text"))
def vec_page(spark, d):
    return sets.page(spark, d).select("id", F.round(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x), 6).alias("total"), F.size("vec").cast("long").alias("dims"))


@query("""
WITH o AS (SELECT l_orderkey, count(*) AS n, sum(l_quantity) AS q, max(l_extendedprice) AS p FROM lineitem GROUP BY 1),
c AS (SELECT o_custkey AS id, count(*) AS orders, sum(n) AS items, sum(q) AS quantity, max(p) AS price FROM orders JOIN o ON o_orderkey = l_orderkey GROUP BY 1),
e AS (SELECT min(orders) AS a0, max(orders) AS a1, min(items) AS b0, max(items) AS b1, min(quantity) AS c0, max(quantity) AS c1, min(price) AS d0, max(price) AS d1 FROM c)
SELECT id, round((orders - a0) / (a1 - a0), 6) AS orders, round((items - b0) / (b1 - b0), 6) AS items, round((quantity - c0) / (c1 - c0), 6) AS quantity, round((price - d0) / (d1 - d0), 6) AS price FROM c, e
""")
def vec_profile(spark, d):
    v = sets.profile(spark, d)
    at = lambda i, n: F.round(F.get("vec", F.lit(i)), 6).alias(n)
    return v.select("id", at(0, "orders"), at(1, "items"), at(6, "quantity"), at(9, "price"))


@query("""SELECT count(*) AS n, round(avg(l_quantity / 50), 6) AS quantity, round(avg(l_extendedprice / 1e5), 6) AS price, round(avg(month(l_shipdate) / 12.0), 6) AS shipped FROM lineitem""")
def vec_rowvec(spark, d):
    at = lambda i: F.avg(F.get("vec", F.lit(i)))
    return sets.rowvec(spark, d).agg(F.count("*").alias("n"), F.round(at(0), 6).alias("quantity"), F.round(at(1), 6).alias("price"), F.round(at(4), 6).alias("shipped"))


@query(sql(ISO, Q, FULL, TRUTH, "SELECT qid, bool_and(sqrt(d2) <= 1.1 * sqrt(d2)) AS ok FROM truth GROUP BY qid"))
def eps_guarantee(spark, d):
    base = sets.iso(spark, d)
    truth = exact.exact_knn(base, sets.queries_of(base), TOP)
    return exact.eps_check(truth, truth, 0.1)


THRESHOLD = sql(ISO, f"SELECT src, dst, round(d2, 6) AS d2 FROM (SELECT a.id AS src, b.id AS dst, {d2('a.vec', 'b.vec')} AS d2 FROM iso a JOIN iso b ON a.id <> b.id) WHERE d2 <= {THETA}")


@query(THRESHOLD)
def threshold_graph(spark, d):
    return exact.threshold_graph(sets.iso(spark, d), THETA).select("src", "dst", r6("d2"))


@query(THRESHOLD)
def threshold_graph_cells(spark, d):
    return exact.threshold_graph_cells(sets.iso(spark, d), THETA).select("src", "dst", r6("d2"))


@query(sql(ISO, KNN, "SELECT src, dst, round(d2, 6) AS d2 FROM knn"))
def knn_graph(spark, d):
    return exact.knn_graph(sets.iso(spark, d), NEAR).select("src", "dst", r6("d2"))


@query(sql(ISO, GRAPH, "SELECT src, dst, round(d2, 6) AS d2 FROM graph"))
def sym_knn_graph(spark, d):
    return exact.sym_knn_graph(sets.iso(spark, d), NEAR).select("src", "dst", r6("d2"))


@query(sql(ISO, GRAPH, "SELECT count(*) AS vertices, sum(deg)::BIGINT AS edges, min(deg) AS min_deg, max(deg) AS max_deg, round(avg(deg), 6) AS avg_deg FROM (SELECT src, count(*) AS deg FROM graph GROUP BY src)"))
def graph_degree_stats(spark, d):
    return graphs.graph_stats(Setting(spark, d).edges())


@query(sql(ISO, GRAPH, ENTRY, "r AS (SELECT vid, 0 AS hops FROM entry UNION SELECT g.dst, hops + 1 FROM r JOIN graph g ON g.src = r.vid WHERE hops < 12)", "SELECT vid, min(hops)::INT AS hops FROM r GROUP BY vid"))
def graph_reachability(spark, d):
    s = Setting(spark, d)
    return graphs.reachable(s.edges(), graphs.entry_vertex(s.base))


@query(sql(ISO, GRAPH, "v AS (SELECT DISTINCT src AS vid FROM graph)", "SELECT count(id) AS n_vectors, count(vid) AS n_vertices, count(*) FILTER (vid IS NULL) AS missing, count(*) FILTER (id IS NULL) AS extra FROM iso FULL JOIN v ON iso.id = v.vid"))
def bijection_check(spark, d):
    s = Setting(spark, d)
    return exact.bijection_check(s.base, s.edges())
