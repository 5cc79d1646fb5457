"""The functions registered for SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from vecgraph.functions import udfs
from vecgraph.operators import quantize

from .common import ADC, BEAM_RESULT, BOOK, CODES, ENTRY, GRAPH, ISO, LUT, TOP, H, Q, Setting, beam, query, sql


def _view(spark, d) -> tuple[Setting, str]:
    s = Setting(spark, d)
    udfs.register(spark, s.model)
    name = f"vectors_{uuid.uuid4().hex}"
    s.base.createOrReplaceTempView(name)
    return s, name


@query(sql(ISO, BOOK, CODES, "SELECT vid, array_to_string(code, ',') AS code FROM codes"))
def udf_pq_encode(spark, d):
    _, v = _view(spark, d)
    return spark.sql(f"SELECT id AS vid, array_join(pq_encode(vec), ',') AS code FROM {v}")


@query("SELECT e.label, round(list_sum(list(m ORDER BY i)), 6) AS total FROM (SELECT label, i, avg(embedding[i]::DOUBLE) AS m FROM embeddings, range(1, 65) t(i) GROUP BY label, i) e GROUP BY e.label")
def udaf_vector_mean(spark, d):
    _, v = _view(spark, d)
    labels = spark.read.parquet(f"{d}/embeddings.parquet").select(F.col("vec_id").alias("id"), "label")
    labels.createOrReplaceTempView(f"{v}_labels")
    return spark.sql(f"SELECT label, round(aggregate(vector_mean(vec), 0D, (a, x) -> a + x), 6) AS total FROM {v} JOIN {v}_labels USING (id) GROUP BY label")


@query(sql(ISO, "SELECT id, j::INT AS chunk, round(list_sum(vec[j * 8 + 1:(j + 1) * 8]), 6) AS total FROM iso, range(8) t(j)"))
def udtf_subvectors(spark, d):
    _, v = _view(spark, d)
    return spark.sql(f"SELECT id, chunk, round(aggregate(sub, 0D, (a, x) -> a + x), 6) AS total FROM {v}, LATERAL subvectors(vec, 8)")


@query(sql(ISO, "q AS (SELECT id AS qid, vec AS qvec FROM iso WHERE id % 50 = 0)", BOOK, CODES, "lut AS (SELECT qid, list(row ORDER BY j) AS lut FROM (SELECT qid, j, list(d ORDER BY k) AS row FROM (SELECT qid, j, k, list_sum(list_transform(list_zip(qvec[j * 8 + 1:(j + 1) * 8], cw), lambda p: (p[1] - p[2]) * (p[1] - p[2]))) AS d FROM q, book) GROUP BY qid, j) GROUP BY qid)", "SELECT qid, round(list_sum(list_transform(range(8), lambda j: lut[j + 1][code[j + 1] + 1])), 6) AS own FROM lut JOIN codes ON vid = qid"))
def udf_adc_distance(spark, d):
    s, v = _view(spark, d)
    quantize.build_lut(s.queries, s.model).join(s.codes(), F.col("qid") == F.col("vid")).createOrReplaceTempView(f"{v}_luts")
    return spark.sql(f"SELECT qid, round(adc_distance(lut, code), 6) AS own FROM {v}_luts")


@query(sql(ISO, GRAPH, "n AS (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY dst) - 1 AS place FROM graph)", "SELECT src AS vid, place::INT AS place, dst FROM n"))
def udtf_expand_neighbours(spark, d):
    s, v = _view(spark, d)
    s.edges().groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("nbrs")).createOrReplaceTempView(f"{v}_links")
    return spark.sql(f"SELECT src AS vid, place, dst FROM {v}_links, LATERAL expand_neighbours(nbrs)")


@query(sql(ISO, Q, BOOK, CODES, LUT, ADC, GRAPH, ENTRY, beam(), BEAM_RESULT, "SELECT qid, rank, vid, round(d2, 6) AS d2, hops FROM ranked WHERE rank <= 10"))
def udtf_ann_search(spark, d):
    s, v = _view(spark, d)
    udfs.register_search(spark, s.index(vectors=False), s.model)
    s.queries.createOrReplaceTempView(f"{v}_queries")
    return spark.sql(f"SELECT id AS qid, rank, vid, round(d2, 6) AS d2, hops FROM {v}_queries, LATERAL ann_search(id, vec, {TOP}, {H})")
