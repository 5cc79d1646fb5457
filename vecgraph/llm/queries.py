"""The thin queries of this subpackage: each operator, with production parameters, over its whole table."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, decontaminate, fmindex, langid, linededup, secrets, simhash, suffixarray, topk, urlfilter
from .common import table

#: The public tokenizer's file; a parameter, nothing is copied.
VOCABULARY = public_tokenizers.path("word_bpe_49k.json")

# fixed values: the contract's rules (host, path, verdict)
URL_RULES = [("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block")]


def op1_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    rules = spark.createDataFrame(URL_RULES, "host string, path string, verdict string")
    return urlfilter.url_filter(table(spark, sf_dir, "pages"), rules)


OP1_SQL = r"""
WITH u AS (
  SELECT page_id,
         translate(coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         coalesce(regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1), '') AS path
  FROM pages),
r(rhost, rpath, verdict) AS (VALUES ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'), ('net', '/es/', 'block'), ('net', '/fr/', 'block')),
best AS (
  SELECT host, path, max_by(struct_pack(rule := rhost || rpath, verdict := verdict), length(rhost || rpath) * 1000 + length(rhost)) AS b
  FROM (SELECT DISTINCT host, path FROM u) p JOIN r
    ON (p.host = r.rhost OR ends_with(p.host, '.' || r.rhost)) AND starts_with(p.path, r.rpath)
  GROUP BY host, path)
SELECT u.page_id, u.host, u.path, best.b.rule AS rule, coalesce(best.b.verdict, 'allow') AS verdict
FROM u LEFT JOIN best ON u.host = best.host AND u.path = best.path
"""


def op2_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secret_digest(table(spark, sf_dir, "documents"))


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linededup.dedup_digest(table(spark, sf_dir, "documents"))


OP3_SQL = r"""
WITH l AS (
  SELECT doc_id, source, pos, line, trim(line, ' ') AS key
  FROM (SELECT doc_id, source, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS pos FROM documents)),
b AS (
  SELECT key, min(doc_id) AS first FROM l WHERE length(key) >= 16
  GROUP BY key HAVING count(DISTINCT coalesce('s' || source, '')) >= 10),
j AS (
  SELECT l.doc_id, l.pos, l.line,
         b.key IS NOT NULL AND NOT (b.first = l.doc_id AND row_number() OVER (PARTITION BY l.doc_id, l.key ORDER BY l.pos) = 1) AS cut
  FROM l LEFT JOIN b ON l.key = b.key),
a AS (
  SELECT doc_id, count(*) AS n_lines, count(*) FILTER (cut) AS n_cut,
         coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT cut), '') AS kept
  FROM j GROUP BY doc_id)
SELECT d.doc_id, coalesce(a.n_lines, 0) AS n_lines, coalesce(a.n_cut, 0) AS n_cut, sha256(coalesce(a.kept, '')) AS kept_sha256
FROM documents d LEFT JOIN a ON d.doc_id = a.doc_id
"""


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = langid.fit(docs.where(~langid.held_out(F.col("doc_id"))))
    found = langid.predict(docs.select("doc_id", "text"), model)
    return found.select("doc_id", langid.held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


def op5_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = topk.integer_vectors(table(spark, sf_dir, "embeddings"))
    return topk.exact_topk(vectors, vectors.where(F.col("vec_id") % 50 == 0), k=5)


OP5_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(x::DOUBLE * 256)::BIGINT) AS vec FROM embeddings
  WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (
  SELECT q.vec_id AS query_id, c.vec_id, list_sum(list_transform(list_zip(q.vec, c.vec), lambda p: p[1] * p[2]))::BIGINT AS score
  FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id AND len(q.vec) = len(c.vec)),
r AS (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INT AS rank, vec_id, score FROM s)
SELECT * FROM r WHERE rank <= 5
"""


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"), shingle=4, distance=4)


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contamination_digest(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


OP7_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT row_number() OVER () AS item, item_id::VARCHAR AS item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
s AS (SELECT item, item_id, least(10, len(w)) AS n, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS i, w FROM b WHERE len(w) > 0),
win AS (SELECT DISTINCT item, item_id, n, array_to_string(w[i:i + n - 1], ' ') AS t FROM s),
sizes AS (SELECT DISTINCT n FROM win),
p AS (SELECT d.r, sizes.n, unnest(range(1, len(d.w) - sizes.n + 2)) AS i, d.w FROM d, sizes WHERE len(d.w) >= sizes.n),
dw AS (SELECT r, n, i, array_to_string(w[i:i + n - 1], ' ') AS t FROM p),
hit AS (SELECT dw.r, dw.i, dw.n, win.item, win.item_id FROM dw JOIN win ON win.n = dw.n AND win.t = dw.t),
pos AS (SELECT r, count(*) AS n FROM (SELECT DISTINCT r, unnest(range(i, i + n)) AS pos FROM hit) GROUP BY r),
its AS (SELECT r, count(*) AS n, string_agg(item_id, ',' ORDER BY item_id) AS ids FROM (SELECT DISTINCT r, item, item_id FROM hit) GROUP BY r)
SELECT d.doc_id, len(d.w) AS n_words, coalesce(pos.n, 0) AS n_hit, coalesce(its.n, 0) AS n_items, sha256(coalesce(its.ids, '')) AS items_sha256, coalesce(pos.n, 0) > 0 AS contaminated
FROM d LEFT JOIN pos ON pos.r = d.r LEFT JOIN its ON its.r = d.r
"""


def op8_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_digest(table(spark, sf_dir, "documents"), VOCABULARY)


def op9_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixarray.kept_digest(table(spark, sf_dir, "documents"), window=400)


OP9_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, hex(encode(coalesce(text, ''))) AS x FROM documents),
b AS (SELECT r, b, substring(x, 2 * b + 1, 1798) AS y FROM (SELECT r, x, unnest(range(0, length(x) // 2 - 399, 500)) AS b FROM d WHERE length(x) >= 800)),
n AS (SELECT r, b, y, unnest(range(0, least(500, length(y) // 2 - 399))) AS j FROM b),
h AS (SELECT r, b + j AS i, hash(substring(y, 2 * j + 1, 800)) AS h FROM n),
rep AS (SELECT r, i FROM h WHERE h IN (SELECT h FROM h GROUP BY h HAVING count(*) > 1)),
e AS (SELECT r, i, i > 400 + lag(i) OVER w AS new FROM rep WINDOW w AS (PARTITION BY r ORDER BY i)),
g AS (SELECT r, i, sum(coalesce(new, true)::INT) OVER (PARTITION BY r ORDER BY i) AS run FROM e),
runs AS (SELECT r, run, min(i) AS lo, max(i) + 400 AS hi FROM g GROUP BY r, run),
parts AS (SELECT r, lo, lag(hi, 1, 0) OVER (PARTITION BY r ORDER BY lo) AS before, hi FROM runs),
k AS (SELECT parts.r, count(*) AS spans, sum(hi - lo) AS removed, max(hi) AS last, string_agg(x[2 * before + 1:2 * lo], '' ORDER BY lo) AS kept FROM parts JOIN d ON d.r = parts.r GROUP BY parts.r)
SELECT d.doc_id, length(x) // 2 AS n_bytes, coalesce(removed, 0)::BIGINT AS n_removed, coalesce(spans, 0) AS n_spans,
       sha256(unhex(CASE WHEN k.r IS NULL THEN x ELSE coalesce(kept, '') || x[2 * last + 1:] END)) AS kept_sha256
FROM d LEFT JOIN k ON k.r = d.r
"""


def op10_fm_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fmindex.kept_digest(table(spark, sf_dir, "documents"), window=35)


OP10_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w FROM documents),
n AS (SELECT r, unnest(range(1, len(w) - 33)) AS i FROM d WHERE len(w) >= 35),
h AS (SELECT n.r, n.i, md5(array_to_string(d.w[n.i:n.i + 34], ' ')) AS h FROM n JOIN d ON d.r = n.r),
rep AS (SELECT r, i FROM h WHERE h IN (SELECT h FROM h GROUP BY h HAVING count(*) > 1)),
gone AS (SELECT DISTINCT r, unnest(range(i, i + 35)) AS pos FROM rep),
words AS (SELECT r, unnest(w) AS word, generate_subscripts(w, 1) AS pos FROM d),
kept AS (SELECT words.r, string_agg(word, ' ' ORDER BY words.pos) AS t FROM words LEFT JOIN gone ON gone.r = words.r AND gone.pos = words.pos WHERE gone.r IS NULL GROUP BY words.r),
c AS (SELECT r, count(*) AS n FROM gone GROUP BY r)
SELECT d.doc_id, len(d.w) AS n_words, coalesce(c.n, 0) AS n_removed, sha256(coalesce(kept.t, '')) AS kept_sha256
FROM d LEFT JOIN c ON c.r = d.r LEFT JOIN kept ON kept.r = d.r
"""


def secret_base_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What SQL can express of op2: how many base spans of each kind its digest counts."""
    return op2_secret_scan(spark, sf_dir).select("doc_id", "n_assign", "n_access", "n_hex")


SECRET_BASE_SQL = r"""
SELECT doc_id, len(list_filter(regexp_extract_all(t, '(?i:password|passwd|secret|token|api_?key)["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)', 1), lambda x: length(x) >= 6)) AS n_assign,
       len(list_filter(regexp_extract_all(t, 'AKIA[A-Z0-9]+'), lambda x: length(x) >= 20)) AS n_access,
       len(list_filter(regexp_extract_all(t, '[0-9a-f]+'), lambda x: length(x) >= 24)) AS n_hex
FROM (SELECT doc_id, coalesce(text, '') AS t FROM documents)
"""


def decontamination_near(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op7's other matches: the benchmark items whose rarest terms stand within ten words of each other."""
    found = decontaminate.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), slop=10)
    return found.select("doc_id", F.size("near").cast("long").alias("n_near"), F.size("items").cast("long").alias("n_items"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_url_filter": op1_url_filter,
    "op2_secret_scan": op2_secret_scan,
    "op3_line_dedup": op3_line_dedup,
    "op4_language_id": op4_language_id,
    "op5_exact_topk": op5_exact_topk,
    "op6_simhash": op6_simhash,
    "op7_decontamination": op7_decontamination,
    "op8_bpe": op8_bpe,
    "op9_suffix_array": op9_suffix_array,
    "op10_fm_index": op10_fm_index,
    "secret_base_counts": secret_base_counts,
    "decontamination_near": decontamination_near,
}
ORACLES: dict[str, str] = {"op1_url_filter": OP1_SQL, "op3_line_dedup": OP3_SQL, "op5_exact_topk": OP5_SQL, "op7_decontamination": OP7_SQL, "op9_suffix_array": OP9_SQL, "op10_fm_index": OP10_SQL, "secret_base_counts": SECRET_BASE_SQL}
