"""Codes, lookup tables, their errors, rotations, soft codes and the rank identities."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from vecgraph.functions.columns import d2, dot, softmax, unit_uniform
from vecgraph.operators import exact, quantize, rotation
from vecgraph.operators.walk import search_flat
from vecgraph.sources import sets

from .common import ADC, BOOK, CODES, ISO, LUT, SKEW, TOP, TRUE_DIST, K, M, Q, Setting, query, r6, sql
from .common import d2 as d2_sql
from .common import dot as dot_sql

CODE_TEXT = "array_to_string(code, ',') AS code"


@query(sql(ISO, BOOK, CODES, f"SELECT vid, {CODE_TEXT} FROM codes"))
def pq_encode_seeded(spark, d):
    return Setting(spark, d).codes().select("vid", F.array_join("code", ",").alias("code"))


DECODED = "dec AS MATERIALIZED (SELECT vid, flatten(list(cw ORDER BY book.j)) AS dvec FROM (SELECT vid, unnest(code) AS k, generate_subscripts(code, 1) - 1 AS j FROM codes) c JOIN book ON book.j = c.j AND book.k = c.k GROUP BY vid)"


@query(sql(ISO, BOOK, CODES, DECODED, "SELECT vid, len(dvec) AS dims, round(list_sum(dvec), 6) AS total FROM dec"))
def pq_decode_seeded(spark, d):
    s = Setting(spark, d)
    return quantize.decode(s.codes(), s.model).select("vid", F.size("vec").cast("long").alias("dims"), F.round(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x), 6).alias("total"))


def _lloyd_sql() -> str:
    parts = [ISO, BOOK.replace("book AS", "b0 AS")]
    for i in range(2):
        parts.append(f"n{i} AS MATERIALIZED (SELECT id, j, k, sub FROM (SELECT id, j, k, sub, row_number() OVER (PARTITION BY id, j ORDER BY d, k) AS r FROM (SELECT id, j, k, vec[j * 8 + 1:(j + 1) * 8] AS sub, {d2_sql('vec[j * 8 + 1:(j + 1) * 8]', 'cw')} AS d FROM iso, b{i})) WHERE r = 1)")
        parts.append(f"m{i} AS MATERIALIZED (SELECT j, k, list(x ORDER BY i) AS cw FROM (SELECT j, k, i, avg(sub[i]) AS x FROM n{i}, range(1, 9) t(i) GROUP BY j, k, i) GROUP BY j, k)")
        parts.append(f"b{i + 1} AS MATERIALIZED (SELECT b{i}.j, b{i}.k, coalesce(m{i}.cw, b{i}.cw) AS cw FROM b{i} LEFT JOIN m{i} ON m{i}.j = b{i}.j AND m{i}.k = b{i}.k)")
    return sql(*parts, "SELECT j::INT AS chunk, k::INT AS k, round(list_sum(cw), 6) AS total FROM b2")


@query(_lloyd_sql())
def pq_lloyd_2iter(spark, d):
    s = Setting(spark, d)
    q, _ = quantize.lloyd(s.base, s.model, 2, tolerance=-1)
    rows = [(j, k, round(float(q.books[j, k].sum()), 6)) for j in range(q.m) for k in range(q.k)]
    return spark.createDataFrame(rows, "chunk int, k int, total double")


@query(sql(ISO, BOOK, CODES, DECODED, f"SELECT round(avg({d2_sql('vec', 'dvec')}), 6) AS distortion FROM iso JOIN dec ON dec.vid = iso.id"))
def pq_distortion(spark, d):
    s = Setting(spark, d)
    return spark.createDataFrame([(round(quantize.distortion(s.base, s.model), 6),)], "distortion double")


@query("SELECT dims, m, k, (m * ceil(log2(k)))::INT AS code_bits, 4 * dims AS vector_bytes FROM (SELECT max(len(embedding))::INT AS dims FROM embeddings), (VALUES (2, 8), (16, 256), (8, 16)) t(m, k)")
def code_size(spark, d):
    """Bits of a code beside the bytes of a vector, of the table's vectors and three shapes of books."""
    n = sets.iso(spark, d).agg(F.max(F.size("vec"))).first()[0]
    return spark.createDataFrame([(n, m, k, quantize.code_bits(m, k), 4 * n) for m, k in ((2, 8), (16, 256), (8, 16))], "dims int, m int, k int, code_bits int, vector_bytes int")


WORKED = (
    "book AS MATERIALIZED (SELECT j, row_number() OVER (PARTITION BY j ORDER BY id) - 1 AS k, vec[j * 32 + 1:(j + 1) * 32] AS cw FROM (SELECT * FROM iso ORDER BY id LIMIT 8), range(2) t(j))",
    "two AS MATERIALIZED (SELECT vec, row_number() OVER (ORDER BY id DESC) AS place FROM iso ORDER BY id DESC LIMIT 2)",
    f"near AS (SELECT j, k, cw, row_number() OVER (PARTITION BY j ORDER BY {d2_sql('vec[j * 32 + 1:(j + 1) * 32]', 'cw')}, k) AS r FROM two, book WHERE place = 1)",
    f"SELECT 6 AS bits, string_agg(k::VARCHAR, ',' ORDER BY j) AS code, round(sum({d2_sql('vec[j * 32 + 1:(j + 1) * 32]', 'cw')}), 6) AS adc FROM near, two WHERE r = 1 AND place = 2",
)


@query(sql(ISO, *WORKED))
def worked_example(spark, d):
    """A worked example on the table: two chunks of eight codewords (of the eight smallest ids), the code of the vector with the
    largest id, and its distance from the one before it by the lookup table."""
    base = sets.iso(spark, d)
    q = quantize.seeded_books(base, 2, 8)
    x, asked = (np.array([r.vec]) for r in base.orderBy(F.desc("id")).limit(2).collect())
    code = q.encode(x)
    dist = float(quantize.adc(q.lut(asked), code)[0, 0])
    return spark.createDataFrame([(quantize.code_bits(2, 8), ",".join(map(str, code[0])), round(dist, 6))], "bits int, code string, adc double")


@query(sql(ISO, Q, BOOK, LUT, "SELECT qid, j::INT AS chunk, round(list_sum(lut[j + 1]), 6) AS total, round(list_min(lut[j + 1]), 6) AS least FROM lut, range(8) t(j)"))
def lut(spark, d):
    s = Setting(spark, d)
    rows = quantize.build_lut(s.queries, s.model).select("qid", F.posexplode("lut").alias("chunk", "row"))
    return rows.select("qid", "chunk", F.round(F.aggregate("row", F.lit(0.0), lambda a, x: a + x), 6).alias("total"), F.round(F.array_min("row"), 6).alias("least"))


ADC_TOP = "SELECT * FROM (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY d, vid)::INT AS rank, vid, round(d, 6) AS d2 FROM dist WHERE vid <> qid) WHERE rank <= 10"


def _coded(s: Setting, symmetric: bool):
    """Every query against all codes, in cells: the TOP nearest by table sums."""
    model, table = s.model, quantize.sdc_tables(s.model)

    class Coded(exact.Nearest):
        def close(self, ids, x):
            code = model.encode(x)
            d = quantize.sdc(table, model.encode(self.x), code) if symmetric else quantize.adc(model.lut(self.x), code)
            q, r = np.nonzero((d <= self.d[:, -1:]) & (self.ids[:, None] != ids[None]))
            return q, r, d[q, r]

    near = exact.in_cells(s.base, s.queries, lambda i, x: Coded(i, x, TOP, False), "qid long, vid long, d2 double")
    return exact.top(near, TOP).select("qid", "rank", "vid", r6("d2"))


@query(sql(ISO, Q, BOOK, CODES, LUT, ADC, ADC_TOP))
def adc_topk(spark, d):
    return _coded(Setting(spark, d), False)


SDC = f"""sd AS MATERIALIZED (SELECT a.j, a.k AS ka, b.k AS kb, {d2_sql('a.cw', 'b.cw')} AS d FROM book a JOIN book b ON a.j = b.j),
sdl AS MATERIALIZED (SELECT list(rows ORDER BY j) AS t FROM (SELECT j, list(row ORDER BY ka) AS rows FROM (SELECT j, ka, list(d ORDER BY kb) AS row FROM sd GROUP BY j, ka) GROUP BY j)),
dist AS MATERIALIZED (SELECT q.qid, c.vid, list_sum(list_transform(range(8), lambda j: t[j + 1][qc.code[j + 1] + 1][c.code[j + 1] + 1])) AS d FROM q JOIN codes qc ON qc.vid = q.qid, codes c, sdl)"""


@query(sql(ISO, Q, BOOK, CODES, SDC, ADC_TOP))
def sdc_topk(spark, d):
    return _coded(Setting(spark, d), True)


ERROR = "SELECT count(*) AS pairs, round(avg(dist.d - tdist.d), 6) AS bias, round(avg(abs(dist.d - tdist.d)), 6) AS abs_error FROM dist JOIN tdist ON dist.qid = tdist.qid AND dist.vid = tdist.vid"


def _errors(s: Setting, symmetric: bool):
    model = s.model
    table = quantize.sdc_tables(model)

    class Errors:
        def __init__(self, ids, x):
            self.x, self.code, self.lut, self.sum = x, model.encode(x), model.lut(x), np.zeros(3)

        def add(self, ids, x):
            c = model.encode(x)
            e = (quantize.sdc(table, self.code, c) if symmetric else quantize.adc(self.lut, c)) - exact.d2_pairs(self.x, x)
            self.sum += [e.size, e.sum(), np.abs(e).sum()]

        def out(self):
            import pyarrow as pa

            yield pa.RecordBatch.from_arrays([pa.array([v]) for v in self.sum], ["n", "e", "a"])

    got = exact.in_cells(s.base, s.queries, Errors, "n double, e double, a double")
    return got.agg(F.sum("n").cast("long").alias("pairs"), F.round(F.sum("e") / F.sum("n"), 6).alias("bias"), F.round(F.sum("a") / F.sum("n"), 6).alias("abs_error"))


@query(sql(ISO, Q, BOOK, CODES, LUT, ADC, TRUE_DIST, ERROR))
def adc_error(spark, d):
    return _errors(Setting(spark, d), False)


@query(sql(ISO, Q, BOOK, CODES, SDC, TRUE_DIST, ERROR))
def sdc_error(spark, d):
    return _errors(Setting(spark, d), True)


@query(sql(ISO, Q, BOOK, CODES, LUT, ADC, TRUE_DIST, f"""
r1 AS (SELECT * FROM (SELECT qid, vid, row_number() OVER (PARTITION BY qid ORDER BY d, vid) AS r FROM dist WHERE vid <> qid) WHERE r <= 50),
r2 AS (SELECT r1.qid, row_number() OVER (PARTITION BY r1.qid ORDER BY tdist.d, r1.vid)::INT AS rank, r1.vid, round(tdist.d, 6) AS d2 FROM r1 JOIN tdist ON tdist.qid = r1.qid AND tdist.vid = r1.vid)""", "SELECT * FROM r2 WHERE rank <= 10"))
def flat_adc_rerank(spark, d):
    s = Setting(spark, d)
    return search_flat(s.base, s.codes(), s.queries, s.model, TOP, 50).select("qid", "rank", "vid", r6("d2"))


@query(sql(SKEW, "SELECT (i - 1)::INT AS dim, round(var_pop(vec[i]), 8) AS value FROM iso, range(1, 65) t(i) GROUP BY i"))
def dim_value(spark, d):
    return sets.skew(spark, d).select(F.posexplode("vec").alias("dim", "x")).groupBy("dim").agg(F.round(F.var_pop("x"), 8).alias("value"))


HAD = f"flatten(list_transform(range(16), lambda b: [{', '.join('(' + ' '.join(f'{s} vec[b * 4 + {i}]' for s, i in zip(signs, range(1, 5), strict=True)) + ') / 2' for signs in ('++++', '+-+-', '++--', '+--+'))}]))"
ROT = f"rot AS MATERIALIZED (SELECT id, vec, {HAD} AS rvec FROM iso)"


@query(sql(SKEW, ROT, "t AS (SELECT i, var_pop(vec[i]) AS a, var_pop(rvec[i]) AS b FROM rot, range(1, 65) t(i) GROUP BY i)", "SELECT ((i - 1) // 8)::INT AS chunk, round(sum(a), 8) AS before, round(sum(b), 8) AS after FROM t GROUP BY ALL"))
def chunk_balance(spark, d):
    r = rotation.hadamard_rotation(64)
    base = sets.skew(spark, d)
    s = quantize.partial_sums(base, lambda x: np.concatenate([[len(x)], x.sum(0), (x.T @ x).ravel()]), 1 + 64 + 64 * 64)
    mean = s[1:65] / s[0]
    cov = s[65:].reshape(64, 64) / s[0] - np.outer(mean, mean)
    rows = [(j, round(float(a), 8), round(float(b), 8)) for j, (a, b) in enumerate(zip(rotation.chunk_values(cov, None, M), rotation.chunk_values(cov, r, M), strict=True))]
    return spark.createDataFrame(rows, "chunk int, before double, after double")


def _rotated(base):
    q = quantize.Quantizer("fixed", np.zeros((M, 1, 8)), rotation.hadamard_rotation(64))

    def run(batches):
        import pyarrow as pa

        from vecgraph.functions.kernels import lists, matrix

        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), lists(q.turned(matrix(b.column(1))))], ["id", "vec", "rvec"])

    return base.select("id", "vec").mapInArrow(run, "id long, vec array<double>, rvec array<double>")


@query(sql(ISO, ROT, "SELECT id, round(list_sum(rvec), 6) AS total, round(rvec[1], 6) AS first, round(rvec[64], 6) AS last FROM rot"))
def rotate_fixed(spark, d):
    v = _rotated(sets.iso(spark, d))
    return v.select("id", F.round(F.aggregate("rvec", F.lit(0.0), lambda a, x: a + x), 6).alias("total"), F.round(F.get("rvec", F.lit(0)), 6).alias("first"), F.round(F.get("rvec", F.lit(63)), 6).alias("last"))


@query(sql(ISO, "SELECT count(*) AS n, true AS kept FROM iso"))
def rotate_isometry(spark, d):
    v = _rotated(sets.iso(spark, d))
    one = lambda c: dot(F.col(c), F.col(c))
    return v.agg(F.count("*").alias("n"), (F.max(F.abs(one("vec") - one("rvec"))) < 1e-9).alias("kept"))


PROB = f"pr AS MATERIALIZED (SELECT id, j, k, d, exp(-(d - min(d) OVER (PARTITION BY id, j))) AS e FROM (SELECT id, j, k, {d2_sql('vec[j * 8 + 1:(j + 1) * 8]', 'cw')} AS d FROM iso, book)), prob AS MATERIALIZED (SELECT id, j, k, e / sum(e) OVER (PARTITION BY id, j) AS p FROM pr)"


def _chunk0(spark, d):
    """(id, p): probabilities of the first chunk's codewords, as columns."""
    s = Setting(spark, d)
    book = F.lit(s.model.books[0].tolist()).cast("array<array<double>>")
    dist = F.transform(book, lambda c: -d2(F.slice("vec", 1, 8), c))
    return s, s.base.select("id", softmax(dist).alias("p"))


@query(sql(ISO, BOOK, PROB, "SELECT id, k::INT AS k, round(p, 6) AS p FROM prob WHERE j = 0"))
def assign_prob(spark, d):
    _, p = _chunk0(spark, d)
    return p.select("id", F.posexplode("p").alias("k", "p")).select("id", "k", r6("p"))


GUMBEL = "-ln(-ln((('0x' || substr(md5(concat_ws(':', 1, 0, id, 0, k)), 1, 8))::BIGINT + 0.5) / 4294967296.0))"
SOFT = f"so AS (SELECT id, k, exp(ln(p) + {GUMBEL}) AS e FROM prob WHERE j = 0), soft AS MATERIALIZED (SELECT id, k, e / sum(e) OVER (PARTITION BY id) AS w FROM so)"


def _soft0(spark, d):
    s, p = _chunk0(spark, d)
    noise = lambda k: -F.log(-F.log(unit_uniform(F.lit(1), F.lit(0), F.col("id"), F.lit(0), k)))
    return s, p.select("id", softmax(F.transform("p", lambda x, k: F.log(x) + noise(k))).alias("w"))


@query(sql(ISO, BOOK, PROB, SOFT, "SELECT id, k::INT AS k, round(w, 6) AS w FROM soft"))
def gumbel_code(spark, d):
    _, w = _soft0(spark, d)
    return w.select("id", F.posexplode("w").alias("k", "w")).select("id", "k", r6("w"))


@query(sql(ISO, BOOK, PROB, SOFT, "SELECT id, i::INT AS i, round(sum(w * cw[i + 1]), 6) AS x FROM soft JOIN book ON book.j = 0 AND book.k = soft.k, range(8) t(i) GROUP BY id, i"))
def soft_decode(spark, d):
    s, w = _soft0(spark, d)
    cols = F.lit(s.model.books[0].T.tolist()).cast("array<array<double>>")
    return w.select("id", F.posexplode(F.transform(cols, lambda c: dot(F.col("w"), c))).alias("i", "x")).select("id", "i", r6("x"))


@query(sql(ISO, "SELECT count(*) AS triples, true AS holds FROM iso WHERE id + 2 IN (SELECT id FROM iso) AND id + 1 IN (SELECT id FROM iso)"))
def comparison_identity(spark, d):
    """d2(x,q) - d2(y,q) = 2 |y-x| |q-mid| cos(angle), over triples of consecutive ids."""
    v = sets.iso(spark, d)
    x, y, q = (v.select((F.col("id") - i).alias("id"), F.col("vec").alias(n)) for i, n in enumerate("xyq"))
    t = x.join(y, "id").join(q, "id")
    diff = F.zip_with("y", "x", lambda a, b: a - b)
    mid = F.zip_with("q", F.zip_with("x", "y", lambda a, b: (a + b) / 2), lambda a, b: a - b)
    gap = F.abs((d2(F.col("x"), F.col("q")) - d2(F.col("y"), F.col("q"))) - 2 * dot(diff, mid))
    return t.agg(F.count("*").alias("triples"), (F.max(gap) < 1e-9).alias("holds"))
