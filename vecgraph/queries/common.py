"""The registry, the default parameters, and pieces of oracle SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecgraph.operators import exact, quantize
from vecgraph.operators.sharded import stored_index
from vecgraph.session import materialize, ship
from vecgraph.sources import sets

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

#: Chunks, codewords, beam, answers, neighbours of the substrate graph.
M, K, H, TOP, NEAR = 8, 16, 16, 10, 8


def query(oracle: str | None = None):
    def register(f):
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            ship(spark)
            return f(spark, sf_dir)

        QUERIES[f.__name__] = run
        if oracle:
            ORACLES[f.__name__] = oracle
        return f

    return register


class Setting:
    """The frozen index most queries use: a seeded quantizer and the symmetrized neighbour graph of a set."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str = "iso") -> None:
        self.spark = spark
        base = sets.SETS[name](spark, sf_dir)
        self.base = base if name in ("iso", "skew") else materialize(base)  # the others are aggregates, not to be worked out for each use
        self.queries = sets.queries_of(self.base)
        self.model = quantize.seeded_books(self.base, M, K)

    def codes(self) -> DataFrame:
        return quantize.encode(self.base, self.model)

    def edges(self) -> DataFrame:
        return materialize(exact.sym_knn_graph(self.base, NEAR))

    def index(self, vectors: bool, codes: bool = True, edges: DataFrame | None = None, allowed: DataFrame | None = None) -> DataFrame:
        return stored_index(self.base, edges if edges is not None else self.edges(), self.codes() if codes else None, vectors, allowed=allowed)


def r6(c: str, name: str | None = None):
    return F.round(F.col(c), 6).alias(name or c)


# ---- oracle SQL ----


def d2(a: str, b: str) -> str:
    return f"list_sum(list_transform(list_zip({a}, {b}), lambda p: (p[1] - p[2]) * (p[1] - p[2])))"


def dot(a: str, b: str) -> str:
    return f"list_sum(list_transform(list_zip({a}, {b}), lambda p: p[1] * p[2]))"


ISO = "iso AS MATERIALIZED (SELECT vec_id AS id, embedding::DOUBLE[] AS vec FROM embeddings)"
SKEW = "iso AS MATERIALIZED (SELECT vec_id AS id, list_transform(embedding::DOUBLE[], lambda x, i: x * power(2.0, -floor((i - 1) / 8))) AS vec FROM embeddings)"


def hashed(table: str, key: str, text: str) -> str:
    """SQL of a hashed word set (id, vec)."""
    return f"""(SELECT id, list_transform(v, lambda x: x / sqrt({dot('v', 'v')})) AS vec FROM (
  SELECT id, list_transform(range(64), lambda b: coalesce(map_extract(m, b)[1], 0)::DOUBLE) AS v FROM (
    SELECT id, map_from_entries(list({{'k': b, 'v': n}})) AS m FROM (
      SELECT id, ('0x' || substr(md5(w), 1, 6))::BIGINT % 64 AS b, count(*) AS n
      FROM (SELECT {key} AS id, unnest(string_split({text}, ' ')) AS w FROM {table} WHERE {text} IS NOT NULL) GROUP BY ALL) GROUP BY id)))"""


TEXT = f"iso AS MATERIALIZED {hashed('documents', 'doc_id', 'text')}"
Q = "q AS MATERIALIZED (SELECT id AS qid, vec AS qvec FROM iso WHERE id % 50 = 0)"
FULL = f"dist AS MATERIALIZED (SELECT qid, id AS vid, {d2('qvec', 'vec')} AS d FROM q, iso)"
TRUTH = "truth AS MATERIALIZED (SELECT * FROM (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY d, vid)::INT AS rank, vid, d AS d2 FROM dist WHERE vid <> qid) WHERE rank <= 10)"
TRUE_DIST = f"tdist AS MATERIALIZED (SELECT qid, id AS vid, {d2('qvec', 'vec')} AS d FROM q, iso)"
TTRUTH = TRUTH.replace("truth AS", "truth AS", 1).replace("FROM dist", "FROM tdist")
KNN = f"""knn AS MATERIALIZED (SELECT src, dst, d2 FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY d2, dst) AS r FROM (
  SELECT a.id AS src, b.id AS dst, {d2('a.vec', 'b.vec')} AS d2 FROM iso a JOIN iso b ON a.id <> b.id)) WHERE r <= {NEAR})"""
GRAPH = f"{KNN}, graph AS MATERIALIZED (SELECT src, dst, min(d2) AS d2 FROM (SELECT * FROM knn UNION ALL SELECT dst, src, d2 FROM knn) GROUP BY src, dst)"
MEAN = "mean AS MATERIALIZED (SELECT list(x ORDER BY i) AS mv FROM (SELECT i, avg(vec[i]) AS x FROM iso, range(1, 65) t(i) GROUP BY i))"
ENTRY = f"{MEAN}, entry AS MATERIALIZED (SELECT id AS vid, {d2('vec', 'mv')} AS d2 FROM iso, mean ORDER BY d2, id LIMIT 1)"
BOOK = f"book AS MATERIALIZED (SELECT j, row_number() OVER (PARTITION BY j ORDER BY id) - 1 AS k, vec[j * 8 + 1:(j + 1) * 8] AS cw FROM (SELECT * FROM iso ORDER BY id LIMIT {K}), range({M}) t(j))"
CODES = f"""near AS MATERIALIZED (SELECT id, i.j, k, d, row_number() OVER (PARTITION BY id, i.j ORDER BY d, k) AS r FROM (
  SELECT id, j, k, {d2('vec[j * 8 + 1:(j + 1) * 8]', 'cw')} AS d FROM iso, book) i),
codes AS MATERIALIZED (SELECT id AS vid, list(k ORDER BY j) AS code FROM near WHERE r = 1 GROUP BY id)"""
LUT = f"lut AS MATERIALIZED (SELECT qid, list(row ORDER BY j) AS lut FROM (SELECT qid, j, list(d ORDER BY k) AS row FROM (SELECT qid, j, k, {d2('qvec[j * 8 + 1:(j + 1) * 8]', 'cw')} AS d FROM q, book) GROUP BY qid, j) GROUP BY qid)"
ADC = f"dist AS MATERIALIZED (SELECT qid, vid, list_sum(list_transform(range({M}), lambda j: lut[j + 1][code[j + 1] + 1])) AS d FROM lut, codes)"


def beam(h: int = H, links: str = "graph") -> str:
    """Walk states from dist, links and entry: w(qid, step, beam, visited, nxt)."""
    return f"""cand AS MATERIALIZED (SELECT qid, src, list({{'d': d, 'vid': dst}}) AS near FROM {links} AS graph JOIN dist ON dist.vid = graph.dst GROUP BY qid, src),
w AS (
  SELECT dist.qid, 0 AS step, [{{'d': d, 'vid': dist.vid}}] AS beam, []::BIGINT[] AS visited, dist.vid AS nxt FROM dist JOIN entry ON entry.vid = dist.vid
  UNION ALL
  SELECT qid, step + 1, beam, visited, list_filter(beam, lambda c: NOT list_contains(visited, c.vid))[1].vid FROM (
    SELECT w.qid, step, list_append(visited, nxt) AS visited, list_sort(list_distinct(list_concat(beam, near)))[1:{h}] AS beam
    FROM w LEFT JOIN cand ON cand.qid = w.qid AND cand.src = w.nxt WHERE nxt IS NOT NULL)),
ended AS MATERIALIZED (SELECT qid, step AS hops, beam, visited FROM w WHERE nxt IS NULL)"""


BEAM_RESULT = """found AS (SELECT qid, hops, unnest(list_filter(beam, lambda c: c.vid <> qid)) AS c FROM ended),
ranked AS (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY c.d, c.vid)::INT AS rank, c.vid AS vid, c.d AS d2, hops::BIGINT AS hops FROM found)"""


def sql(*parts: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(parts[:-1]) + "\n" + parts[-1]
