"""Plans read only what they need, and rewrites avoid nested loops."""

from pyspark.sql import functions as F

from vecgraph.operators import exact, quantize
from vecgraph.plans import checks
from vecgraph.plans.rangejoin import band_join, even_shards
from vecgraph.sources import sets


def test_encoding_reads_only_ids_and_vectors(spark, sf_dir):
    q = quantize.seeded_books(sets.iso(spark, sf_dir), 8, 16)
    df = quantize.encode(sets.iso(spark, sf_dir), q)
    assert checks.columns_read(df) == {"vec_id", "embedding"} and checks.count(df, "Exchange") == 0


def test_filters_reach_the_scan(spark, sf_dir):
    df = sets.table(spark, sf_dir, "embeddings").where("label = 3").select("vec_id")
    assert "EqualTo(label,3)" in checks.pushed(df) and checks.columns_read(df) == {"vec_id", "label"}


def test_no_cross_joins(spark, sf_dir):
    base = sets.iso(spark, sf_dir)
    for df in (exact.threshold_graph_cells(base, 1.2), exact.exact_knn(base, sets.queries_of(base), 10)):
        assert checks.count(df, "CartesianProduct") == 0 and checks.count(df, "BroadcastNestedLoopJoin") == 0


def test_band_join(spark):
    a = spark.createDataFrame([(i, float(i)) for i in range(40)], "i int, x double")
    b = spark.createDataFrame([(j, j * 0.7 - 3) for j in range(60)], "j int, y double")
    got = {(r.i, r.j) for r in band_join(a, b, "x", "y", -1.5, 2.0).collect()}
    assert got == {(i, j) for i in range(40) for j in range(60) if i - 1.5 <= j * 0.7 - 3 <= i + 2}
    assert checks.count(band_join(a, b, "x", "y", -1.5, 2.0), "CartesianProduct") == 0


def test_even_shards_with_many_equal_values(spark):
    rows = spark.range(103).select((F.col("id") % 3).alias("v"), "id")
    got = {r.id: r.shard for r in even_shards(rows, ["v", "id"], 8).collect()}
    order = sorted(range(103), key=lambda i: (i % 3, i))
    size = [103 // 8 + (i < 103 % 8) for i in range(8)]
    want, at = {}, 0
    for s, n in enumerate(size):
        for i in order[at : at + n]:
            want[i] = s + 1
        at += n
    assert got == want


def test_searches_read_the_index_where_it_lies(spark, sf_dir):
    """Only queries and answers are shuffled: between the index's scan and the walk stands no exchange."""
    from vecgraph.operators.sharded import ShardedIndex
    from vecgraph.operators.walk import beam_search
    from vecgraph.queries.common import Setting

    s = Setting(spark, sf_dir)
    sharded = ShardedIndex.build(s.base, s.model, 3)
    for found, rows in ((beam_search(s.index(vectors=False), s.queries, 8, 5, "code_only", s.model), 500), (sharded.search(s.queries, 2, 8, 5), None)):
        plan = found._jdf.queryExecution().executedPlan().toString().splitlines()
        walk = next(i for i, line in enumerate(plan) if "FlatMapCoGroupsInArrow" in line)
        depth = lambda line: len(line) - len(line.lstrip(" :+-*()0123456789"))
        index = plan[walk + 1 :]
        index = index[: next(i for i, line in enumerate(index) if i and depth(line) <= depth(index[0]))]
        scan = next(line for line in index if "Bucketed: true" in line)
        above = index[: index.index(scan)]
        assert not any("Exchange" in line and "Broadcast" not in line for line in above)
