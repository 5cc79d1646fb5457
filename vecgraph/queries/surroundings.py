"""Relational operations around a search service, on the given tables."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from vecgraph.session import bucketed
from vecgraph.sources import io
from vecgraph.sources.sets import table
from vecgraph.streaming.streams import micros

from .common import query


def _t(name):
    return lambda spark, d: table(spark, d, name)


events, lineitem, orders, customer, nation, region, part, supplier, documents, embeddings, labels, conversations, pages = map(_t, "events lineitem orders customer nation region part supplier documents embeddings labels conversations pages".split())


@query("SELECT vec_id, label FROM embeddings WHERE label IN (1, 3, 5) AND vec_id BETWEEN 10 AND 400 AND label IS NOT DISTINCT FROM 3")
def ops_filters(spark, d):
    return embeddings(spark, d).where(F.col("label").isin(1, 3, 5) & F.col("vec_id").between(10, 400) & F.col("label").eqNullSafe(3)).select("vec_id", "label")


@query("SELECT page_id, regexp_extract(url, '://([^/]+)', 1) AS host FROM pages WHERE url LIKE 'https://%' AND regexp_matches(url, '/(en|fr)/')")
def ops_like_rlike(spark, d):
    return pages(spark, d).where(F.col("url").like("https://%") & F.col("url").rlike("/(en|fr)/")).select("page_id", F.regexp_extract("url", "://([^/]+)", 1).alias("host"))


@query("SELECT o_orderkey, c_custkey, n_name FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'ASIA'")
def ops_join_star(spark, d):
    j = orders(spark, d).join(customer(spark, d), F.col("o_custkey") == F.col("c_custkey")).join(nation(spark, d), F.col("c_nationkey") == F.col("n_nationkey"))
    return j.join(region(spark, d).where("r_name = 'ASIA'"), F.col("n_regionkey") == F.col("r_regionkey")).select("o_orderkey", "c_custkey", "n_name")


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def ops_semi_join(spark, d):
    return customer(spark, d).join(orders(spark, d), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("c_custkey")


@query("SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
def ops_anti_join(spark, d):
    return documents(spark, d).join(labels(spark, d), "doc_id", "left_anti").select("doc_id")


@query("SELECT count(d.doc_id) AS docs, count(l.doc_id) AS labelled, count(*) AS both_sides FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")
def ops_full_join(spark, d):
    a, b = documents(spark, d).select("doc_id", F.lit(1).alias("a")), labels(spark, d).select("doc_id", F.lit(1).alias("b"))
    return a.join(b, "doc_id", "full_outer").agg(F.count("a").alias("docs"), F.count("b").alias("labelled"), F.count("*").alias("both_sides"))


@query("""WITH v AS (SELECT event_id AS version, ts, user_id FROM events WHERE event_type = (SELECT min(event_type) FROM events)),
e AS (SELECT event_id, ts, user_id FROM events WHERE event_type = (SELECT max(event_type) FROM events))
SELECT e.event_id, v.version FROM e ASOF LEFT JOIN v ON e.user_id = v.user_id AND e.ts >= v.ts""")
def ops_asof_join(spark, d):
    """Each event of one type with the latest earlier one of another type by the same user: a union and a running last value."""
    e = events(spark, d)
    lo, hi = e.agg(F.min("event_type"), F.max("event_type")).first()
    rows = e.where(F.col("event_type").isin(lo, hi)).select("user_id", "ts", F.when(F.col("event_type") == lo, F.col("event_id")).alias("v"), F.when(F.col("event_type") == hi, F.col("event_id")).alias("event_id"))
    w = Window.partitionBy("user_id").orderBy("ts", F.col("v").isNull()).rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("version", F.last("v", ignorenulls=True).over(w)).where("event_id is not null").select("event_id", "version")


@query("""SELECT a.event_id, count(b.event_id) AS before FROM events a LEFT JOIN events b ON a.user_id = b.user_id AND b.ts < a.ts AND b.ts >= a.ts - INTERVAL 1 DAY GROUP BY a.event_id""")
def ops_interval_join(spark, d):
    """Events of the same user in the day before, by a range frame instead of a self-join."""
    w = Window.partitionBy("user_id").orderBy("at").rangeBetween(-86_400_000_000, -1)
    return events(spark, d).withColumn("at", micros("ts")).select("event_id", F.count("*").over(w).alias("before"))


@query("""SELECT p_partkey, s_suppkey FROM part JOIN supplier ON s_acctbal BETWEEN p_retailprice AND p_retailprice + 5""")
def ops_range_join(spark, d):
    """A band join by bins: each part looks into the two bins its band can touch."""
    from vecgraph.plans.rangejoin import band_join

    return band_join(part(spark, d).select("p_partkey", "p_retailprice"), supplier(spark, d).select("s_suppkey", "s_acctbal"), "p_retailprice", "s_acctbal", 0.0, 5.0).select("p_partkey", "s_suppkey")


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(avg(l_discount), 6) AS discount FROM lineitem GROUP BY 1, 2")
def ops_hash_agg(spark, d):
    return lineitem(spark, d).groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"), F.round(F.avg("l_discount"), 6).alias("discount"))


@query("SELECT coalesce(l_returnflag, '*') AS flag, coalesce(l_linestatus, '*') AS status, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def ops_cube(spark, d):
    return lineitem(spark, d).cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")).select(F.coalesce("l_returnflag", F.lit("*")).alias("flag"), F.coalesce("l_linestatus", F.lit("*")).alias("status"), "n")


@query("SELECT coalesce(lang, '*') AS lang, coalesce(source, '*') AS source, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY ROLLUP (lang, source)")
def ops_rollup(spark, d):
    return documents(spark, d).rollup("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars")).select(F.coalesce("lang", F.lit("*")).alias("lang"), F.coalesce("source", F.lit("*")).alias("source"), "n", "chars")


@query("SELECT lang, count(DISTINCT source) AS sources, min(doc_id) AS first, arg_max(doc_id, (n_chars, doc_id)) AS longest FROM documents GROUP BY lang")
def ops_distinct_agg(spark, d):
    return documents(spark, d).groupBy("lang").agg(F.countDistinct("source").alias("sources"), F.min("doc_id").alias("first"), F.max_by("doc_id", F.struct("n_chars", "doc_id")).alias("longest"))


@query("SELECT label, count(*) FILTER (t = 0) AS a, count(*) FILTER (t = 1) AS b FROM (SELECT quality AS label, toxic AS t FROM labels) GROUP BY label")
def ops_pivot(spark, d):
    return labels(spark, d).groupBy(F.col("quality").alias("label")).pivot("toxic", [0, 1]).agg(F.count(F.lit(1))).na.fill(0).select("label", F.col("0").alias("a"), F.col("1").alias("b"))


@query("SELECT doc_id, 'quality' AS name, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def ops_unpivot(spark, d):
    return labels(spark, d).unpivot("doc_id", ["quality", "toxic"], "name", "value")


@query("SELECT doc_id, ntile(8) OVER (ORDER BY n_chars, doc_id) AS shard FROM documents")
def ops_ntile_shards(spark, d):
    """Shards of even size by length. Bounds come from a bounded quantile sketch where rows are many; here ranks are exact."""
    from vecgraph.plans.rangejoin import even_shards

    return even_shards(documents(spark, d).select("doc_id", "n_chars"), ["n_chars", "doc_id"], 8)


@query("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS recent FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def ops_lag_lead(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return events(spark, d).select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.round(F.sum("value").over(w.rowsBetween(-2, 0)), 6).alias("recent"))


@query("SELECT c_nationkey, c_custkey, rank() OVER w AS r, dense_rank() OVER w AS dr FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC) QUALIFY rank() OVER w <= 5")
def ops_group_topk(spark, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"))
    ranked = customer(spark, d).select("c_nationkey", "c_custkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"))
    return ranked.where("r <= 5").select("c_nationkey", "c_custkey", F.col("r").cast("long").alias("r"), F.col("dr").cast("long").alias("dr"))


@query("SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def ops_take_ordered(spark, d):
    return orders(spark, d).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey")


@query("(SELECT doc_id FROM documents INTERSECT SELECT doc_id FROM labels) EXCEPT SELECT doc_id FROM labels WHERE toxic = 1")
def ops_set_ops(spark, d):
    la = labels(spark, d)
    return documents(spark, d).select("doc_id").intersect(la.select("doc_id")).exceptAll(la.where("toxic = 1").select("doc_id").distinct())


@query("SELECT event_type, count(*) AS n, sum(json_extract(props, '$.k')::BIGINT)::BIGINT AS total FROM events GROUP BY 1")
def ops_json(spark, d):
    return events(spark, d).groupBy("event_type").agg(F.count("*").alias("n"), F.sum(F.get_json_object("props", "$.k").cast("long")).alias("total"))


@query("SELECT date_trunc('month', l_shipdate)::TIMESTAMP AS month, count(*) AS n, max(date_diff('day', DATE '1992-01-01', l_shipdate::DATE)) AS last_day FROM lineitem GROUP BY 1")
def ops_dates(spark, d):
    t = lineitem(spark, d).groupBy(F.date_trunc("month", "l_shipdate").cast("timestamp_ntz").alias("month"))
    return t.agg(F.count("*").alias("n"), F.max(F.datediff(F.col("l_shipdate").cast("date"), F.lit("1992-01-01").cast("date"))).cast("long").alias("last_day"))


@query("SELECT doc_id, len(string_split(text, ' ')) AS words, md5(lower(text)) AS digest, left(text, 3) AS head FROM documents WHERE text IS NOT NULL")
def ops_strings(spark, d):
    return documents(spark, d).where("text is not null").select("doc_id", F.size(F.split("text", " ")).cast("long").alias("words"), F.md5(F.lower("text")).alias("digest"), F.left("text", F.lit(3)).alias("head"))


@query("SELECT vec_id, round(list_max(embedding::DOUBLE[]), 6) AS most, list_position(embedding, list_max(embedding)) - 1 AS at, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def ops_arrays(spark, d):
    return embeddings(spark, d).select("vec_id", F.round(F.array_max("embedding").cast("double"), 6).alias("most"), (F.array_position("embedding", F.array_max("embedding")) - 1).cast("int").alias("at"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))


@query("SELECT conv_id, string_agg(role, '>' ORDER BY turn, role) AS roles, count(*) AS turns FROM conversations GROUP BY conv_id")
def ops_ordered_lists(spark, d):
    lists = conversations(spark, d).groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role"))).alias("l"), F.count("*").alias("turns"))
    return lists.select("conv_id", F.array_join(F.transform("l", lambda x: x["role"]), ">").alias("roles"), "turns")


@query("SELECT label, count(*) AS n FROM embeddings WHERE ('0x' || substr(md5(vec_id::VARCHAR), 1, 4))::BIGINT < 16384 GROUP BY label")
def ops_hash_sample(spark, d):
    """A quarter of the rows by hash: the same rows in any partitioning."""
    h = F.conv(F.substring(F.md5(F.col("vec_id").cast("string")), 1, 4), 16, 10).cast("long")
    return embeddings(spark, d).where(h < 16384).groupBy("label").agg(F.count("*").alias("n"))


@query("SELECT vec_id, label FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY md5(vec_id::VARCHAR), vec_id) AS r FROM embeddings) WHERE r <= 20")
def ops_stratified_sample(spark, d):
    w = Window.partitionBy("label").orderBy(F.md5(F.col("vec_id").cast("string")), "vec_id")
    return embeddings(spark, d).withColumn("r", F.row_number().over(w)).where("r <= 20").select("vec_id", "label")


@query("SELECT event_type, round(covar_pop(value, event_id), 4) AS cov, round(var_pop(value), 6) AS var FROM events GROUP BY 1")
def ops_covariance(spark, d):
    return events(spark, d).groupBy("event_type").agg(F.round(F.covar_pop("value", "event_id"), 4).alias("cov"), F.round(F.var_pop("value"), 6).alias("var"))


@query("SELECT event_type, quantile_disc(value, 0.5) AS median, quantile_disc(value, 0.9) AS high, true AS users_near FROM events GROUP BY event_type")
def ops_approx_agg(spark, d):
    """Approximate quantiles, at an accuracy beyond the groups' sizes here, and approximate distinct counts within five standard errors."""
    users = (F.approx_count_distinct("user_id", 0.02) / F.count_distinct("user_id") - 1).alias("u")
    got = events(spark, d).groupBy("event_type").agg(F.percentile_approx("value", 0.5, 1_000_000).alias("median"), F.percentile_approx("value", 0.9, 1_000_000).alias("high"), users)
    return got.select("event_type", "median", "high", (F.abs("u") < 0.1).alias("users_near"))


@query("SELECT label, count(*) AS n, min(vec_id) AS least FROM embeddings GROUP BY label")
def ops_io_bucketed(spark, d):
    """Written in buckets by label, aggregated in place."""
    return bucketed(embeddings(spark, d).select("vec_id", "label"), "label", 4).groupBy("label").agg(F.count("*").alias("n"), F.min("vec_id").alias("least"))


for _format in ("parquet", "json", "csv", "orc"):

    def _round_trip(spark, d, kind=_format):
        return io.round_trip(labels(spark, d), kind)

    _round_trip.__name__ = f"ops_io_{_format}"
    query("SELECT doc_id, quality, toxic FROM labels")(_round_trip)


@query("SELECT vec_id, label FROM embeddings WHERE label = 3")
def ops_io_partitioned(spark, d):
    """Written by label, read back with a filter that prunes partitions."""
    return io.partitioned(embeddings(spark, d).select("vec_id", "label"), "label").where("label = 3").select("vec_id", "label")
