"""Vector sets (id long, vec array<double>) derived from the given tables.

Every set covers its whole table. Queries of a search are the rows whose id is divisible by 50, asked
against all rows but themselves.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from vecgraph.functions.columns import dot
from vecgraph.session import ship

BLOCK = 10_000  # equal rows told out in one go
QUERY_STEP = 50
BUCKETS = 64


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def iso(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"))


def skew(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Dimension d scaled by 2^-(d div 8): exact powers of two, so a set of very unequal dimensions."""
    return iso(spark, sf_dir).select("id", F.transform("vec", lambda x, i: x * F.pow(F.lit(2.0), -F.floor(i / 8))).alias("vec"))


def hashed_words(rows: DataFrame, text: Column, buckets: int = BUCKETS) -> DataFrame:
    """(id, vec): counts of words by hash bucket, scaled to length one. Rows without words are left out."""
    word = rows.select("id", F.explode(F.split(text, " ")).alias("w"))
    bucket = F.conv(F.substring(F.md5("w"), 1, 6), 16, 10).cast("long") % buckets
    counts = word.groupBy("id", bucket.cast("int").alias("b")).agg(F.count("*").alias("n"))
    by_row = counts.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("b", "n"))).alias("m"))
    raw = by_row.select("id", F.transform(F.sequence(F.lit(0), F.lit(buckets - 1)), lambda b: F.coalesce(F.try_element_at("m", b.cast("int")), F.lit(0)).cast("double")).alias("v"))
    return raw.select("id", F.transform("v", lambda x: x / F.sqrt(dot(F.col("v"), F.col("v")))).alias("vec"))


def text(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = table(spark, sf_dir, "documents").where("text is not null")
    return hashed_words(d.select(F.col("doc_id").alias("id"), "text"), F.col("text"))


def ood(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries from another distribution than `text`: the benchmark's passages."""
    d = table(spark, sf_dir, "benchmark").where("text is not null")
    return hashed_words(d.select(F.col("item_id").alias("id"), "text"), F.col("text"))


def page(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = table(spark, sf_dir, "pages").where("html is not null").select(F.col("page_id").alias("id"), F.regexp_replace("html", "<[^>]*>", " ").alias("t"))
    return hashed_words(d, F.col("t"))


def rowvec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight scaled measures of every lineitem; the id is a row hash with a counter for equal rows.

    Equal rows are counted and told out again in blocks, so a large group of copies is in no single task.
    """
    row = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate", "l_quantity", "l_discount", "l_tax", "l_returnflag", "l_linestatus"]
    blocks = table(spark, sf_dir, "lineitem").groupBy(*row).agg(F.count("*").alias("n")).withColumn("block", F.explode(F.expr(f"sequence(0L, (n - 1) div {BLOCK})")))
    li = blocks.repartition(*row, "block").withColumn("copy", F.explode(F.expr(f"sequence(block * {BLOCK}, least(n, (block + 1) * {BLOCK}) - 1)")))
    v = F.array(F.col("l_quantity") / 50, F.col("l_extendedprice") / 1e5, F.col("l_discount") * 10, F.col("l_tax") * 10, F.month("l_shipdate") / F.lit(12.0), F.col("l_linenumber") / F.lit(7.0), F.when(F.col("l_returnflag") == "A", 0.0).when(F.col("l_returnflag") == "N", 0.5).otherwise(1.0), F.when(F.col("l_linestatus") == "O", 0.0).otherwise(1.0))
    return li.select(F.xxhash64(*row, "copy").alias("id"), v.cast("array<double>").alias("vec"))


def profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sixteen measures of every customer's orders, scaled to [0, 1] by the set's own extremes."""
    o, li = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    per_order = li.groupBy("l_orderkey").agg(F.count("*").alias("n"), *[f(c).alias(f"{n}_{c}") for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax") for n, f in (("s", F.sum), ("mx", F.max))])
    joined = o.join(per_order, o.o_orderkey == per_order.l_orderkey)
    m = [F.count("*"), F.sum("n"), F.sum("o_totalprice"), F.avg("o_totalprice"), F.max("o_totalprice"), F.min("o_totalprice")] + [f(c) for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax") for f in (lambda c: F.sum(f"s_{c}"), lambda c: F.max(f"mx_{c}"))] + [F.countDistinct("o_orderpriority"), F.countDistinct(F.year("o_orderdate"))]
    wide = joined.groupBy(F.col("o_custkey").alias("id")).agg(*[x.cast("double").alias(f"c{i}") for i, x in enumerate(m)])
    ends = wide.agg(*[f(f"c{i}").alias(f"{n}{i}") for i in range(16) for n, f in (("lo", F.min), ("hi", F.max))]).first()
    unit = lambda i: (F.col(f"c{i}") - ends[f"lo{i}"]) / (ends[f"hi{i}"] - ends[f"lo{i}"]) if ends[f"hi{i}"] is not None and ends[f"hi{i}"] > ends[f"lo{i}"] else F.lit(0.0)
    return wide.select("id", F.array(*[unit(i) for i in range(16)]).alias("vec"))


SETS = {"iso": iso, "skew": skew, "text": text, "page": page, "rowvec": rowvec, "profile": profile}


def queries_of(base: DataFrame) -> DataFrame:
    return base.where(F.col("id") % QUERY_STEP == 0)


def validation_of(base: DataFrame) -> DataFrame:
    """The fold that models are chosen by."""
    return base.where(F.pmod("id", F.lit(10)) == 9)


def training_of(base: DataFrame) -> DataFrame:
    """What models are fitted on: neither queries nor the validation fold."""
    return base.where((F.pmod("id", F.lit(10)) != 9) & (F.pmod("id", F.lit(QUERY_STEP)) != 0))
