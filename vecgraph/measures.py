"""Measures of searches and sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def recall(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(qid, recall): share of the k true neighbours that were found; a query without results has zero."""
    t = truth.where(F.col("rank") <= k).select("qid", "vid")
    hit = result.where(F.col("rank") <= k).select("qid", "vid").withColumn("hit", F.lit(1))
    return t.join(hit, ["qid", "vid"], "left").groupBy("qid").agg((F.sum(F.coalesce("hit", F.lit(0))) / k).alias("recall"))


def lid(truth: DataFrame) -> DataFrame:
    """(qid, lid): maximum likelihood estimate of the local intrinsic dimensionality from distances to the nearest rows; null where
    all of them are equal, so that there is no estimate."""
    last = F.max("d2").over(Window.partitionBy("qid"))
    ratio = truth.withColumn("far", last).where("d2 > 0").select("qid", (0.5 * F.log(F.col("d2") / F.col("far"))).alias("l"))
    return ratio.groupBy("qid").agg(F.try_divide(F.lit(-1.0), F.avg("l")).alias("lid"))


def block_reads(result: DataFrame, vector_bytes: int, block: int = 4096, latency: float = 100e-6, bandwidth: float = 2e9) -> DataFrame:
    """(qid, reads, blocks, bytes, io_s): a model of the disk tier's cost from the vertices visited."""
    per = -(-vector_bytes // block)
    one = result.groupBy("qid").agg(F.max("reads").alias("reads"))
    bytes_ = F.col("reads") * per * block
    return one.select("qid", "reads", (F.col("reads") * per).alias("blocks"), bytes_.alias("bytes"), (F.col("reads") * latency + bytes_ / bandwidth).alias("io_s"))


def result_objective(results: DataFrame, codes: DataFrame, lut: DataFrame) -> DataFrame:
    """(pairs, objective): what the problem statement minimizes, the sum of the distances between queries and the decoded codes of
    their result sets. Result sets are given: without them the minimum means nothing."""
    from vecgraph.functions.columns import adc

    both = results.select("qid", "vid").join(codes, "vid").join(lut, "qid")
    return both.agg(F.count("*").alias("pairs"), F.sum(adc(F.col("lut"), F.col("code"))).alias("objective"))


def plan_budget(n: int, d: int, degree: int, f: float, link_bytes: int = 4, k: int = 256) -> tuple[int, int]:
    """(bytes allowed, largest number of one-byte chunks): a fraction f of vectors and graph, for codes and books."""
    allowed = int(f * n * (4 * d + link_bytes * degree))
    return allowed, max(0, (allowed - 4 * k * d) // n)


def qps_at(sweep: DataFrame, floor: float) -> DataFrame:
    """(config, qps): straight-line value at the recall floor from a sweep (config, h, recall, qps); null where it isn't reached."""
    w = Window.partitionBy("config").orderBy("h")
    s = sweep.withColumn("r0", F.lag("recall").over(w)).withColumn("q0", F.lag("qps").over(w))
    cross = (F.col("recall") >= floor) & (F.col("r0").isNull() | (F.col("r0") < floor))
    share = (F.lit(floor) - F.col("r0")) / (F.col("recall") - F.col("r0"))
    at = F.when(F.col("r0").isNull(), F.col("qps")).otherwise(F.col("q0") + share * (F.col("qps") - F.col("q0")))
    reached = s.where(cross).groupBy("config").agg(F.min(F.struct("h", at.alias("qps"))).alias("b")).select("config", F.col("b.qps").alias("qps"))
    return sweep.select("config").distinct().join(reached, "config", "left")
