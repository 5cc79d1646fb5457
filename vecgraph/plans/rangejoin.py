"""Range conditions rewritten to equi-joins on bins, and shards of even size."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def band_join(left: DataFrame, right: DataFrame, a: str, b: str, low: float, high: float) -> DataFrame:
    """Rows with a + low <= b <= a + high. Bins as wide as the band: each left row looks into the two or three it can touch."""
    width = max(high - low, 1e-9)
    bin_of = lambda c: F.floor(c / width).cast("long")
    asked = left.withColumn("_bin", F.explode(F.sequence(bin_of(F.col(a) + low), bin_of(F.col(a) + high))))
    held = right.withColumn("_bin", bin_of(F.col(b)))
    return asked.join(held, "_bin").where((F.col(b) >= F.col(a) + low) & (F.col(b) <= F.col(a) + high)).drop("_bin")


def even_shards(rows: DataFrame, order: list[str], n: int, blocks: int = 256) -> DataFrame:
    """Rows and their n-tile in an order, without a global window: ranks within range blocks plus the blocks' offsets.

    Blocks are cut at quantiles of the first column; a block's rows are ranked together, so equal values of the first
    column share a block. Only the blocks' counts reach the driver.
    """
    cuts = sorted(set(rows.approxQuantile(order[0], [i / blocks for i in range(1, blocks)], 1 / (4 * blocks))))
    block = F.aggregate(F.lit(cuts).cast("array<double>"), F.lit(0), lambda s, c: s + F.when(F.col(order[0]) > c, 1).otherwise(0))
    placed = rows.withColumn("_b", block)
    size = {r["_b"]: r["n"] for r in placed.groupBy("_b").agg(F.count("*").alias("n")).collect()}
    total, start, at = sum(size.values()), {}, 0
    for b in sorted(size):
        start[b] = at
        at += size[b]
    offset = F.create_map(*[F.lit(x) for kv in start.items() for x in kv])
    rank = F.row_number().over(Window.partitionBy("_b").orderBy(*order)) - 1 + offset[F.col("_b")]
    base, more = divmod(total, n)
    edge = more * (base + 1)
    tile = F.when(rank < edge, F.floor(rank / (base + 1))).otherwise(more + F.floor((rank - edge) / max(base, 1))) + 1
    return placed.select(order[-1], tile.cast("long").alias("shard"))
