"""Structured Streaming: windows over the query log, dedup, encoding of arriving vectors, a fresh-vector buffer.

Each function builds a streaming DataFrame from a streaming source. `finished` runs one to the end of what has
arrived (availableNow) into a parquet sink in the shared folder and reads the sink.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecgraph.session import scratch_dir


def micros(name: str):
    """Microseconds of a wall-clock column, whatever the session's time zone."""
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', {name})")


def instant(name: str):
    """A wall-clock column read as UTC, for watermarks."""
    return F.timestamp_micros(micros(name))


def wall(name: str):
    """The way back."""
    return F.expr(f"timestampadd(MICROSECOND, unix_micros({name}), TIMESTAMP_NTZ'1970-01-01 00:00:00')")


def source(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table's files as a stream; the glob lets the same path name one file or a folder of them."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", 8).parquet(f"{sf_dir}/{name}.parque[t]")
    return rows.withColumn("ts", instant("ts")) if dict(rows.dtypes).get("ts") == "timestamp_ntz" else rows


def finished(stream: DataFrame, mode: str = "append") -> DataFrame:
    spark = stream.sparkSession
    root = f"{scratch_dir(spark)}/streams/{uuid.uuid4().hex}"
    w = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{root}/checkpoint").trigger(availableNow=True)
    if mode == "append":
        w.format("parquet").option("path", f"{root}/out").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{root}/out")
    last: list[str] = []

    def put(batch: DataFrame, number: int) -> None:
        path = f"{root}/out-{number}"
        batch.write.mode("overwrite").parquet(path)
        last[:] = [path]

    w.foreachBatch(put).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(last[0])


def tumbling(events: DataFrame, width: str = "1 hour") -> DataFrame:
    g = events.groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"))
    return g.select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "1 day", step: str = "6 hours") -> DataFrame:
    g = events.groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("value"))
    return g.select(F.col("window.start").alias("start"), "n", "value")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    g = events.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return g.select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def first_seen(events: DataFrame, late: str = "2 days") -> DataFrame:
    """The first event of each user, type and hour within the watermark; later copies are dropped."""
    return events.withWatermark("ts", late).select("user_id", "event_type", F.timestamp_micros(F.floor(F.unix_micros("ts") / 3600000000) * 3600000000).alias("hour"), "ts").dropDuplicatesWithinWatermark(["user_id", "event_type", "hour"]).select("user_id", "event_type", "hour")


def closed_windows(events: DataFrame, width: str = "1 day", late: str = "1 day") -> DataFrame:
    """Windows given out once the watermark has passed them; rows later than that are dropped."""
    g = events.withWatermark("ts", late).groupBy(F.window("ts", width)).agg(F.count("*").alias("n"))
    return g.select(F.col("window.start").alias("start"), "n")


def enriched(events: DataFrame, users: DataFrame) -> DataFrame:
    """Stream joined with a static table."""
    return events.join(users, events.user_id == users.uid).select("event_id", "user_id", "segment")


def fresh_counts(vectors: DataFrame) -> DataFrame:
    """Stateful buffer of arriving vectors per label: how many have come, and the smallest and largest id, kept across batches."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(key, batches, state):
        n, lo, hi = state.get if state.exists else (0, 1 << 62, -1)
        for b in batches:
            n, lo, hi = n + len(b), min(lo, int(b.vec_id.min())), max(hi, int(b.vec_id.max()))
        state.update((n, lo, hi))
        yield pd.DataFrame({"label": [key[0]], "n": [n], "first": [lo], "last": [hi]})

    rows = vectors.select("vec_id", "label")
    return rows.groupBy("label").applyInPandasWithState(step, "label int, n long, first long, last long", "n long, first long, last long", "update", GroupStateTimeout.NoTimeout)


def finished_last(stream: DataFrame, key: str) -> DataFrame:
    """An updating stream run to its end: the last row of each key."""
    spark = stream.sparkSession
    root = f"{scratch_dir(spark)}/streams/{uuid.uuid4().hex}"

    def put(batch: DataFrame, number: int) -> None:
        batch.withColumn("_batch", F.lit(number)).write.mode("append").parquet(f"{root}/out")

    w = stream.writeStream.outputMode("update").option("checkpointLocation", f"{root}/checkpoint").trigger(availableNow=True)
    w.foreachBatch(put).start().awaitTermination()
    rest = [c for c in stream.columns if c != key]
    rows = spark.read.parquet(f"{root}/out")
    return rows.groupBy(key).agg(F.max_by(F.struct(*rest), "_batch").alias("r")).select(key, *[F.col(f"r.{c}").alias(c) for c in rest])
