"""Sinks and sources in the shared scratch folder."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame

from vecgraph.session import scratch_dir


def round_trip(df: DataFrame, kind: str) -> DataFrame:
    """Write in a file format and read back with the same schema."""
    path = f"{scratch_dir(df.sparkSession)}/tables/{uuid.uuid4().hex}"
    df.write.format(kind).save(path)
    return df.sparkSession.read.format(kind).schema(df.schema).load(path)


def partitioned(df: DataFrame, *by: str) -> DataFrame:
    """Written partitioned by columns; filters on them read only their folders."""
    path = f"{scratch_dir(df.sparkSession)}/tables/{uuid.uuid4().hex}"
    df.write.partitionBy(*by).parquet(path)
    return df.sparkSession.read.parquet(path)


def version(df: DataFrame, root: str, number: int) -> str:
    """A table's version as a folder of its own; readers name the version, so a write never changes what they read."""
    path = f"{root.rstrip('/')}/v={number:06d}"
    df.write.parquet(path)
    return path
