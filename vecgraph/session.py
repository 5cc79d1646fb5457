"""Session helpers: shipping the package to executors, shared scratch tables."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile

from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()
_MADE: list[str] = []
_TABLES: list[str] = []
#: What holds tables made by `materialize` or `bucketed` for later calls, and has to forget them when they are cleared.
CACHES: list[dict] = []


def ship(spark: SparkSession) -> None:
    """Make this package importable in Python workers, once per application."""
    sc = spark.sparkContext
    if sc.applicationId in _SHIPPED:
        return
    root = os.path.dirname(os.path.abspath(__file__))
    target = os.path.join(tempfile.mkdtemp(prefix="vecgraph-"), "vecgraph_pkg.zip")
    with zipfile.ZipFile(target, "w") as z:
        for folder, _, names in os.walk(root):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    z.write(full, os.path.join("vecgraph", os.path.relpath(full, root)))
    sc.addPyFile(target)
    _SHIPPED.add(sc.applicationId)


def scratch_dir(spark: SparkSession) -> str:
    """The shared folder named by spark.checkpoint.dir; a local one only where none is set and all tasks run in this process' machine (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        named = "file://" + tempfile.mkdtemp(prefix="vecgraph-checkpoint-")
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


def materialize(df: DataFrame, group: int | None = None) -> DataFrame:
    """Write a table into the shared scratch folder and read it back: cuts lineage, survives lost executors. `group`: bytes that a
    row group holds, looked at after each row, for tables of few and large rows: a writer keeps, and a reader gets, whole row groups,
    and the size of one is otherwise looked at after a hundred rows only."""
    path = f"{scratch_dir(df.sparkSession)}/tables/{uuid.uuid4().hex}"
    small = {} if group is None else {"parquet.block.size": group, "parquet.page.size.row.check.min": 1, "parquet.page.size.row.check.max": 1}
    df.write.options(**small).parquet(path)
    _MADE.append(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def bucketed(df: DataFrame, key: str, buckets: int) -> DataFrame:
    """Write a table into the shared scratch folder, its rows dealt to buckets by `key`, and read it back: groups and joins by
    `key` then read it in place, however often, without another shuffle."""
    spark, name = df.sparkSession, f"vecgraph_{uuid.uuid4().hex}"
    path = f"{scratch_dir(spark)}/tables/{name}"
    df.repartition(buckets, key).write.format("parquet").bucketBy(buckets, key).option("path", path).saveAsTable(name)
    _MADE.append(path)
    _TABLES.append(name)
    return spark.table(name)


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def clear_scratch(spark: SparkSession) -> int:
    """Delete the tables that `materialize` and `bucketed` have written in this process; call it when no result that reads them is needed any more."""
    jvm, n = spark._jvm, 0
    for name in _TABLES:
        spark.sql(f"DROP TABLE IF EXISTS {name}")
    _TABLES.clear()
    for cache in CACHES:
        cache.clear()
    for path in _MADE:
        p = jvm.org.apache.hadoop.fs.Path(path)
        n += bool(p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True))
    _MADE.clear()
    return n
