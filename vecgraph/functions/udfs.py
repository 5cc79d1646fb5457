"""Functions for SQL: encoding and distances as vectorized scalars, a mean of vectors, chunks as a table function."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecgraph.operators.quantize import Quantizer
from vecgraph.operators.walk import assemble, searcher
from vecgraph.session import ship


def register(spark: SparkSession, model: Quantizer) -> None:
    """pq_encode(vec), adc_distance(lut, code), vector_mean(vec), subvectors(vec, width), expand_neighbours(nbrs)."""
    ship(spark)

    @F.pandas_udf("array<int>")
    def pq_encode(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for v in parts:
            yield pd.Series(list(model.encode(np.array(v.tolist(), float)).astype(np.int32))) if len(v) else pd.Series([], dtype=object)

    @F.pandas_udf("double")
    def adc_distance(lut: pd.Series, code: pd.Series) -> pd.Series:
        return pd.Series([float(sum(row[k] for row, k in zip(t, c, strict=True))) for t, c in zip(lut, code, strict=True)])

    @F.pandas_udf("array<double>")
    def vector_mean(v: pd.Series) -> np.ndarray:
        return np.mean(np.array(v.tolist(), float), 0)

    @F.udtf(returnType="chunk int, sub array<double>")
    class Subvectors:
        def eval(self, vec: list, width: int):
            for j in range(0, len(vec), width):
                yield j // width, vec[j : j + width]

    @F.udtf(returnType="place int, dst long")
    class ExpandNeighbours:
        def eval(self, nbrs: list):
            for i, v in enumerate(nbrs or ()):
                yield i, v

    spark.udtf.register("expand_neighbours", ExpandNeighbours)
    for name, f in (("pq_encode", pq_encode), ("adc_distance", adc_distance), ("vector_mean", vector_mean)):
        spark.udf.register(name, f)
    spark.udtf.register("subvectors", Subvectors)


#: Rows of an index that a table function may hold in each task; larger ones are searched by `walk.beam_search`.
FUNCTION_ROWS = 200_000


def register_search(spark: SparkSession, index: DataFrame, model: Quantizer, name: str = "ann_search") -> None:
    """ann_search(id, vec, k, h) -> (rank, vid, d2, hops): code-only walks over one stored index, for SQL's LATERAL. The index is
    broadcast, so it is refused if it has several shards or more than FUNCTION_ROWS rows."""
    ship(spark)
    size = index.agg(F.count("*").alias("n"), F.max("shard").alias("last")).first()
    if size.n > FUNCTION_ROWS or (size.last or 0) > 0:
        raise ValueError(f"ann_search holds an index of one shard and {FUNCTION_ROWS} rows at most, not {size.n}")
    held = spark.sparkContext.broadcast(assemble(index.drop("vec").toArrow()))

    @F.udtf(returnType="rank int, vid long, d2 double, hops long")
    class AnnSearch:
        def eval(self, number: int, vec: list, k: int, h: int):
            kernel = searcher(k, "code_only", model)
            for b in kernel(held.value, np.array([number], np.int64), np.array([vec], float), h):
                for i, (v, d, hops) in enumerate(zip(*(b.column(c).to_pylist() for c in (1, 2, 3)), strict=True)):
                    yield i + 1, v, d, hops

    spark.udtf.register(name, AnnSearch)
