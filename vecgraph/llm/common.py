"""What several operators need: table access and Arrow column helpers."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from vecgraph.session import ship


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def id_text(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Only the two columns an operator reads, so further columns can't clash and are pruned."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


#: What tells rows apart, whatever their ids are: two hashes of id and text.
ROW = ["row", "row2"]


def row_keys(id_col: str = "doc_id", text_col: str = "text", names: list[str] = ROW) -> list[Column]:
    number, text = F.col(id_col).cast("long"), F.col(text_col).cast("string")
    return [F.xxhash64(number, text).alias(names[0]), F.xxhash64(F.lit(1), text, number).alias(names[1])]


def fresh(taken: list[str], *names: str) -> list[str]:
    """The names, each with underscores added until no column has it (in any case)."""
    used, out = {c.lower() for c in taken}, []
    for n in names:
        while n.lower() in used:
            n += "_"
        used.add(n.lower())
        out.append(n)
    return out


def column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def raw(batch: pa.RecordBatch, name: str = "text") -> list:
    """Strings of an Arrow column as UTF-8 bytes (None where null), without decoding them."""
    col = column(batch, name)
    return col.cast(pa.large_binary() if pa.types.is_large_string(col.type) else pa.binary()).to_pylist()


def strings(batch: pa.RecordBatch, name: str = "text") -> list:
    return column(batch, name).to_pylist()


def slices(n: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
    """Cut a list of sizes into runs whose sum is at most `most` (or of one element)."""
    ends, lo = np.cumsum(n), 0
    while lo < len(n):
        hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + most, "right")))
        yield lo, hi
        lo = hi


#: What a worker keeps from task to task, by operator.
_KEPT: dict[str, dict] = {}


def kept(operator: str, key, make: Callable):
    """A model or table that a worker keeps for its next tasks, until it works for another operator."""
    turn(operator)
    own = _KEPT.setdefault(operator, {})
    if key not in own:
        own[key] = make()
    return own[key]


def turn(operator: str | None) -> None:
    """Workers outlive stages: what this one has kept for other operators goes, back to the system."""
    others = [o for o in _KEPT if o != operator]
    for o in others:
        del _KEPT[o]
    if others:
        pa.default_memory_pool().release_unused()
        try:
            ctypes.CDLL("libc.so.6").malloc_trim(0)
        except (OSError, AttributeError):  # another C library
            pass


def small(batches: Iterator[pa.RecordBatch], name: str = "text", most: int = 4 << 20, operator: str | None = None) -> Iterator[pa.RecordBatch]:
    """Batches cut so that their texts hold `most` bytes (or are one row): what a worker decodes at once is bounded. `operator`: whose
    `kept` tables stay."""
    turn(operator)
    for b in batches:
        size = pc.fill_null(pc.binary_length(column(b, name)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        for lo, hi in slices(size, most):
            yield b.slice(lo, hi - lo)
