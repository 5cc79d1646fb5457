"""Line dedup by the number of different sites that a line appears on.

Lines (trimmed of ASCII spaces, at least MIN_CHARS long) are hashed; a HyperLogLog sketch of the sites per
hash is built in each map task and merged by aggregation. Lines whose estimate is surely under the threshold
stay, those surely over it are boilerplate; for lines within BAND standard errors of it the different sites
are counted exactly. A boilerplate line stays in its first place (smallest doc_id, first there) and goes
everywhere else, so no text is lost from the corpus as a whole.

The boilerplate list is broadcast only up to BROADCAST lines; beyond that places to cut are found by a join
on the row itself (doc_id and a SHA-256 of its text), so both ways cut the same lines of the same rows.

Defined cases: a null site counts as one site of its own; a null text stays null and has no lines; short and
blank lines always stay; a document may end up empty but is never dropped; of repeated rows with one doc_id
each keeps its first such line; a null doc_id is never a line's first place if another has it.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecgraph.session import materialize, ship

from .common import column, fresh, small

#: Sites from which on a line is boilerplate; least length of a line that can be.
MIN_SITES, MIN_CHARS = 10, 16
#: log2 of the registers of a sketch; standard errors of the band that is counted exactly.
LG_K, BAND = 11, 5
#: Boilerplate lines (16 bytes each) that may be broadcast.
BROADCAST = 1_000_000


def line_key(line: Column) -> Column:
    return F.xxhash64(F.trim(line))


def row_key(text: Column) -> Column:
    """What tells rows with one doc_id (or none) apart; equal rows have the same lines cut."""
    return F.unhex(F.sha2(text.cast("string"), 256))


def lines(docs: DataFrame, min_chars: int, *more: str) -> DataFrame:
    """(doc_id, pos, h, site) of every line that can be boilerplate, and further columns of its row."""
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.concat(F.lit("s"), F.col("source").cast("string")), F.lit("")).alias("site"), F.col("text").cast("string").alias("text"), *more)
    each = d.select("doc_id", "site", *more, F.posexplode(F.split("text", "\n", -1)).alias("pos", "line")).where(F.length(F.trim("line")) >= min_chars)
    return each.select("doc_id", "pos", line_key(F.col("line")).alias("h"), "site", *more)


def boilerplate(docs: DataFrame, min_sites: int = MIN_SITES, min_chars: int = MIN_CHARS) -> DataFrame:
    """(h, first): hashes of the lines on min_sites or more different sites, with their smallest doc_id."""
    each = lines(docs, min_chars)
    spread = each.groupBy("h").agg(F.hll_sketch_agg(F.xxhash64("site"), LG_K).alias("sketch"), F.min("doc_id").alias("first"), F.count("*").alias("rows"))
    guess = spread.where(F.col("rows") >= min_sites).select("h", "first", F.hll_sketch_estimate("sketch").alias("sites"))
    error = BAND * 1.04 / 2 ** (LG_K / 2)
    guess = materialize(guess.where(F.col("sites") >= int(min_sites * (1 - error))))
    near = guess.where(F.col("sites") <= int(min_sites * (1 + error)) + 1)
    exact = each.join(near.select("h"), "h").groupBy("h", "site").agg(F.lit(1).alias("one")).groupBy("h").agg(F.count("*").alias("exact"))
    return guess.join(exact, "h", "left").where(F.coalesce("exact", "sites") >= min_sites).select("h", "first")


def _cut(text: str, where: set[int]) -> str:
    return "\n".join(x for i, x in enumerate(text.split("\n")) if i not in where)


def dedup_lines(docs: DataFrame, min_sites: int = MIN_SITES, min_chars: int = MIN_CHARS, id_col: str = "doc_id", out: tuple[str, str] = ("n_lines", "n_cut")) -> DataFrame:
    """All columns of docs with boilerplate cut from text, and the numbers of lines and of cut lines, named in `out`; these replace columns of docs with their names."""
    from pyspark.sql.types import LongType, StringType, StructField, StructType

    spark = docs.sparkSession
    ship(spark)
    known = materialize(boilerplate(docs.select(F.col(id_col).alias("doc_id"), "text", "source"), min_sites, min_chars))
    rows = docs.withColumn("text", F.col("text").cast("string")).drop(*out)
    schema = StructType([*rows.schema.fields, *(StructField(c, LongType()) for c in out)])

    def rewritten(b: pa.RecordBatch, texts: list, n: list, cut: list, names: list[str]) -> pa.RecordBatch:
        new = {"text": pa.array(texts, pa.string()), out[0]: pa.array(n, pa.int64()), out[1]: pa.array(cut, pa.int64())}
        return pa.RecordBatch.from_arrays([new[c] if c in new else column(b, c) for c in names], names)

    names = [f.name for f in schema.fields]
    if known.count() <= BROADCAST:
        first = spark.sparkContext.broadcast({r["h"]: r["first"] for r in known.collect()})

        def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            table, digest = first.value, xxhash.xxh64_intdigest
            for b in small(batches):
                texts, counts, cuts = [], [], []
                for doc, text in zip(column(b, id_col).to_pylist(), column(b, "text").to_pylist(), strict=True):
                    each = text.split("\n") if text is not None else []
                    seen, kept = set(), []
                    for line in each:
                        key = line.strip(" ")
                        if len(key) >= min_chars:
                            h = digest(key.encode(), 42)
                            h = h - (1 << 64) if h >> 63 else h
                            if h in table:
                                if table[h] != doc or h in seen:
                                    continue
                                seen.add(h)
                        kept.append(line)
                    texts.append("\n".join(kept) if len(kept) < len(each) else text)
                    counts.append(len(each))
                    cuts.append(len(each) - len(kept))
                yield rewritten(b, texts, counts, cuts, names)

        return rows.mapInArrow(scan, schema)

    keyed = docs.select(F.col(id_col).alias("doc_id"), "text", "source", row_key(F.col("text")).alias("row"))
    where = lines(keyed, min_chars, "row").join(known, "h")
    ahead = where.groupBy("doc_id", "row", "h", "first").agg(F.collect_set("pos").alias("at"))
    gone = ahead.select("doc_id", "row", F.when(F.col("first").eqNullSafe(F.col("doc_id")), F.array_except("at", F.array(F.array_min("at")))).otherwise(F.col("at")).alias("at"))
    cut_id, cut_row, cut_at = fresh(docs.columns, "cut_id", "cut_row", "cut_at")
    gone = gone.groupBy(F.col("doc_id").alias(cut_id), F.col("row").alias(cut_row)).agg(F.flatten(F.collect_list("at")).alias(cut_at))
    joined = rows.join(gone, F.col(id_col).eqNullSafe(F.col(cut_id)) & (row_key(F.col("text")) == F.col(cut_row)), "left").drop(cut_id, cut_row)

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            at, texts = column(b, cut_at).to_pylist(), column(b, "text").to_pylist()
            counts = [t.count("\n") + 1 if t is not None else 0 for t in texts]
            cut = [set(a or ()) for a in at]
            yield rewritten(b, [_cut(t, w) if w else t for t, w in zip(texts, cut, strict=True)], counts, list(map(len, cut)), names)

    return joined.mapInArrow(apply, schema)


def dedup_digest(docs: DataFrame) -> DataFrame:
    """(doc_id, n_lines, n_cut, kept_sha256)."""
    found = dedup_lines(docs.select("doc_id", "text", "source"))
    return found.select("doc_id", "n_lines", "n_cut", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))

