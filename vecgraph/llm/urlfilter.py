"""URL filters by a sort-merge range join.

A host is written with its labels reversed, each followed by a dot ("com.example.www."), so that a
rule's host and all its subdomains form one interval of the sorted keys. URLs and rules are dealt to
ranges of keys; a rule goes to every range its interval overlaps (at any key at most as many intervals
are open as a host has labels). Each range is sorted and swept once with a stack of the open, nested
rule hosts; rules of one host are looked up by path prefix.

Defined cases: a null URL or one without "://" has host "" and path ""; it meets only rules of host "".
Of the matching rules the longest (host and path) wins; equally long ones: the longer host. A rule
given twice with both verdicts blocks. Repeated rows stay repeated rows. Empty tables give empty results.
Without a matching rule the verdict is `default` ("allow").
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecgraph.session import ship, shuffle_partitions

from .common import column

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Sampled keys for each range of keys.
SAMPLE_PER_RANGE = 200
LAST = "\U0010ffff"


def url_host(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")), UPPER, LOWER)


def url_path(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def reversed_host(host: Column) -> Column:
    """"www.example.com" -> "com.example.www."; the empty host has the empty key."""
    return F.when(host == "", F.lit("")).otherwise(F.concat(F.array_join(F.reverse(F.split(host, r"\.")), "."), F.lit(".")))


class Sweep:
    """The stack of open rule hosts while keys pass in ascending order."""

    def __init__(self) -> None:
        self.stack: list[tuple[str, str, dict[str, str], list[int]]] = []

    def close_before(self, key: str) -> None:
        while self.stack and not key.startswith(self.stack[-1][0]):
            self.stack.pop()

    def open_rule(self, key: str, host: str, path: str, verdict: str) -> None:
        self.close_before(key)
        if not self.stack or self.stack[-1][0] != key:
            self.stack.append((key, host, {}, []))
        _, _, paths, lengths = self.stack[-1]
        paths[path] = verdict
        if len(path) not in lengths:
            lengths.append(len(path))
            lengths.sort(reverse=True)

    def match(self, key: str, path: str) -> tuple[str, str] | None:
        self.close_before(key)
        best = None
        for _, host, paths, lengths in self.stack:
            for n in lengths:
                if n <= len(path) and (verdict := paths.get(path[:n])) is not None:
                    if best is None or (len(host) + n, len(host)) > best[0]:
                        best = (len(host) + n, len(host)), host + path[:n], verdict
                    break
        return best and best[1:]


def url_filter(pages: DataFrame, rules: DataFrame, id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """pages(id, url), rules(host, path, verdict) -> (id, host, path, rule, verdict), one row per page row."""
    spark = pages.sparkSession
    ship(spark)
    url = F.col(url_col).cast("string")
    urls = pages.select(F.col(id_col).cast("long").alias("id"), url_host(url).alias("host"), url_path(url).alias("path"))
    urls = urls.withColumn("key", reversed_host(F.col("host")))
    host = F.translate(F.coalesce(F.col("host").cast("string"), F.lit("")), UPPER, LOWER)
    clean = rules.select(host.alias("host"), F.coalesce(F.col("path").cast("string"), F.lit("")).alias("path"), F.col("verdict").cast("string").alias("verdict"))
    clean = clean.where("verdict in ('allow', 'block')").groupBy("host", "path").agg(F.max("verdict").alias("verdict")).withColumn("key", reversed_host(F.col("host")))

    ranges = shuffle_partitions(spark)
    fraction = min(1.0, SAMPLE_PER_RANGE * ranges / max(1, pages.count()))
    keys = sorted(r[0] for r in urls.select("key").sample(fraction, seed=7).collect())
    bounds = [keys[len(keys) * i // ranges] for i in range(1, ranges)] if keys else []

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            part = []
            for i, key in enumerate(column(b, "key").to_pylist()):
                lo, hi = bisect_left(bounds, key), bisect_right(bounds, key)
                part.append(lo + i % (hi - lo + 1))  # a hot host fills several whole ranges
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), *b.columns], ["part", *b.schema.names])

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [(part, i) for i, key in enumerate(column(b, "key").to_pylist()) for part in range(bisect_left(bounds, key), bisect_right(bounds, key + LAST) + 1)]
            take = b.take(pa.array([i for _, i in rows], pa.int64()))
            yield pa.RecordBatch.from_arrays([pa.array([p for p, _ in rows], pa.int32()), *take.columns], ["part", *take.schema.names])

    def sweep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, state = None, Sweep()
        for b in batches:
            ids, hosts, paths, names, verdicts = [], [], [], [], []
            cols = (column(b, c).to_pylist() for c in ("part", "key", "id", "host", "path", "verdict"))
            for part, key, page, h, path, verdict in zip(*cols, strict=True):
                if part != at:
                    at, state = part, Sweep()
                if verdict is not None:
                    state.open_rule(key, h, path, verdict)
                    continue
                found = state.match(key, path)
                ids.append(page)
                hosts.append(h)
                paths.append(path)
                names.append(found[0] if found else None)
                verdicts.append(found[1] if found else default)
            kinds = (pa.int64(), pa.string(), pa.string(), pa.string(), pa.string())
            yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip((ids, hosts, paths, names, verdicts), kinds, strict=True)], ["id", "host", "path", "rule", "verdict"])

    schema = "part int, id long, host string, path string, key string, verdict string"
    dealt = urls.withColumn("verdict", F.lit(None).cast("string")).select("id", "host", "path", "key", "verdict").mapInArrow(deal, schema)
    laid = clean.select(F.lit(None).cast("long").alias("id"), "host", "path", "key", "verdict").mapInArrow(spread, schema)
    both = dealt.unionByName(laid).repartitionById(ranges, F.col("part")).sortWithinPartitions("part", "key", F.col("verdict").isNull())
    return both.mapInArrow(sweep, "id long, host string, path string, rule string, verdict string").withColumnRenamed("id", id_col)
