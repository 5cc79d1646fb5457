"""An index that takes inserts and deletes: a large graph, a small exact delta, a delete list, and merges."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecgraph.session import materialize

from .exact import exact_knn, top


@dataclass(frozen=True)
class FreshIndex:
    """search_main(queries, k) answers from the large index; delta holds rows not merged yet; deleted holds ids (vid)."""

    base: DataFrame
    search_main: Callable[[DataFrame, int], DataFrame]
    delta: DataFrame
    deleted: DataFrame
    rebuild: Callable[[DataFrame], Callable[[DataFrame, int], DataFrame]]

    def insert(self, rows: DataFrame) -> FreshIndex:
        back = self.deleted.join(rows.select(F.col("id").alias("vid")), "vid", "left_anti")
        return replace(self, delta=self.delta.join(rows, "id", "left_anti").unionByName(rows), deleted=back)

    def delete(self, ids: DataFrame) -> FreshIndex:
        gone = ids.select("vid")
        return replace(self, delta=self.delta.join(gone.withColumnRenamed("vid", "id"), "id", "left_anti"), deleted=self.deleted.unionByName(gone).distinct())

    def search(self, queries: DataFrame, k: int, slack: int) -> DataFrame:
        """(qid, rank, vid, d2): up to `slack` more answers are asked of the large index, so that deleted ones can go. Of an exact index
        a longer list begins with the shorter one, so lists are asked twice as long only for queries that have fewer than k left."""
        gone = self.deleted.select("vid").unionByName(self.delta.select(F.col("id").alias("vid"))).distinct()
        width, most, left, main = k + min(slack, k), k + slack, queries, None
        while True:
            got = self.search_main(left, width).select("qid", "vid", "d2").join(gone, "vid", "left_anti").select("qid", "vid", "d2")
            if width < most:
                got = materialize(got)
                done = got.groupBy("qid").agg(F.count("*").alias("n")).where(F.col("n") >= k).select("qid")
                left = materialize(left.join(done.withColumnRenamed("qid", "id"), "id", "left_anti"))
                got = got.join(done, "qid", "left_semi")
            main = got if main is None else main.unionByName(got)
            if width >= most or left.isEmpty():
                break
            width = min(most, 2 * width)
        new = exact_knn(self.delta, queries, k).select("qid", "vid", "d2")
        return top(main.unionByName(new), k).select("qid", "rank", "vid", "d2")

    def merge(self) -> FreshIndex:
        """Fold delta and deletes into a new large index."""
        kept = self.base.join(self.deleted.withColumnRenamed("vid", "id"), "id", "left_anti").join(self.delta.select("id"), "id", "left_anti")
        base = materialize(kept.unionByName(self.delta))
        return FreshIndex(base, self.rebuild(base), self.delta.limit(0), self.deleted.limit(0), self.rebuild)
