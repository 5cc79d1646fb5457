"""The corpus pipeline: five stages over documents, each applying one operator to all its predecessor kept.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame with the columns of documents; the last
returns one row per document with its tokens' digest. Stages judge rows, not ids: rows without an id, or with
the id of another row, are kept or go by their own text. Columns of documents named like an operator's stay.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecgraph.llm import bpe, decontaminate, langid, linededup, simhash
from vecgraph.llm.common import ROW, fresh, row_keys, table
from vecgraph.llm.queries import VOCABULARY
from vecgraph.session import materialize


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a language (no text, or no letters) go."""
    model = langid.fit(docs.where(~langid.held_out(F.col("doc_id"))))
    found, score = fresh(docs.columns, "lang_pred", "score")
    return langid.predict(docs, model, out=(found, score)).where(F.col(found) != langid.UND).select(*docs.columns)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cross-site boilerplate lines stay in their first place only; n_chars follows the text."""
    lines, gone = fresh(docs.columns, "n_lines", "n_cut")
    cut = linededup.dedup_lines(docs, out=(lines, gone))
    n = F.when(F.col(gone) > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))
    return cut.withColumn("n_chars", n).select(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates the document with the smallest id stays; of repeated rows one."""
    return simhash.one_of_each(docs, shingle=4, distance=4)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go."""
    found = decontaminate.matches(decontaminate.build_index(docs), table(spark, sf_dir, "benchmark"))
    keys = fresh(docs.columns, *ROW)
    gone = materialize(found.select(*(F.col(r).alias(k) for r, k in zip(ROW, keys, strict=True))))
    return docs.select("*", *row_keys(names=keys)).join(gone, keys, "left_anti").select(*docs.columns)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe.encode_digest(docs, VOCABULARY)


STAGES = [("language ID", language), ("line dedup", line_dedup), ("SimHash near-dedup", near_dedup), ("benchmark decontamination", decontamination), ("BPE encoding", tokens)]

#: The stages' models and sketches are beyond SQL; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each stage's result is written and reread, so no later stage computes it again."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
