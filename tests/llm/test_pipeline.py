"""The pipeline's stages: columns, decisions against the operators' brute force, and that clean documents stay."""

import pytest

pytest.importorskip("corpus_pipeline")

import brute  # noqa: E402
import corpus_pipeline  # noqa: E402
from test_operators import _components, _prints  # noqa: E402



def test_stages(spark, sf_dir, tmp_path):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    items = [(str(r.item_id), r.text) for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect()]
    columns, last = docs.columns, len(corpus_pipeline.STAGES) - 1
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        before = {r.doc_id: r for r in docs.collect()}
        out = stage(spark, docs, sf_dir)
        out.write.parquet(f"{tmp_path}/{i}")
        docs = spark.read.parquet(f"{tmp_path}/{i}")
        after = {r.doc_id: r for r in docs.collect()}
        if i < last:
            assert docs.columns == columns
        if name == "language ID":
            assert set(before) - set(after) == {k for k, r in before.items() if not any(c.isalpha() for c in r.text or "")}
        elif name == "line dedup":
            assert set(before) == set(after)
        elif name == "SimHash near-dedup":
            ids = sorted(before)
            up = _components(ids, _prints([before[k].text for k in ids]))
            assert set(after) == set(up.values())
        elif name == "benchmark decontamination":
            ids = sorted(before)
            hits = brute.contamination([before[k].text for k in ids], items)
            assert set(after) == {k for k, (_, h, _) in zip(ids, hits, strict=True) if not h}
        else:
            assert set(before) == set(after)
    assert sorted(r.doc_id for r in corpus_pipeline.run(spark, sf_dir).collect()) == sorted(after)


def test_clashing_columns_stay(spark, sf_dir):
    names = ["lang_pred", "score", "n_lines", "n_cut", "row", "row2", "all", "fp", "order"]
    rows = [(i, f"words of text number {i} " * (i + 1), "en", f"s{i}", 1, *range(len(names))) for i in range(5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{n}` long" for n in names))
    columns = docs.columns
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, sf_dir)
        assert docs.columns == columns
        kept = docs.collect()
        assert kept and all([r[n] for n in names] == list(range(len(names))) for r in kept)


def test_odd_rows(spark, tmp_path, sf_dir):
    passage = spark.read.parquet(f"{sf_dir}/benchmark.parquet").first().text
    rows = [(None, "the words of a text without an id and more", "en", "s", 1), (1, None, None, None, None), (2, "", "en", "s", 0), (3, "123", "de", "s", 3), (4, "a b c d e f g", "en", None, 1), (4, "a b c d e f g", "en", None, 1), (None, f"leak: {passage}", "en", "s", 2)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf_dir)
    assert sorted((r.doc_id is None, r.doc_id or 0) for r in docs.collect()) == [(False, 4), (True, 0)]
    empty = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in corpus_pipeline.STAGES:
        empty = stage(spark, empty, sf_dir)
    assert empty.count() == 0
