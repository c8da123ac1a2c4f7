"""The pipeline over the smallest tables: each stage does its whole work, and packing keeps every document left."""

import pytest

pytest.importorskip("corpus_pipeline")

import corpus_pipeline  # noqa: E402
from hotgraph.llm.common import settle  # noqa: E402

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, counts = docs.columns, [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = settle(stage(spark, docs, SF), "stage")
        assert docs.columns == columns, name
        counts.append(docs.count())
    assert counts == sorted(counts, reverse=True) and counts[-1] > 0.5 * counts[0]
    out = corpus_pipeline.STAGES[-1][1](spark, docs, SF)
    assert {r.doc_id for r in out.collect()} == {r.doc_id for r in docs.collect()}


def test_stages_on_odd_rows(spark):
    rows = [(1, None, None, None, None), (2, "", "en", "s", 0), (2, "", "en", "s", 0), (None, "a text of its own kind", None, "s", 9), (3, "x " * 60_000, "en", "s", 1)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    for d in (docs, docs.limit(0)):
        for _, stage in corpus_pipeline.STAGES[:-1]:
            d = settle(stage(spark, d, SF), "stage")
        corpus_pipeline.STAGES[-1][1](spark, d, SF).count()


def test_run(spark):
    from hotgraph import storage

    before = len(storage._written)
    assert corpus_pipeline.run(spark, SF).count() > 0
    assert len(storage._written) <= before + 2  # the last stage's input and pieces


def test_ties_and_a_table_without_lengths(spark):
    """Of equal and near texts the smallest id stays, whatever the order of rows; columns are those of the table."""
    words = [f"w{k}" for k in range(200)]
    near = [" ".join(words[:k] + [f"x{k}"] + words[k + 1 :]) for k in (40, 90, 150)]
    rows = [(9, " ".join(words)), (4, " ".join(words)), (4, " ".join(words)), *zip((7, 2, 8), near, strict=True), (3, "other words than those")]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(3)
    near_dedup = dict(corpus_pipeline.STAGES)["SimHash near-dedup"]
    assert sorted(r.doc_id for r in near_dedup(spark, docs, SF).collect()) == [2, 3]
    cut = dict(corpus_pipeline.STAGES)["line dedup"](spark, docs, SF)
    assert cut.columns == docs.columns and sorted(r.doc_id for r in cut.where("text <> ''").collect()) == [2, 3, 4, 4, 7, 8]
