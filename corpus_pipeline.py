"""The corpus pipeline: toxicity, line dedup, SimHash near-dedup, benchmark decontamination, best-fit packing."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotgraph.llm import decontaminate, linededup, packing, simhash, toxicity, widesimhash
from hotgraph.llm.common import read, settle
from hotgraph.llm.queries import tokenizer_path
from hotgraph.storage import cleared, discard


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score is below one half."""
    model = toxicity.train(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))
    return toxicity.keep_clean(docs, model)


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the lines that a document of smaller id holds; n_chars follows the text."""
    bitmaps = settle(linededup.keep_bitmaps(docs), "bitmaps")
    cut = linededup.apply_bitmaps(docs, bitmaps)
    return cut.withColumn("n_chars", F.length("text").cast("bigint")) if "n_chars" in docs.columns else cut


def dedup_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies (five-word shingles, similarity 0.8 or more) the document with the smallest id."""
    return simhash.keep_first(docs, widesimhash.similar(docs, words=5, similarity=0.8))


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no window of a benchmark item."""
    return decontaminate.keep_clean(docs, read(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents and their places in sequences."""
    return packing.packed(docs, tokenizer_path())


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", drop_toxic),
    ("line dedup", dedup_lines),
    ("SimHash near-dedup", dedup_near),
    ("benchmark decontamination", decontaminated),
    ("best-fit packing", pack),
]

#: The learnt scores, near copies and packing of the stages are not expressible in SQL; tests hold them to brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written and read again; a stage's own tables and its input go when it is written."""
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        with cleared(spark) as kept:
            found = settle(stage(spark, docs, sf_dir), name.replace(" ", "-"))
            kept.append(found)
        discard(docs)
        docs = found
    return STAGES[-1][1](spark, docs, sf_dir)
