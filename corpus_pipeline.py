"""The corpus pipeline: quality, near duplicates, decontamination, mixing, token output.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet and read back as the next
stage's docs. All but the last return the columns of documents, whatever they are called; each works on whole rows, so that
extra columns travel along unread. An empty table stays empty through all stages. Repeated rows count each time.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from topkpaths.llm import common, decontaminate, ngram_join, quality_crf, source_mix, token_orc


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the line field rates good; it is fitted on the labelled documents among them.

    A null or empty text gets the smoothed share of good ones among such texts, one half without any, and stays if that reaches
    the threshold; without labels every document stays. A null id has no label and is judged like any other.
    """
    return quality_crf.keep_good(docs, quality_crf.train(docs, common.table(spark, sf_dir, "labels")))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: the one with the smallest id.

    Rows that share that id stay together; of a group of null ids alone one row stays; rows without words all stay.
    """
    return ngram_join.keep_one(docs)


def clean_of_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a passage of a test item; items with a null id count, items without words and null texts don't."""
    rows = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("row"))
    found = decontaminate.find(rows, common.table(spark, sf_dir, "benchmark"), carry=("row",), inside=("row", common.place_of(docs, "text")))
    return found.where(F.size("ranges") == 0).select("row.*")


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the source mix takes it; a null source is one of its own, the last.

    A text without words has no size: it stays as often as its source is taken whole, and once more if the seeded order takes it.
    """
    return source_mix.materialise(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The index of the written token files: doc_id, start, n_tokens, ids_crc32; a null id comes first, a null text has its end id alone."""
    return token_orc.tokens_of(docs)


STAGES = [
    ("quality", quality),
    ("near_duplicates", near_duplicates),
    ("decontaminate", clean_of_benchmark),
    ("mix", mixed),
    ("tokens", tokens),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage. What a stage wrote is deleted as soon as the next one has written its own."""
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        before, docs = docs, common.spill(stage(spark, docs, sf_dir), f"pipeline-{name}")
        common.release(before)
    return STAGES[-1][1](spark, docs, sf_dir)


#: The first stage is a fitted model: no SQL twin. tests/llm holds the stages against plain versions.
ORACLE_SQL = None
