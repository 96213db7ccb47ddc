"""The corpus pipeline: language, quality, near-duplicates, repeated passages, packing.

Each stage takes (spark, docs, sf_dir) and works on all rows its predecessor kept; what
it returns is written as Parquet and read again as the next stage's ``docs``.  All but
the last return the columns of ``documents``.

* language_id rejects documents without any letter (``und``) and those whose greatest
  pooled language probability is under ``LANGUAGE_MARGIN`` times that of a guess among
  the learned languages (one language: none but ``und``), as evenly mixed texts have.
* quality rejects documents whose neighbour vote is under 0.7.
* near_dedup keeps the document with the smallest doc_id of each group (of rows that
  share a doc_id, each stays or goes with it); a row without doc_id stays.
* substring_dedup removes words of passages that an earlier document also has and sets
  n_chars anew; a document whose text changes keeps its row.
* packing returns one row per piece of a packed sequence.

Null texts hold no letter and go at the first stage, empty tables pass through empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eigenveil.llm.common import materialise, table
from eigenveil.llm.language_id import learn_and_identify
from eigenveil.llm.near_dedup import near_duplicates
from eigenveil.llm.packing import pack_documents
from eigenveil.llm.quality import learn_and_score
from eigenveil.llm.queries import vocabulary
from eigenveil.llm.substring_dedup import remove_repeats

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
LANGUAGE_MARGIN = 1.2
QUALITY_FLOOR = 0.7


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return learn_and_identify(docs.select(*COLUMNS), margin=LANGUAGE_MARGIN).where("accepted").select(*COLUMNS)


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    scored = learn_and_score(docs.select(*COLUMNS), table(spark, sf_dir, "labels"), threshold=QUALITY_FLOOR)
    return scored.where("predicted = 1").select(*COLUMNS)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    docs = docs.select(*COLUMNS)
    gone = near_duplicates(docs).where(~F.col("kept")).select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*COLUMNS)


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    cleaned = remove_repeats(docs.select(*COLUMNS), with_text=True)
    changed = F.col("n_removed") > 0
    return cleaned.withColumn("n_chars", F.when(changed, F.length("text").cast("long")).otherwise(F.col("n_chars"))).select(*COLUMNS)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack_documents(docs.select(*COLUMNS), vocabulary("byte_bpe_50k.json"))


STAGES = [("language_id", language_id), ("quality", quality), ("near_dedup", near_dedup), ("substring_dedup", substring_dedup), ("packing", packing)]

#: Learnt models and packing have no SQL form; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
