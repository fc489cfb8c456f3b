"""Corpus pipeline over `documents`: language ID, line dedup, n-gram Jaccard join, mixing, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the
columns of documents. A stage's result is written as Parquet and read again as the next
stage's docs, so a lost executor costs at most the stage that runs.

- language_id: documents whose language is unknown or scored under 0.3 go.
- line_dedup: lines that repeat an earlier line of the corpus (up to one edit per 25
  characters, one at least) go from the texts; documents stay, also when little or nothing is left
  of them.
- jaccard_join: of documents that are near copies (five-word shingles, similarity 0.8 or
  more) the one with the least doc_id stays.
- mixing: documents without a word go first (since stage one only passes texts with a
  letter, these are the ones whose lines were all removed, copies of earlier documents
  among them); then sources are brought to their target weights; documents taken more than once
  appear as repeated rows, a fraction as the start of a document's text.
- packing: one row per piece of a packed token sequence.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stagefilter.llm.common import ensure_checkpoint_dir, table
from stagefilter.llm.jaccard import JaccardJoin, one_per_class
from stagefilter.llm.langid import accepted
from stagefilter.llm.linededup import GROWING, has_word, without_repeated_lines
from stagefilter.llm.mixing import mixed_documents
from stagefilter.llm.packing import pack

NEAR = JaccardJoin(n=5, percent=80)


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return accepted(docs)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return without_repeated_lines(docs, GROWING)


def jaccard_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return one_per_class(docs, NEAR)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixed_documents(docs.filter(has_word(F.col("text"))))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack(docs)


STAGES = [
    ("language_id", language_id),
    ("line_dedup", line_dedup),
    ("jaccard_join", jaccard_join),
    ("mixing", mixing),
    ("packing", packing),
]

#: SQL can't express the network, the edit join or the tokenizer; tests/llm compares run() with a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    ensure_checkpoint_dir(spark)
    folder = f"{spark.sparkContext.getCheckpointDir()}/pipeline-{uuid.uuid4().hex}"
    docs = table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs.write.parquet(f"{folder}/{i}-{name}")
            docs = spark.read.parquet(f"{folder}/{i}-{name}")
    return docs
