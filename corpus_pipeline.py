"""From raw documents to packed training sequences.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and
reread as the next stage's documents. All stages but the last keep the columns of documents.

* quality: documents that the scorer rejects go.
* near_dedup: the first document of each near-duplicate class (five-word shingles,
  similarity 0.8) stays.
* decontaminate: documents that hold a benchmark item within the edit budget go.
* secrets: every secret is replaced by a mask; no document goes.
* packing: what is left becomes pieces of sequences of 4096 tokens.

Defined cases: null and empty texts are rejected by the first stage (later ones would keep
them); repeated rows leave one after the second; ties between copies go to the smallest
doc_id; an empty table gives no piece; more columns, whatever their names, pass through all
stages but the last.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from rotquant.llm.common import table, written
from rotquant.llm.decontaminate import without_benchmark
from rotquant.llm.neardup import one_of_each
from rotquant.llm.packing import pack
from rotquant.llm.quality import good_documents
from rotquant.llm.secrets import redacted


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return good_documents(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return one_of_each(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return without_benchmark(docs, table(spark, sf_dir, "benchmark", "item_id", "text"))


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return redacted(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack(docs)


STAGES = [("quality", quality), ("near_dedup", near_dedup), ("decontaminate", decontaminate), ("secrets", secrets), ("packing", packing)]
#: Encoding, near-duplicate classes and the trained scorer cannot be said in SQL; tests hold run() against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = written(docs)
    return docs
