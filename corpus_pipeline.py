"""A training-data pipeline over `documents`: each stage's rows, written and read again, are the next stage's input.

Toxic documents go; boilerplate lines go from all documents but their first; one document of each near-duplicate group
stays; documents that hold a benchmark passage go; the rest is encoded and decoded.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from geoprobe.llm import bpe, decontamination, line_dedup, near_dedup, toxicity
from geoprobe.llm.common import checkpointed, load, swept, tables_written


def toxic_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.without_toxic(docs, load(spark, sf_dir, "labels", "doc_id", "toxic"))


def boilerplate_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return line_dedup.without_boilerplate(docs).select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dedup.deduplicated(docs)


def benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontamination.decontaminated(docs, load(spark, sf_dir, "benchmark", "item_id", "text"))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe.token_digests(docs)


STAGES = [
    ("toxicity", toxic_documents),
    ("line_dedup", boilerplate_lines),
    ("minhash_near_dedup", near_duplicates),
    ("benchmark_decontamination", benchmark_passages),
    ("bpe_encoding", tokens),
]
#: The toxicity classifier and the sketches can't be said in SQL; a brute-force version tests the stages.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order over the documents of `sf_dir`; the rows between stages are Parquet tables in the shared checkpoint
    folder, each of which goes once the next is written."""
    docs, mark = load(spark, sf_dir, "documents"), tables_written()
    for _, stage in STAGES[:-1]:
        docs = swept(checkpointed(stage(spark, docs, sf_dir)), mark)
    return STAGES[-1][1](spark, docs, sf_dir)


QUERIES = {"pipeline": run}
ORACLE_SQLS: dict[str, str] = {}
