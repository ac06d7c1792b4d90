"""The corpus pipeline: five stages, each written as Parquet and read again as the next one's documents.

Every stage works on all rows its predecessor kept, on whole texts, and an empty table stays empty. Null texts count as empty and stay null.
Columns beyond those of documents are carried along, whatever their names.
"""
from __future__ import annotations

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession, functions as F

from metricspark.llm.common import discard, table, written
from metricspark.llm.decontaminate import drop_contaminated
from metricspark.llm.mixing import mixed
from metricspark.llm.queries import tokenizer_path, toxicity_model
from metricspark.llm.simhash import keep_one_of_each
from metricspark.llm.token_files import document_digests, write_token_file
from metricspark.llm.toxicity import drop_toxic


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose noisy-or score reaches 0.5 go. Empty texts stay; repeated rows and rows of one doc_id are judged each by its own text."""
    return drop_toxic(docs, toxicity_model(spark, sf_dir))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group linked at 0.8 over five-word shingles, found by ball hashing and by bands of minima, the rows of the smallest doc_id stay, and rows without a doc_id. Empty texts are one group."""
    return keep_one_of_each(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a passage of `benchmark` within the edit budget go; each row is judged by itself."""
    return drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, laid out in the mixed order; a null source is a source of its own, ties follow a hash of the row."""
    return mixed(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The token file in the order in which the mixing stage laid the documents out: by file, then by row.

    Documents that don't come from files have no such order and are written by doc_id.
    """
    try:
        laid = docs.select("doc_id", "text", F.col("_metadata.file_name").alias("f_"), F.col("_metadata.row_index").alias("n_"))
    except AnalysisException:
        return document_digests(write_token_file(docs, tokenizer_path()))
    return document_digests(write_token_file(laid, tokenizer_path(), order=["f_", "n_"]))


STAGES = [("toxicity", toxicity), ("near_duplicates", near_duplicates), ("decontamination", decontamination), ("mixing", mixing), ("tokens", tokens)]

#: The classifier, SimHash and tokenizer stages have no SQL; tests/llm hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    before = None
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
        if before is not None:
            discard(before)
        before = docs
    return docs
