"""The corpus pipeline: quality filter, near-duplicates, benchmark passages, personal data, token ids.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and read again
as the docs of the next one. All but the last return the columns of documents.

All stages take rows as they are: nulls in any column, repeated rows, empty tables and further columns do not stop
them, and what each makes of them is stated there and in the module of its operator.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sitereach.llm import bytebpe, decontaminate, linear, neardup, personal, store


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go (score below 0.5).

    Null and empty texts have the score of the bias; rows with a null doc_id are judged like any other; without a
    label every score is 0.5 and all rows stay; columns are kept as they are.
    """
    return linear.kept(docs, linear.fit_quality(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")), 0.5)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group stays, that of the smallest doc_id: five-word shingles, similarity 0.8 or more.

    Rows with a null doc_id and texts without a word are linked with nothing and stay; repeated rows of the doc_id
    that stays all stay, as they are one document.
    """
    return neardup.deduplicated(docs, 5, 80)


def benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go (0.8 of its five-word shingles).

    Null and empty texts, on either side, match nothing; items without an id count; an empty benchmark keeps all rows.
    """
    return decontaminate.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data in the texts is replaced by its kind, and n_chars counted again where a text has changed.

    Null and empty texts stay as they are; rows with null or repeated doc_ids are treated one by one.
    """
    return personal.redacted(docs)


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each document, and the digest of the bytes that they decode to (of no bytes for null and empty texts)."""
    return bytebpe.encode_decode(docs).select("doc_id", F.size("ids").cast("long").alias("n_tokens"), "ids", F.sha2("decoded", 256).alias("decoded_sha256"))


STAGES = [("quality", quality), ("near_duplicates", near_duplicates), ("benchmark_passages", benchmark_passages), ("personal_data", personal_data), ("token_ids", token_ids)]
#: SQL can express neither the trained classifier nor the encoder.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = store.cut_and_free(stage(spark, docs, sf_dir), name)
    return docs
