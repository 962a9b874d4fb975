"""A corpus pipeline of five stages over documents, each written and read again before the next.

Every stage judges rows, not ids: rows that share an id have verdicts of their own. Null and empty texts count as texts
without words. Columns that documents has beyond its own pass through, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from sessionlens.llm import content_store, decontaminate, mixing, similarity, toxicity
from sessionlens.llm.common import new_path


def toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go. It learns from the labelled rows of the stage's own input. A null or empty
    text has the score of the bias alone; without labels nothing goes."""
    weights = toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet").where(~toxicity.held_out()))
    return toxicity.without_toxic(docs, weights)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies (five-word shingles, similarity of 0.8 or more) one row stays, that of the least id. The
    SimHash index gives the first candidates; those that 64 bits can't tell come from shared shingles. Texts without words
    are one group."""
    return similarity.one_of_each(docs)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go; null and empty texts stay."""
    return decontaminate.without_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each source, null among them, is brought near its target: documents come as often as the mix takes them. A text
    without words is never taken."""
    return mixing.mixed_documents(docs)


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The ids of the mix in a content-addressed store, read back: a row for each document that came in. A null or empty text
    is the end id alone."""
    return content_store.read_back(content_store.write_store(docs)).drop("root")


STAGES = [("toxicity", toxic), ("near_copies", near_copies), ("decontamination", decontaminated), ("mixing", mixed), ("token_ids", token_ids)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        path = new_path(spark, name)
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs


#: Training and tokenizing have no SQL; tests hold the stages against brute force.
ORACLE_SQL = None
