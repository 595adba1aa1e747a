"""From documents to packed sequences: five stages, each on all that the one before has kept.

Every stage is a function (spark, docs, sf_dir) -> DataFrame; run() writes its result as Parquet to
shared scratch and reads it again, so a lost executor costs a stage's tasks at most. All but the last
return the columns of ``documents``. Null and empty texts leave at the first stage (no letter); empty
tables pass through all stages; other columns are carried along unread.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coarsesample.llm import decontaminate, language_id, near_text, packing, quality
from coarsesample.runtime import materialize, read_table, ship_package


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language the compression classifier can tell."""
    ship_package(spark)
    dictionaries = language_id.train_dictionaries(docs.where(~language_id.held_out(F.col("doc_id"))))
    return docs.where(language_id.accepts(dictionaries)(F.col("text")))


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier scores 0.7 or more."""
    ship_package(spark)
    labels = read_table(spark, sf_dir, "labels").where(~language_id.held_out(F.col("doc_id")))
    return docs.where(quality.accepts(quality.train(docs, labels))(F.col("text")))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The first document of each group of near copies (five-word shingles, Jaccard 0.8 or more)."""
    ship_package(spark)
    kept = near_text.near_duplicates(docs, width=5, num=80, den=100).where("kept and doc_id is not null").select("doc_id")
    firsts = docs.join(kept.distinct(), "doc_id", "left_semi").dropDuplicates(["doc_id", "text"])
    return firsts.unionByName(docs.where("doc_id is null")).select(*docs.columns)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a benchmark item."""
    ship_package(spark)
    return decontaminate.drop_leaks(docs, read_table(spark, sf_dir, "benchmark")).select(*docs.columns)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of at most 2048 tokens, as pieces of documents with their ids."""
    ship_package(spark)
    return packing.pack(docs)


STAGES = [
    ("language ID", language),
    ("quality classifier", quality_filter),
    ("MinHash near-dedup", near_dedup),
    ("benchmark decontamination", decontamination),
    ("packing", pack),
]

#: Compression, a trained model and token ids can't be stated in SQL; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the whole documents table."""
    docs = read_table(spark, sf_dir, "documents")
    for number, (_, stage) in enumerate(STAGES):
        docs = materialize(stage(spark, docs, sf_dir), f"stage-{number}")
    return docs
