"""Quality rules, quality classifier, near-duplicates, mixing, packing: documents to training sequences.

Each stage gets what its predecessor kept, written and read again in between. All
but the last return the columns of ``documents``; the last returns packed pieces.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecroute.llm import boosting, fertility, mixing, packing, simhash
from vecroute.runtime import Workspace, ship, table


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops what the base rules or the fertility bands reject."""
    ship(spark)
    return docs.where(fertility.kept(F.col("text"), F.col("lang")))


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops what the boosted trees score below the threshold.

    They learn from labelled documents of the whole table, since the rows that the
    rules keep may all have one label; only the incoming rows are scored.
    """
    ship(spark)
    model = boosting.train(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return docs.where(boosting.score(F.col("text"), model) >= boosting.THRESHOLD)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group of near-duplicates."""
    ship(spark)
    return simhash.keep_one(docs)


def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Puts the documents in the order of the scheduled mixture."""
    return mixing.mixed_order(docs)


def tiered_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs the documents, in their order, into sequences."""
    ship(spark)
    pieces = packing.pack(docs)
    return pieces.select("doc_id", "start", "length", F.crc32("token_ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset", "tier", "sequence_tokens", "step_group")


STAGES = [("quality rules", quality_rules), ("quality classifier", quality_classifier), ("near-duplicates", near_duplicates), ("source mixing", source_mixing), ("packing", tiered_packing)]

#: Tokens and models have no SQL; tests hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each result is written and read as the next one's input."""
    workspace = Workspace(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        done = stage(spark, docs, sf_dir)
        docs = workspace.keep(done, name.replace(" ", "-")) if k < len(STAGES) - 1 else done
    return docs
