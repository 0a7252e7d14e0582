"""A corpus from documents: five stages, each written as Parquet and read again by the next."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldmr.llm.decontam import clean
from fieldmr.llm.mixing import mixed
from fieldmr.llm.neardup import near_duplicates
from fieldmr.llm.runtime import broadcast_if_small, delete, materialise, read_table, scratch, shared_dir
from fieldmr.llm.tokenfile import token_table
from fieldmr.llm.toxicity import without_toxic
from fieldmr.session import ship


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents rated toxic go."""
    return without_toxic(docs, read_table(ship(spark), sf_dir, "labels"))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near-duplicates stays, the one with the least doc_id; rows without an id give way to those with one.

    Rows are told apart by a key of their own, written with them, so that repeated and absent ids decide nothing.
    """
    row = F.struct(*(F.col(f"`{c}`") for c in docs.columns))
    rows = materialise(docs.select(F.monotonically_increasing_id().alias("key"), row.alias("row")), "rows")
    verdict = near_duplicates(rows.select(F.col("key").alias("doc_id"), F.col("row.text").alias("text")))
    placed = rows.select("key", F.col("row.doc_id").cast("long").alias("id")).join(verdict.select(F.col("doc_id").alias("key"), "component_id"), "key")
    order = F.struct(F.col("id").isNull(), "id", "key")
    groups = materialise(placed.select("key", "component_id", order.alias("o")), "groups")
    first = groups.groupBy("component_id").agg(F.min("o").alias("o"), F.count("*").alias("n")).where("n > 1").select("component_id", F.col("o.key").alias("first"))
    gone = materialise(groups.join(first, "component_id").where("key <> first").select("key"), "gone")
    return rows.join(broadcast_if_small(gone), "key", "left_anti").select("row.*")


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a window of a benchmark item go."""
    return clean(docs, read_table(ship(spark), sf_dir, "benchmark"))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents come as often as the mix says."""
    return mixed(docs, read_table(spark, sf_dir, "labels"))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token files, read back per document."""
    return token_table(docs)


STAGES = [("toxicity", toxicity), ("near-duplicates", near_dedup), ("decontamination", decontamination), ("mixing", mixing), ("tokens", tokens)]

#: Learned and iterative stages have no SQL; tests hold the result against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order, over the whole table of documents."""
    ship(spark)
    docs = read_table(spark, sf_dir, "documents")
    folder = f"{shared_dir(spark)}/fieldmr-pipeline-{uuid.uuid4().hex}"
    for k, (_, stage) in enumerate(STAGES):
        with scratch(spark):
            stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
        if k:
            delete(spark, f"{folder}/{k - 1}")
        docs = spark.read.parquet(f"{folder}/{k}")
    return docs
