"""The corpus pipeline: toxicity, exact copies, near copies, benchmark passages, tokens.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of
``documents``.  Stages judge only what their predecessors kept.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from flowrings.llm import bpe, decontaminate, exact_dedup, simhash, toxicity
from flowrings.scratch import materialize, release_heaps


KEY = "__row"


def _stage(step: Callable) -> Callable:
    """``step`` after the executors have given back the heap that earlier stages needed: its Python workers take its place."""

    @wraps(step)
    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        release_heaps(spark)
        return step(spark, docs, sf_dir)

    return run


def _keyed(docs: DataFrame) -> DataFrame:
    """``docs`` with a number of its own for each row, written once so that it stays the same."""
    return materialize(docs.withColumn(KEY, F.monotonically_increasing_id()), "keyed")


def _one_of_each(keyed: DataFrame, groups: DataFrame, first: Column) -> DataFrame:
    """``keyed`` with one row of each group (KEY, group), which ``first``, an aggregate over (doc_id, KEY), names.

    Only the numbers of rows that go are looked up: a small table is sent to the tasks by the planner's own
    size limit, and the texts are shuffled beyond it only.
    """
    several = groups.groupBy("group").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("group")
    members = materialize(groups.join(several, "group").join(keyed.select(KEY, "doc_id"), KEY), "members")
    stays = members.groupBy("group").agg(first.alias("first")).select(F.col("first")[KEY].alias(KEY))
    goes = materialize(members.select(KEY).join(stays, KEY, "left_anti"), "copies")
    return keyed.join(goes, KEY, "left_anti").drop(KEY)


@_stage
def reject_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose toxicity score stays below the threshold, judged by a model of the labels.

    Each row is judged by its own text, also where its doc_id is null or repeated; a null text stays.
    """
    return toxicity.keep_harmless(docs, toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


@_stage
def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts one row, with the largest doc_id; a null id only where no row has another.

    Null and empty texts are equal to each other.
    """
    keyed = _keyed(docs)
    groups = exact_dedup.deduplicate_once(keyed, id_col=KEY).select(F.col("doc_id").alias(KEY), F.col("keep_id").alias("group"))
    return _one_of_each(keyed, groups, F.max(F.struct("doc_id", KEY)))


@_stage
def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies one row, with the smallest doc_id; a null id only where no row has another."""
    keyed = _keyed(docs)
    groups = simhash.near_components(keyed, id_col=KEY).select(F.col("doc_id").alias(KEY), F.col("component_id").alias("group"))
    return _one_of_each(keyed, groups, F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", KEY)))


@_stage
def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows without a contaminating share of benchmark passages, each judged by its own text; a null text stays."""
    return decontaminate.keep_clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


@_stage
def tokenize(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document: doc_id, n_tokens, ids_sha256, decoded_sha256, ids."""
    return bpe.encode_documents(docs, bpe.default_vocabulary())


STAGES = [
    ("toxicity", reject_toxic),
    ("exact dedup", drop_copies),
    ("near dedup", drop_near_copies),
    ("decontamination", drop_contaminated),
    ("tokens", tokenize),
]

#: The first stage is a trained model and the third needs XXH64: SQL cannot express them.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), f"stage-{name.replace(' ', '-')}")
    return docs
