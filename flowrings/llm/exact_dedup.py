"""Exact deduplication against a persistent index of digests.

The index is a table of (digest, keep_id), bucketed and sorted by digest, so that looking up a new
batch is a sort-merge join that shuffles the batch alone.  A batch is first reduced to one row per
digest; the digests that the index lacks (anti-join) are appended.  DataFrame functions only.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowrings.llm.arrow import documents_view
from flowrings.scratch import materialize


class DigestIndex:
    """A table of digests that have been seen, each with the id of the document that stays."""

    def __init__(self, spark: SparkSession, table: str, buckets: int | None = None):
        self.spark, self.table = spark, table
        self.buckets = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))

    def read(self) -> DataFrame:
        return self.spark.table(self.table)

    def create(self) -> None:
        """An empty index, if there is none yet."""
        self.spark.sql(
            f"CREATE TABLE IF NOT EXISTS {self.table} (digest BINARY, keep_id BIGINT) USING parquet "
            f"CLUSTERED BY (digest) SORTED BY (digest) INTO {self.buckets} BUCKETS"
        )

    def append(self, fresh: DataFrame) -> None:
        """Add rows (digest, keep_id): one sorted file per bucket and call."""
        (
            fresh.select("digest", "keep_id").repartition(self.buckets, "digest")
            .write.mode("append").format("parquet")
            .bucketBy(self.buckets, "digest").sortBy("digest").saveAsTable(self.table)
        )

    def add(self, seen: DataFrame) -> None:
        """Add the digests of a batch (doc_id, digest) that the index lacks; the largest doc_id of each stays."""
        self.create()
        groups = seen.groupBy("digest").agg(F.max("doc_id").alias("keep_id"))
        self.append(groups.join(self.read().hint("merge"), "digest", "left_anti"))

    def drop(self) -> None:
        self.spark.sql(f"DROP TABLE IF EXISTS {self.table}")


def digests_of(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, digest): SHA-256 of the UTF-8 text; a null text counts as empty."""
    view = documents_view(docs, id_col, text_col)
    return view.select("doc_id", F.unhex(F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256)).alias("digest"))


def deduplicate(docs: DataFrame, index: DigestIndex, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256; new digests go to ``index``.

    Texts are equal when identical.  A text that the index already has keeps the document named
    there; otherwise the largest doc_id of the batch stays.  group_size counts the batch's rows.
    Null texts count as empty; a null id never wins over another id; rows that repeat an id and a
    text are all marked kept if that id stays.  An empty batch gives no rows and leaves the index
    as it is.  Running the same batch again changes nothing.
    """
    seen = materialize(digests_of(docs, id_col, text_col), "digests")
    index.add(seen)
    return _judged(seen, index)


def _judged(seen: DataFrame, index: DigestIndex) -> DataFrame:
    """Each row of ``seen`` (doc_id, digest) with the owner that the index names and the rows of its group in ``seen``."""
    sizes = seen.groupBy("digest").agg(F.count(F.lit(1)).alias("group_size"))
    owners = materialize(sizes.join(index.read().hint("merge"), "digest"), "owners")
    return seen.join(owners, "digest").select(
        "doc_id", "keep_id", "group_size",
        F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def deduplicate_in_batches(docs: DataFrame, index: DigestIndex, batches: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``deduplicate`` of a whole corpus, as if it had come in ``batches`` batches of descending doc_id.

    The first batch that has a text holds the largest doc_id with it, so an index that grows batch by batch
    names that document; rows with a null doc_id come last.  group_size counts all rows of the corpus.
    Batches are cut at quantiles of doc_id, rows of one id stay together.
    """
    seen = materialize(digests_of(docs, id_col, text_col), "digests")
    shares = [i / batches for i in range(1, batches)]
    bounds = sorted({int(x) for x in (seen.approxQuantile("doc_id", shares, 0.01) if shares else [])}, reverse=True)
    for low, high in zip([*bounds, None], [None, *bounds]):
        above = F.lit(True) if low is None else F.col("doc_id") > low
        index.add(seen.filter(above if high is None else above & (F.col("doc_id") <= high)))
    index.add(seen.filter("doc_id IS NULL"))
    return _judged(seen, index)


def deduplicate_once(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", batches: int = 4) -> DataFrame:
    """``deduplicate_in_batches`` with a fresh index that is dropped afterwards."""
    index = DigestIndex(docs.sparkSession, f"flowrings_digests_{uuid.uuid4().hex}")
    try:
        return deduplicate_in_batches(docs, index, batches, id_col, text_col)
    finally:
        index.drop()


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return deduplicate_once(spark.read.parquet(f"{sf_dir}/documents.parquet"))


ORACLE = """
WITH d AS (SELECT doc_id, sha256(coalesce(text, '')) AS text_sha256 FROM documents),
g AS (SELECT text_sha256, max(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY 1)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, text_sha256 FROM d JOIN g USING (text_sha256)
"""
