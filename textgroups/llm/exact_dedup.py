"""Exact dedup through a persistent digest index (operator 8).

Two texts are equal when they are the same after every white space character (space, tab to carriage return) is
deleted. The index is a table bucketed and sorted by digest; a new batch is reduced to its digests, met with the index
by a sort-merge anti-join (no shuffle of the index) and what is new is appended. Defined results: a null text is the
empty text; of equal texts the row with the most code points and then the smallest ``doc_id`` (null last) stays; of
rows equal in both, one stays, by a hash of the text; a digest that the index already holds keeps the row that came
first. Empty tables give no rows; extra columns are ignored.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from textgroups.llm.rows import keep_unmarked, text_key
from textgroups.plans.skew import join_lookup
from textgroups.plans.storage import drop_path, materialise, workspace

WHITE = " \t\n\x0b\x0c\r"


def normalised(text: Column) -> Column:
    text = F.coalesce(text, F.lit(""))
    for c in WHITE:
        text = F.replace(text, F.lit(c), F.lit(""))
    return text


def digests(docs: DataFrame) -> DataFrame:
    """(doc_id, digest binary, n_chars, tx, uid): all that later steps need of a document. ``uid`` numbers the rows of one
    run, so write them before they are used twice."""
    digest = F.unhex(F.sha2(normalised(F.col("text")), 256))
    return docs.select(F.col("doc_id").cast("long"), digest.alias("digest"), F.coalesce(F.char_length("text"), F.lit(0)).cast("long").alias("n_chars"), text_key(F.col("text")).alias("tx"), F.monotonically_increasing_id().alias("uid"))


def best_of(rows: DataFrame) -> DataFrame:
    """One row per digest: the document that stays, the number of its row, and the number of rows."""
    ranked = F.struct("n_chars", F.col("doc_id").isNotNull(), F.bitwise_not(F.col("doc_id")), "tx", F.bitwise_not(F.col("uid")), "doc_id", "uid")
    return rows.groupBy("digest").agg(F.max(ranked).alias("best"), F.count(F.lit(1)).alias("group_size")).select("digest", F.col("best.doc_id").alias("keep_id"), "group_size", F.col("best.n_chars").alias("keep_chars"), F.col("best.uid").alias("keep_uid"))


class DigestIndex:
    """A table of (digest, keep_id, group_size, keep_chars, keep_uid, batch) in the session's catalog, bucketed and sorted by digest."""

    def __init__(self, spark: SparkSession, name: str, buckets: int = 0, path: str | None = None):
        self.spark, self.name = spark, name
        self.buckets = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
        self.path = path or workspace(spark, name)

    def read(self) -> DataFrame:
        return self.spark.table(self.name)

    def append(self, fresh: DataFrame) -> None:
        """One file per bucket and batch: the rows are dealt by the bucket hash before they are written."""
        writer = fresh.repartition(self.buckets, "digest").write.bucketBy(self.buckets, "digest").sortBy("digest")
        writer.option("path", self.path).mode("append").saveAsTable(self.name)

    def add(self, docs: DataFrame) -> tuple[DataFrame, str]:
        """Dedup ``docs`` against the index and themselves, append what is new, and return the digests of ``docs`` with
        the name of their batch. A new index begins as an empty table, so every batch takes the same way."""
        rows, batch = materialise(digests(docs), "digests"), uuid.uuid4().hex
        own = best_of(rows).withColumn("batch", F.lit(batch))
        if not self.spark.catalog.tableExists(self.name):
            self.append(self.spark.createDataFrame([], own.schema))
        self.append(materialise(own.join(self.read().hint("merge"), "digest", "left_anti"), "fresh"))
        return rows, batch

    def drop(self) -> None:
        self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")
        drop_path(self.spark, self.path)


def _judged(docs: DataFrame, index: DigestIndex | None) -> DataFrame:
    """The digests of ``docs`` with what the index says of each; written, so that an index of its own is dropped again."""
    spark = docs.sparkSession
    held = index or DigestIndex(spark, "digest_index_" + uuid.uuid4().hex)
    rows, batch = held.add(docs)
    found = join_lookup(rows, held.read(), "digest", "group_size")
    kept = (F.col("batch") == batch) & (F.col("uid") == F.col("keep_uid"))
    found = found.select("doc_id", "tx", "keep_id", "group_size", kept.alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"))
    if index is None:
        found = materialise(found, "judged")
        held.drop()
    return found


def deduplicate(docs: DataFrame, index: DigestIndex | None = None) -> DataFrame:
    """One row per row of ``docs``: doc_id, keep_id, group_size, kept, text_sha256.

    ``group_size`` counts the rows of the batch that brought the digest into the index; a row whose digest came with an
    earlier batch is not kept.
    """
    return _judged(docs, index).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def keep_first(docs: DataFrame) -> DataFrame:
    """The documents that stay, one per digest, with their own columns."""
    rows = _judged(docs, None)
    texts = rows.groupBy(F.col("doc_id").alias("id"), "tx").agg(F.count(F.lit(1)).alias("times"), F.bool_or("kept").alias("stays"))
    return keep_unmarked(docs, materialise(texts.filter("not stays or times > 1").drop("times"), "marks"))
