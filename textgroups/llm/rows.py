"""Taking rows out of a table of documents by a small list of marks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Marks go to the tasks by broadcast up to so many rows (24 bytes each), beyond it by shuffle.
BROADCAST_ROWS = 500_000


def text_key(text: Column) -> Column:
    """A hash of the text; null counts as the empty text."""
    return F.xxhash64(F.coalesce(text, F.lit("")))


def sized(rows: DataFrame) -> DataFrame:
    """The written ``rows`` as the side of a join that is sent to all tasks, if they are few."""
    return F.broadcast(rows) if rows.count() <= BROADCAST_ROWS else rows.hint("merge")


def tagged(docs: DataFrame) -> DataFrame:
    """(row, id, tx): the documents with the two columns by which marks find them."""
    return docs.select(F.struct("*").alias("row"), F.col("doc_id").cast("long").alias("id"), text_key(F.col("text")).alias("tx"))


def keep_unmarked(docs: DataFrame, marks: DataFrame) -> DataFrame:
    """``docs`` without the rows that the written ``marks(id, tx, stays)`` name; of equal rows named with ``stays`` one stays.

    Rows are met by id (null like any other) and text. The documents are shuffled only where the marks are too many.
    """
    rows, names = tagged(docs), sized(marks.withColumnsRenamed({"id": "_id", "tx": "_tx"}))
    marked = rows.join(names, F.col("id").eqNullSafe(F.col("_id")) & (F.col("tx") == F.col("_tx")), "left")
    kept = marked.filter("stays is null")
    if not marks.filter("stays").isEmpty():
        kept = kept.unionByName(marked.filter("stays").dropDuplicates(["id", "tx"]))
    return kept.select("row.*")
