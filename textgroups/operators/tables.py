"""Rounds over centres that stay a table: nothing the size of terms x clusters is on the driver or in one task.

The path of all methods where the matrix of centres is beyond ``MATRIX_BYTES``. Labels, sums and centres are equal to
those of the matrix path, since all sums are whole numbers and centres are rounded to fixed-point numbers alike.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textgroups.functions.text import UNIT
from textgroups.functions.vectors import Vectors
from textgroups.operators import assign
from textgroups.plans.skew import join_lookup
from textgroups.plans.storage import materialise


def by_table(strategy: str, k: int, v: int) -> bool:
    """Whether centres stay a table: ``shuffle``, or ``auto`` with a matrix that is too large."""
    if strategy not in ("auto", "matrix", "shuffle"):
        raise ValueError(f"unknown strategy {strategy}")
    return strategy == "shuffle" or (strategy == "auto" and not assign.fits(k, v))


def chosen(vecs: Vectors, picked: DataFrame) -> DataFrame:
    """(center_id, term_id, cq) of the documents in ``picked(center_id, doc_id)``; k short rows are sent to the tasks."""
    rows = vecs.packed.join(F.broadcast(picked), "doc_id").select("center_id", F.explode(F.arrays_zip("idx", "val")).alias("p"))
    return materialise(rows.select("center_id", F.col("p.idx").alias("term_id"), F.col("p.val").alias("cq")), "centers")


class Round(NamedTuple):
    """One assignment added up: ``labels(doc_id, center_id, dp)``, ``sums(center_id, term_id, s)`` and
    ``head(center_id, n, ss, ls2, low)`` of the clusters that are not empty; all written."""

    labels: DataFrame
    sums: DataFrame
    head: DataFrame

    def rss(self) -> float:
        return rss_of_head(self.head)


def rss_of_head(head: DataFrame) -> float:
    return float(head.agg(F.sum((F.col("ss") - F.col("ls2") / F.col("n")) / float(UNIT * UNIT))).first()[0] or 0.0)


def sums_of(vecs: Vectors, labels: DataFrame) -> DataFrame:
    """(center_id, term_id, s), written. The vectors meet their labels packed, once, by id."""
    rows = vecs.packed.join(labels.select("doc_id", "center_id").hint("merge"), "doc_id")
    long = rows.select("center_id", F.explode(F.arrays_zip("idx", "val")).alias("p")).select("center_id", F.col("p.idx").alias("term_id"), F.col("p.val").alias("x"))
    return materialise(long.groupBy("center_id", "term_id").agg(F.sum("x").alias("s")), "sums")


def _squares(sums: DataFrame) -> DataFrame:
    return sums.groupBy("center_id").agg(F.sum(F.col("s").cast("double") * F.col("s")).alias("ls2"))


def add_up(vecs: Vectors, centers: DataFrame, fixed: DataFrame | None = None) -> Round:
    """Assign by a salted shuffle join and add up; ``fixed(doc_id, fixed)`` holds labels that stay."""
    found = assign.nearest_by_join(vecs, centers)
    if fixed is not None:
        found = found.join(fixed.hint("merge"), "doc_id", "left").withColumn("center_id", F.coalesce("fixed", "center_id"))
    labels = materialise(found.select("doc_id", "center_id", "dp"), "labels")
    sums = sums_of(vecs, labels)
    own = vecs.packed.select("doc_id", F.aggregate("val", F.lit(0).cast("long"), lambda s, x: s + x * x).alias("q"))
    head = labels.join(own.hint("merge"), "doc_id").groupBy("center_id").agg(F.count(F.lit(1)).alias("n"), F.sum("q").alias("ss"), F.min("dp").alias("low"))
    head = head.join(_squares(sums), "center_id", "left").withColumn("ls2", F.coalesce("ls2", F.lit(0.0)))
    return Round(labels, sums, materialise(head, "head"))


def add_up_sparse(vecs: Vectors, centers: DataFrame, k: int) -> tuple[DataFrame, DataFrame] | None:
    """``sums`` and ``head`` of ``add_up`` in one pass, for centres of few terms (documents): the matrix of their own terms
    goes to the tasks, which add up the cells that occur. None if that matrix is beyond its checked size."""
    got = centers.select("center_id", "term_id", "cq").limit(assign.MATRIX_BYTES // 8 + 1).toArrow()
    c, t, x = (got.column(i).to_numpy() for i in range(3))
    terms, row = np.unique(t, return_inverse=True)
    if not assign.fits(k, len(terms) + 1):
        return None
    small, place = np.zeros((len(terms) + 1, k)), np.full(vecs.v, len(terms), np.int32)
    small[row, c], place[terms] = x, np.arange(len(terms))
    held = vecs.packed.sparkSession.sparkContext.broadcast((small, place))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            best, dots = assign.nearest_in_batch(batch, held.value[0], 1, held.value[1])
            label, dp = best[:, 0].astype(np.int64), dots[:, 0].astype(np.int64)
            sizes = np.diff(batch.column("idx").offsets.to_numpy())
            idx, val = batch.column("idx").flatten().to_numpy().astype(np.int64), batch.column("val").flatten().to_numpy()
            cells, inverse = np.unique(np.repeat(label, sizes) << 32 | idx, return_inverse=True)
            sums = np.bincount(inverse, val, len(cells)).astype(np.int64)
            n, square, low = np.bincount(label, minlength=k), np.zeros(k, np.int64), np.full(k, 1 << 62, np.int64)
            np.add.at(square, np.repeat(label, sizes), val * val)
            np.minimum.at(low, label, dp)
            some, none = np.flatnonzero(n), np.zeros(np.count_nonzero(n), np.int64)
            rows = [(cells >> 32, cells & 0xFFFFFFFF, sums, np.zeros(len(cells), np.int64)), (some, none - 1, n[some], low[some]), (some, none - 2, square[some], none)]
            yield pa.record_batch([pa.array(np.concatenate(x).astype(np.int64)) for x in zip(*rows, strict=True)], names=["center_id", "term_id", "s", "m"])

    partial = vecs.packed.select("doc_id", "idx", "val").mapInArrow(run, "center_id long, term_id long, s long, m long")
    added = materialise(partial.groupBy("center_id", "term_id").agg(F.sum("s").alias("s"), F.min("m").alias("m")), "sums")
    sums = added.filter("term_id >= 0").select("center_id", F.col("term_id").cast("int").alias("term_id"), "s")
    count = added.filter("term_id = -1").select("center_id", F.col("s").alias("n"), F.col("m").alias("low"))
    square = added.filter("term_id = -2").select("center_id", F.col("s").alias("ss"))
    head = count.join(square, "center_id").join(_squares(sums), "center_id", "left").withColumn("ls2", F.coalesce("ls2", F.lit(0.0)))
    return sums, materialise(head, "head")


def unit_table(sums: DataFrame, old: DataFrame | None = None, head: DataFrame | None = None) -> DataFrame:
    """Sums scaled to length one and rounded to fixed-point numbers, written; centres of clusters that ``head`` lacks
    stay as in ``old``."""
    lengths = materialise(_squares(sums).join(sums.groupBy("center_id").agg(F.count(F.lit(1)).alias("cells")), "center_id"), "lengths")
    scaled = F.floor(F.abs("s") / F.sqrt("ls2") * UNIT + 0.5) * F.signum(F.col("s").cast("double"))
    out = join_lookup(sums, lengths.filter("ls2 > 0"), "center_id", "cells").select("center_id", "term_id", scaled.cast("long").alias("cq"))
    if old is not None:
        out = out.unionByName(old.join(head.select("center_id").hint("merge"), "center_id", "left_anti").select("center_id", "term_id", "cq"))
    return materialise(out, "centers")


def largest_move(fresh: DataFrame, old: DataFrame) -> float:
    """The longest way of a centre, in lengths of a unit vector."""
    moves = fresh.select("center_id", "term_id", F.col("cq").cast("double").alias("d")).unionByName(old.select("center_id", "term_id", (-F.col("cq")).cast("double").alias("d")))
    by_cell = moves.groupBy("center_id", "term_id").agg(F.sum("d").alias("d"))
    got = by_cell.groupBy("center_id").agg(F.sqrt(F.sum(F.col("d") * F.col("d"))).alias("d")).agg(F.max("d")).first()[0]
    return (got or 0.0) / UNIT


def products(rows: DataFrame, m: int) -> np.ndarray:
    """Products of all pairs of ``m`` checked vectors (center_id, term_id, cq), as an m x m matrix."""
    one, two = rows.select("term_id", F.col("center_id").alias("a"), F.col("cq").alias("x")), rows.select("term_id", F.col("center_id").alias("b"), F.col("cq").alias("y"))
    got = one.join(two.hint("merge"), "term_id").filter("a <= b").groupBy("a", "b").agg(F.sum(F.col("x") * F.col("y")).alias("dp")).toArrow()
    a, b, dp = (got.column(i).to_numpy().astype(np.int64) for i in range(3))
    out = np.zeros((m, m))
    out[a, b] = out[b, a] = dp
    return out
