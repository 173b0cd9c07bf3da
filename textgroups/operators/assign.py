"""Nearest centre of every document: the kernel that all methods share (2.4, A2, A12, B1m, H10)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textgroups.functions.text import UNIT
from textgroups.functions.vectors import Vectors

#: A centre matrix beyond this is neither broadcast nor brought to the driver: centres stay a table (operators/tables.py).
MATRIX_BYTES = 256 << 20
#: Products that a kernel holds at once.
_CELLS = 4_000_000
ZERO_POLICIES = ("lowest", "drop", "noise")
STRATEGIES = ("block", "dense", "join", "shuffle", "expr", "truncate", "prune")
_SALT = 16


def fits(k: int, v: int) -> bool:
    """Whether a matrix of k centres of v terms may be held by the driver and each task."""
    return k * v * 8 <= MATRIX_BYTES


def checked(k: int, v: int) -> None:
    if not fits(k, v):
        raise ValueError(f"a matrix of {k} centres and {v} terms is beyond MATRIX_BYTES: use strategy 'shuffle'")


def plan_strategy(n: int, z: float, k: int, v: int) -> str:
    """Exact strategy by the size of the centre matrix (D-table): a kernel while it can be broadcast, else a shuffle."""
    return "block" if fits(k, v) else "shuffle"


def centre_matrix(centers: DataFrame, v: int, k: int | None = None) -> np.ndarray:
    """``centers(center_id, term_id, cq)`` as rows of terms (v x k), centres being numbered 0..k-1."""
    got = centers.select(F.col("center_id").cast("long"), F.col("term_id").cast("long"), F.col("cq").cast("double")).toArrow()
    c, t, x = (got.column(i).to_numpy() for i in range(3))
    k = k if k is not None else (int(c.max()) + 1 if len(c) else 0)
    checked(k, v)
    out = np.zeros((v, k))
    out[t, c] = x
    return out


def centres_frame(spark, matrix: np.ndarray) -> DataFrame:
    """(center_id, term_id, cq) of a matrix."""
    t, c = np.nonzero(matrix)
    table = pa.table({"center_id": c.astype(np.int64), "term_id": t.astype(np.int32), "cq": matrix[t, c].astype(np.int64)})
    return spark.createDataFrame(table)


def vectors_of(vecs: Vectors, picked: DataFrame) -> np.ndarray:
    """Matrix of the documents in ``picked(center_id, doc_id)``: k vectors come to the driver."""
    rows = vecs.packed.join(F.broadcast(picked), "doc_id")
    k = picked.count()
    checked(k, vecs.v)
    out = np.zeros((vecs.v, k))
    for r in rows.select("center_id", "idx", "val").collect():
        out[r["idx"], r["center_id"]] = r["val"]
    return out


def unit(sums: np.ndarray) -> np.ndarray:
    """Columns scaled to length one and rounded to fixed-point numbers; an all-zero column stays zero."""
    length = np.sqrt((sums * sums).sum(axis=0))
    return np.floor(np.abs(sums) / np.where(length > 0, length, 1) * UNIT + 0.5) * np.sign(sums)


def _lists(column: pa.ListArray, kind) -> tuple[np.ndarray, np.ndarray]:
    sizes = np.diff(column.offsets.to_numpy())
    return sizes.astype(np.int64), column.flatten().to_numpy(zero_copy_only=False).astype(kind)


def compact(matrix: np.ndarray) -> tuple[np.ndarray, np.ndarray | None]:
    """A matrix without the terms that no centre holds, its last row being zero, and each term's row in it; a matrix that
    would keep over half its rows stays as it is. What is broadcast lies on the disk of every executor."""
    rows = np.flatnonzero(matrix.any(axis=1))
    if 2 * len(rows) > len(matrix):
        return matrix, None
    place = np.full(len(matrix), len(rows), np.int32)
    place[rows] = np.arange(len(rows))
    return np.vstack([matrix[rows], np.zeros((1, matrix.shape[1]))]), place


def nearest_in_batch(batch: pa.RecordBatch, matrix: np.ndarray, top: int = 1, place: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(centres, products), ``top`` columns each, of a batch of (doc_id, idx, val): exact, ties go to the smaller id.

    ``place``: each term's row of a compact matrix.

    Products of fixed-point unit vectors stay below 2^53, so float64 holds them exactly.
    """
    sizes, idx = _lists(batch.column("idx"), np.int64)
    _, val = _lists(batch.column("val"), np.float64)
    n, k = len(sizes), matrix.shape[1]
    dots = np.zeros((n, k))
    ends = np.concatenate([[0], np.cumsum(sizes)])
    if place is not None:
        idx = place[idx]
    if n and place is None and sizes.min() == sizes.max() == matrix.shape[0]:  # points: all dimensions, in order
        dots = val.reshape(n, -1) @ matrix
    else:
        first = 0
        while first < n:
            last = max(first + 1, int(np.searchsorted(ends, ends[first] + max(1, _CELLS // max(1, k)), side="right")) - 1)
            a, b = ends[first], ends[last]
            some = np.flatnonzero(sizes[first:last] > 0)
            if len(some):
                products = matrix[idx[a:b]] * val[a:b, None]
                dots[first + some] = np.add.reduceat(products, ends[first + some] - a, axis=0)
            first = last
    if top == 1:
        best = dots.argmax(axis=1)[:, None] if k else np.zeros((n, 0), np.int64)
    else:
        best = np.argsort(-dots, axis=1, kind="stable")[:, :top]
    return best, np.take_along_axis(dots, best, axis=1)


def _by_block(vecs: Vectors, matrix: np.ndarray, top: int) -> DataFrame:
    held = vecs.packed.sparkSession.sparkContext.broadcast(compact(matrix))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            best, dots = nearest_in_batch(batch, held.value[0], top, held.value[1])
            empty = np.diff(batch.column("idx").offsets.to_numpy()) == 0
            width = best.shape[1]
            ids = batch.column("doc_id").to_numpy(zero_copy_only=False)
            yield pa.record_batch([pa.array(np.repeat(ids, width)), pa.array(best.ravel().astype(np.int64)), pa.array(dots.ravel().astype(np.int64)), pa.array(np.tile(np.arange(1, width + 1, dtype=np.int32), len(ids))), pa.array(np.repeat(empty, width))], names=["doc_id", "center_id", "dp", "rank", "empty"])

    return vecs.packed.select("doc_id", "idx", "val").mapInArrow(run, "doc_id long, center_id long, dp long, rank int, empty boolean")


def _by_join(vecs: Vectors, centers: DataFrame, top: int, shuffle: bool) -> DataFrame:
    """D1 and D5. A document that meets no centre is brought back by a left join."""
    postings = vecs.postings
    if shuffle:
        # Salting deals a frequent term's postings over _SALT tasks; the centres' rows are repeated for each.
        postings = postings.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(_SALT)))
        dealt = centers.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(_SALT - 1)))).hint("merge")
        pairs = postings.join(dealt, ["term_id", "salt"])
    else:
        pairs = postings.join(F.broadcast(centers), "term_id")
    dots = pairs.groupBy("doc_id", "center_id").agg(F.sum(F.col("wq") * F.col("cq")).alias("dp"))
    ids = vecs.packed.select("doc_id", (F.size("idx") == 0).alias("empty"))
    if top == 1:
        best = dots.groupBy("doc_id").agg(F.max(F.struct(F.col("dp"), -F.col("center_id"))).alias("b"))
        best = best.select("doc_id", F.col("b.dp").alias("dp"), (-F.col("b.col2")).alias("center_id"), F.lit(1).alias("rank"))
    else:
        from pyspark.sql import Window

        by = Window.partitionBy("doc_id").orderBy(F.desc("dp"), "center_id")
        best = dots.withColumn("rank", F.row_number().over(by)).filter(F.col("rank") <= top)
    lowest = F.lit(0).cast("long")
    return ids.join(best, "doc_id", "left").select("doc_id", F.coalesce("center_id", lowest).alias("center_id"), F.coalesce("dp", lowest).alias("dp"), F.coalesce("rank", F.lit(1)).alias("rank"), "empty")


def nearest_by_join(vecs: Vectors, centers: DataFrame) -> DataFrame:
    """(doc_id, center_id, dp, rank, empty) by the salted shuffle join, for centres that stay a table."""
    return _by_join(vecs, centers, 1, True)


def _by_expression(vecs: Vectors, matrix: np.ndarray) -> DataFrame:
    """Dense points against a few centres, inside the JVM's expressions."""
    best = None
    for c in range(matrix.shape[1]):
        literal = F.lit([int(x) for x in matrix[:, c]])
        dp = F.aggregate(F.zip_with("val", literal, lambda x, y: x * y.cast("long")), F.lit(0).cast("long"), lambda s, p: s + p)
        item = F.struct(dp.alias("dp"), F.lit(-c).cast("long").alias("neg"))
        best = item if best is None else F.greatest(best, item)
    rows = vecs.packed.select("doc_id", best.alias("b"), (F.size("idx") == 0).alias("empty"))
    return rows.select("doc_id", (-F.col("b.neg")).alias("center_id"), F.col("b.dp").alias("dp"), F.lit(1).alias("rank"), "empty")


def heavy_terms(matrix: np.ndarray, t: int) -> np.ndarray:
    """Each centre cut to its ``t`` heaviest terms."""
    if t >= matrix.shape[0]:
        return matrix
    cut = np.zeros_like(matrix)
    keep = np.argsort(-np.abs(matrix), axis=0, kind="stable")[:t]
    np.put_along_axis(cut, keep, np.take_along_axis(matrix, keep, axis=0), axis=0)
    return cut


def _pruned(vecs: Vectors, matrix: np.ndarray, t: int) -> DataFrame:
    """Only centres that share one of their ``t`` heaviest terms with the document are compared in full."""
    spark = vecs.packed.sparkSession
    index = centres_frame(spark, heavy_terms(matrix, t)).select("term_id", "center_id")
    pairs = vecs.postings.join(F.broadcast(index), "term_id").select("doc_id", "center_id").distinct()
    full = vecs.postings.join(pairs, "doc_id").join(F.broadcast(centres_frame(spark, matrix)), ["term_id", "center_id"])
    dots = full.groupBy("doc_id", "center_id").agg(F.sum(F.col("wq") * F.col("cq")).alias("dp"))
    best = dots.groupBy("doc_id").agg(F.max(F.struct(F.col("dp"), -F.col("center_id"))).alias("b")).select("doc_id", F.col("b.dp").alias("dp"), (-F.col("b.col2")).alias("center_id"))
    ids = vecs.packed.select("doc_id", (F.size("idx") == 0).alias("empty"))
    zero = F.lit(0).cast("long")
    return ids.join(best, "doc_id", "left").select("doc_id", F.coalesce("center_id", zero).alias("center_id"), F.coalesce("dp", zero).alias("dp"), F.lit(1).alias("rank"), "empty")


def assign_nearest(vecs: Vectors, centers: np.ndarray | DataFrame, strategy: str = "auto", top: int = 1, zero_docs: str = "lowest", terms: int = 64) -> DataFrame:
    """(doc_id, center_id, sim[, rank]): the most similar centre, ties to the smaller id (A2).

    ``block``, ``dense``, ``join``, ``shuffle`` and ``expr`` agree exactly; ``truncate`` and ``prune`` are approximate.
    ``zero_docs``: documents without a term go to the smallest id, are dropped, or get the id -1.
    """
    spark = vecs.packed.sparkSession
    if strategy == "auto":
        strategy = "shuffle" if isinstance(centers, DataFrame) else plan_strategy(vecs.n, 0, centers.shape[1], vecs.v)
    if strategy in ("join", "shuffle"):
        frame = centers if isinstance(centers, DataFrame) else centres_frame(spark, centers)
        found = _by_join(vecs, frame, top, strategy == "shuffle")
    else:
        matrix = centre_matrix(centers, vecs.v) if isinstance(centers, DataFrame) else centers
        if strategy == "expr":
            found = _by_expression(vecs, matrix)
        elif strategy == "prune":
            found = _pruned(vecs, matrix, terms)
        else:
            found = _by_block(vecs, heavy_terms(matrix, terms) if strategy == "truncate" else matrix, top)
    if zero_docs == "drop":
        found = found.filter(~F.col("empty"))
    label = F.when(F.col("empty"), F.lit(-1).cast("long")).otherwise(F.col("center_id")) if zero_docs == "noise" else F.col("center_id")
    out = found.select("doc_id", label.alias("center_id"), (F.col("dp") / float(UNIT * UNIT)).alias("sim"), "rank")
    return out if top > 1 else out.drop("rank")


class Totals:
    """What one pass over the vectors adds up for k centres: counts, linear sums, square sums, lowest similarities."""

    def __init__(self, sums: np.ndarray, count: np.ndarray, square: np.ndarray, least: np.ndarray):
        self.sums, self.count, self.square, self.least = sums, count, square, least

    def rss(self) -> float:
        """Sum over clusters of SS - LS LS / N, in units of squared length (M1)."""
        full = self.count > 0
        lengths = (self.sums[:, full] ** 2).sum(axis=0) / self.count[full]
        return float((self.square[full] - lengths).sum() / UNIT / UNIT)


def totals(packed: DataFrame, matrix: np.ndarray, fixed: str | None = None) -> Totals:
    """Assign and add up in one pass; ``fixed`` names a column of labels that hold where they are not null.

    Each task adds up its documents before anything is shuffled: at most one row per centre and term leaves a task. The
    matrix and its sums are of a checked size; beyond it use ``tables.add_up``.
    """
    v, k = matrix.shape
    checked(k, v)
    spark = packed.sparkSession
    held = spark.sparkContext.broadcast(compact(matrix))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, n, ss, low = None, np.zeros(k, np.int64), np.zeros(k, np.int64), np.full(k, 1 << 62, np.int64)
        for batch in batches:
            best, dots = nearest_in_batch(batch, held.value[0], 1, held.value[1])
            label, dp = best[:, 0], dots[:, 0].astype(np.int64)
            if fixed:
                known = batch.column(fixed).is_valid().to_numpy(zero_copy_only=False)
                label[known] = batch.column(fixed).fill_null(0).to_numpy(zero_copy_only=False)[known]
            sizes, idx = _lists(batch.column("idx"), np.int64)
            _, val = _lists(batch.column("val"), np.int64)
            cell = np.repeat(label, sizes) * v + idx
            sums = np.zeros(k * v, np.int64) if sums is None else sums
            sums += np.bincount(cell, val, k * v).astype(np.int64)
            n += np.bincount(label, minlength=k)
            ss += np.bincount(label, np.bincount(np.repeat(np.arange(len(sizes)), sizes), val * val, len(sizes)), k).astype(np.int64)
            np.minimum.at(low, label, dp)
        if sums is None:
            return
        cells = np.flatnonzero(sums)
        values = sums[cells]
        some = np.flatnonzero(n)
        rows = [(cells // v, cells % v, values, np.zeros(len(cells), np.int64)), (some, np.full(len(some), -1), n[some], low[some]), (some, np.full(len(some), -2), ss[some], np.zeros(len(some), np.int64))]
        c, t, s, m = (np.concatenate(x) for x in zip(*rows, strict=True))
        for i in range(0, len(c), 200_000):
            part = slice(i, i + 200_000)
            yield pa.record_batch([pa.array(c[part]), pa.array(t[part].astype(np.int32)), pa.array(s[part]), pa.array(m[part])], names=["c", "t", "s", "m"])

    partial = packed.select("doc_id", "idx", "val", *([fixed] if fixed else [])).mapInArrow(run, "c long, t int, s long, m long")
    got = partial.groupBy("c", "t").agg(F.sum("s").alias("s"), F.min("m").alias("m")).toArrow()
    c, t, s, m = (got.column(i).to_numpy() for i in range(4))
    sums, count, square, least = np.zeros((v, k)), np.zeros(k), np.zeros(k), np.zeros(k)
    terms = t >= 0
    sums[t[terms], c[terms]] = s[terms]
    count[c[t == -1]], least[c[t == -1]] = s[t == -1], m[t == -1] / UNIT / UNIT
    square[c[t == -2]] = s[t == -2]
    held.unpersist()
    return Totals(sums, count, square, least)
