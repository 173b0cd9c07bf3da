"""The K-Means baseline with cosine (B1) and its Euclidean form (B1u)."""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textgroups.functions.vectors import Vectors
from textgroups.operators import tables
from textgroups.operators.assign import assign_nearest, centre_matrix, centres_frame, totals, unit, vectors_of
from textgroups.operators.sampling import pick_centers


class LloydResult(NamedTuple):
    assign: DataFrame
    centers: np.ndarray | DataFrame
    info: dict


def initial_centers(vecs: Vectors, k: int, init="random", seed: int = 42) -> np.ndarray:
    """Start of the baseline (B1i), or given centres."""
    if isinstance(init, np.ndarray):
        return init
    if isinstance(init, DataFrame):
        return centre_matrix(init, vecs.v)
    if init == "random":
        return vectors_of(vecs, pick_centers(vecs.packed.select("doc_id"), k, seed, n=vecs.n))
    from textgroups.operators.related import seed_centers

    return seed_centers(vecs, k, how=init, seed=seed)


def refill(fresh: np.ndarray, counts: np.ndarray, old: np.ndarray, empty: str, vecs: Vectors) -> np.ndarray:
    """Centres of empty clusters stay (``keep``) or move to the documents least similar to their centre (B1e)."""
    none = np.flatnonzero(counts == 0)
    fresh[:, none] = old[:, none]
    if empty == "farthest" and len(none):
        far = assign_nearest(vecs, old).orderBy("sim", "doc_id").limit(len(none)).select("doc_id").collect()
        spark = vecs.packed.sparkSession
        picked = spark.createDataFrame([(i, r["doc_id"]) for i, r in enumerate(far)], "center_id long, doc_id long")
        fresh[:, none[: len(far)]] = vectors_of(vecs, picked)
    return fresh


def _lloyd_by_table(vecs: Vectors, k: int, init, max_iter: int, tol: float, stop: str, seed: int, empty: str) -> LloydResult:
    """The same rounds with centres that stay a table."""
    if isinstance(init, np.ndarray):
        centers = tables.materialise(centres_frame(vecs.packed.sparkSession, init), "centers")
    elif isinstance(init, DataFrame):
        centers = init.select(F.col("center_id").cast("long"), "term_id", "cq")
    elif init == "random":
        centers = tables.chosen(vecs, pick_centers(vecs.packed.select("doc_id"), k, seed, n=vecs.n))
    elif init == "density":
        from textgroups.operators.related import densest

        centers = tables.chosen(vecs, densest(vecs, k, seed))
    else:
        raise ValueError(f"start {init} needs a matrix of centres; give its centres as a table")
    history, before, rounds = [], None, 0
    for rounds in range(1, max_iter + 1):
        now = tables.add_up(vecs, centers)
        history.append(now.rss())
        fresh = tables.unit_table(now.sums, centers, now.head)
        if empty == "farthest":
            full = {r["center_id"] for r in now.head.select("center_id").collect()}
            none = [c for c in range(k) if c not in full]
            if none:
                far = now.labels.orderBy("dp", "doc_id").limit(len(none)).select("doc_id").collect()
                picked = vecs.packed.sparkSession.createDataFrame([(c, r["doc_id"]) for c, r in zip(none, far)], "center_id long, doc_id long")
                moved = [c for c, _ in zip(none, far)]
                fresh = tables.materialise(fresh.filter(~F.col("center_id").isin(moved)).unionByName(tables.chosen(vecs, picked)), "centers")
        shift = tables.largest_move(fresh, centers)
        centers = fresh
        if shift == 0 or (stop == "shift" and shift <= tol) or (stop == "rss" and before is not None and before - history[-1] <= tol * before):
            break
        before = history[-1]
    labels = assign_nearest(vecs, centers, "shuffle").withColumnRenamed("center_id", "cluster_id")
    return LloydResult(labels, centers, {"rounds": rounds, "rss_by_round": history, "passes": rounds + 1})


def lloyd(vecs: Vectors, k: int, init="random", max_iter: int = 8, tol: float = 0.0, stop: str = "labels", seed: int = 42, empty: str = "keep", strategy: str = "auto") -> LloydResult:
    """Assign, add up in the tasks, add up over tasks, new means (B1, B1c, B1r).

    One pass over the vectors a round: labels are not stored, the sums come from the same pass that assigns. Sums and
    counts are carried, never means of means. Stops when no centre moves, which is when no label does (``labels``), when
    the largest move of a centre is at most ``tol`` (``shift``), or when RSS falls by no more than ``tol`` of itself
    (``rss``); at ``max_iter`` rounds anyway (B1t). ``strategy``: centres as a ``matrix``, as a table (``shuffle``), or
    by the size of the matrix (``auto``); the labels are the same, and ``centers`` is a table in the second case.
    """
    if tables.by_table(strategy, k, vecs.v):
        return _lloyd_by_table(vecs, k, init, max_iter, tol, stop, seed, empty)
    centers = initial_centers(vecs, k, init, seed)
    history, before = [], None
    rounds = 0
    for rounds in range(1, max_iter + 1):
        now = totals(vecs.packed, centers)
        history.append(now.rss())
        fresh = refill(unit(now.sums), now.count, centers, empty, vecs)
        shift = float(np.sqrt(((fresh - centers) ** 2).sum(axis=0)).max()) / (1 << 20) if k else 0.0
        centers = fresh
        if shift == 0 or (stop == "shift" and shift <= tol) or (stop == "rss" and before is not None and before - history[-1] <= tol * before):
            break
        before = history[-1]
    labels = assign_nearest(vecs, centers).withColumnRenamed("center_id", "cluster_id")
    return LloydResult(labels, centers, {"rounds": rounds, "rss_by_round": history, "passes": rounds + 1})


def add_points(ids: DataFrame, centers: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Counts, sums and largest squared distances of the points ``ids(doc_id, x)`` by nearest centre, added up in the tasks."""
    import pyarrow as pa

    def add(batches):
        sums, n, far = np.zeros_like(centers), np.zeros(len(centers), np.int64), np.zeros(len(centers))
        for batch in batches:
            x, label = nearest_point(batch, centers)
            np.add.at(sums, label, x)
            n += np.bincount(label, minlength=len(centers))
            np.maximum.at(far, label, ((x - centers[label]) ** 2).sum(axis=1))
        yield pa.record_batch([pa.array(np.arange(len(centers))), pa.array(n), pa.array(list(sums)), pa.array(far)], names=["c", "n", "x", "far"])

    rows = ids.mapInArrow(add, "c long, n long, x array<double>, far double")
    added = rows.select("c", "n", "far", F.posexplode("x").alias("i", "x")).groupBy("c", "i").agg(F.sum("x").alias("x"), F.sum("n").alias("n"), F.max("far").alias("far")).toArrow()
    c, i, x, n, far = (added.column(j).to_numpy() for j in range(5))
    sums, count, radius = np.zeros_like(centers), np.zeros(len(centers)), np.zeros(len(centers))
    sums[c, i], count[c], radius[c] = x, n, far
    return count, sums, radius


def nearest_point(batch, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    x = batch.column("x").flatten().to_numpy().reshape(batch.num_rows, -1)
    return x, np.round(-2 * x @ c.T + (c * c).sum(axis=1), 9).argmin(axis=1)


def lloyd_euclidean(points: DataFrame, k: int, max_iter: int = 8, seed: int = 42, id_col: str = "vec_id", column: str = "embedding") -> tuple[DataFrame, np.ndarray]:
    """K-Means on points with squared distances x x - 2 x c + c c (B1u); a task adds up its own points."""
    import pyarrow as pa

    ids = points.select(F.col(id_col).alias("doc_id"), F.col(column).cast("array<double>").alias("x"))
    picked = pick_centers(ids.select("doc_id"), k, seed)
    start = ids.join(F.broadcast(picked), "doc_id").orderBy("center_id").select("x").collect()
    centers = np.array([r["x"] for r in start])

    for _ in range(max_iter):
        n, total, _far = add_points(ids, centers)
        fresh = np.where(n[:, None] > 0, total / np.maximum(n, 1)[:, None], centers)
        if np.array_equal(fresh, centers):
            break
        centers = fresh
    last = centers

    def label(batches):
        for batch in batches:
            x, best = nearest_point(batch, last)
            yield pa.record_batch([batch.column("doc_id"), pa.array(best.astype(np.int64)), pa.array(((x - last[best]) ** 2).sum(axis=1))], names=["doc_id", "cluster_id", "dist2"])

    return ids.mapInArrow(label, "doc_id long, cluster_id long, dist2 double"), centers
