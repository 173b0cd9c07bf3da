"""Hierarchical clustering of a sample, then a few rounds of assignment (proposal b: H0-H13)."""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textgroups.functions.vectors import Vectors
from textgroups.operators import tables
from textgroups.operators.assign import assign_nearest, totals, unit
from textgroups.operators.hac import cluster_centers, link_in_one_task, mst_link, parthac, sample_clusters
from textgroups.operators.sampling import draw_sample, sample_size
from textgroups.plans.storage import materialise

#: Sample documents a part of the spanning-tree route, about: a pair of parts is a matrix of 128 MB in its task.
PART_ROWS = 2_000
#: Parts of aligned trees at least, so that the route is parallel for every sample.
LEAST_PARTS = 4
#: Samples of no more documents are clustered by one task (a matrix of 32 MB), with the same labels.
ONE_TASK_ROWS = 2_000
#: Labels of the sample go to the tasks by broadcast up to so many rows (16 bytes each).
BROADCAST_ROWS = 4_000_000


class SampleResult(NamedTuple):
    assign: DataFrame
    centers: np.ndarray | DataFrame
    sample: DataFrame
    info: dict


def seed_from_sample(vecs: Vectors, sample: DataFrame, s: int, k: int, linkage: str, hac: str, parts: int | None) -> DataFrame:
    """(doc_id, cluster_id) of the sample: ``mst`` (exact single link from part pairs), ``exact`` (any linkage, one
    task) or ``parts`` (aligned trees of random parts)."""
    if hac == "parts":
        return parthac(vecs, sample, k, parts or max(LEAST_PARTS, -(-s // PART_ROWS)), linkage)[0]
    parts = parts or max(1, -(-s // PART_ROWS))
    if hac == "mst" and linkage == "single":
        return mst_link(vecs, sample, k=k, parts=max(2, parts))
    return sample_clusters(vecs, sample, k, linkage)


def _by_table(vecs: Vectors, drawn: DataFrame, s: int, k: int, linkage: str, hac: str, parts: int | None, rounds: int, reassign_sample: bool) -> SampleResult:
    """The same with centres that stay a table."""
    fixed = materialise(seed_from_sample(vecs, materialise(drawn, "sample"), s, k, linkage, hac, parts), "seeded")
    centers = tables.unit_table(tables.sums_of(vecs, fixed.withColumnRenamed("cluster_id", "center_id")))
    held = None if reassign_sample else fixed.select("doc_id", F.col("cluster_id").alias("fixed"))
    history = []
    for _ in range(rounds - 1):
        now = tables.add_up(vecs, centers, held)
        history.append(now.rss())
        centers = tables.unit_table(now.sums, centers, now.head)
    found = assign_nearest(vecs, centers, "shuffle")
    if held is not None:
        found = found.join(held.hint("merge"), "doc_id", "left").withColumn("center_id", F.coalesce("fixed", "center_id")).drop("fixed")
    info = {"s": s, "rounds": rounds, "rss_by_round": history, "passes": rounds, "linkage": linkage, "hac": hac}
    return SampleResult(found.withColumnRenamed("center_id", "cluster_id"), centers, fixed, info)


def sampleseed(vecs: Vectors, k: int, *, s: int | None = None, linkage: str = "single", hac: str = "mst", parts: int | None = None, rounds: int = 2, reassign_sample: bool = False, seed: int = 42, strategy: str = "auto") -> SampleResult:
    """Proposal (b) (H0): sample of sqrt(k n) documents, hierarchical clustering, ``rounds`` rounds of assignment.

    The sample's documents keep their cluster unless ``reassign_sample`` (H11b); they count in the centroids anyway.
    ``strategy`` as in ``lloyd``: with the same labels, centres are a matrix or stay a table.
    """
    s = s or sample_size(vecs.n, k)
    drawn = draw_sample(vecs.packed.select("doc_id"), s, seed, n=vecs.n)
    if tables.by_table(strategy, k, vecs.v):
        return _by_table(vecs, drawn, s, k, linkage, hac, parts, rounds, reassign_sample)
    if hac == "mst" and linkage == "single" and parts is None and s <= ONE_TASK_ROWS:
        table, centers = link_in_one_task(vecs, drawn, k)
        fixed = vecs.packed.sparkSession.createDataFrame(table)
    else:
        fixed = materialise(seed_from_sample(vecs, materialise(drawn, "sample"), s, k, linkage, hac, parts), "seeded")
        centers = cluster_centers(vecs, fixed, k)
    labels = fixed.select("doc_id", F.col("cluster_id").alias("fixed"))
    marked = vecs.packed if reassign_sample else vecs.packed.join(F.broadcast(labels) if s <= BROADCAST_ROWS else labels, "doc_id", "left")
    history = []
    for _ in range(rounds - 1):
        now = totals(marked, centers, None if reassign_sample else "fixed")
        history.append(now.rss())
        centers = np.where(now.count > 0, unit(now.sums), centers)
    found = assign_nearest(vecs, centers)
    if not reassign_sample:
        found = found.join(F.broadcast(labels) if s <= BROADCAST_ROWS else labels, "doc_id", "left").withColumn("center_id", F.coalesce("fixed", "center_id")).drop("fixed")
    out = found.withColumnRenamed("center_id", "cluster_id")
    return SampleResult(out, centers, fixed, {"s": s, "rounds": rounds, "rss_by_round": history, "passes": rounds, "linkage": linkage, "hac": hac})
