"""Connected components of a large graph in few rounds."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textgroups.plans.storage import materialise

SCHEMES = ("min_label", "full_exchange", "cluster_to_min", "greater_to_min", "stars")


def spanning_forest(edges: DataFrame) -> DataFrame:
    """Replace each partition's edges ``(a, b)`` by a star forest with the same components.

    Lossless, and at most one edge per node and partition is left, which removes the redundancy of dense links before
    anything is shuffled.
    """

    def forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parent: dict[int, int] = {}

        def root(x: int) -> int:
            top = x
            while (up := parent.setdefault(top, top)) != top:
                top = up
            while (up := parent[x]) != top:
                parent[x], x = top, up
            return top

        for batch in batches:
            for x, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                x, y = root(x), root(y)
                if x != y:
                    parent[max(x, y)] = min(x, y)
        nodes = np.fromiter(parent, np.int64, len(parent))
        roots = np.fromiter((root(x) for x in list(parent)), np.int64, len(parent))
        far = nodes != roots
        nodes, roots = nodes[far], roots[far]
        for i in range(0, len(nodes), 100_000):
            yield pa.record_batch([pa.array(roots[i : i + 100_000]), pa.array(nodes[i : i + 100_000])], names=["a", "b"])

    return edges.select(F.col("a").cast("long"), F.col("b").cast("long")).mapInArrow(forest, "a long, b long")


def _stars(edges: DataFrame, max_rounds: int) -> tuple[DataFrame, int, int]:
    """Alternating large and small stars over parent edges ``(a, b)``, a the smaller end; ends in flat stars."""
    messages = 0
    now = materialise(spanning_forest(edges).distinct(), "stars")
    for rounds in range(1, max_rounds + 1):
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("m"))
        large = both.filter("b > a").join(least, "a").select(F.col("m").alias("a"), "b").filter("a <> b").distinct()
        low = large.groupBy("b").agg(F.min("a").alias("m"))
        small = large.join(low, "b")
        small = small.select(F.col("m").alias("a"), "b").unionByName(small.filter("a <> m").select(F.col("m").alias("a"), F.col("a").alias("b"))).distinct()
        after = materialise(small, "stars")
        ends = after.select(F.col("b").alias("node"), F.lit(1).alias("up"), F.lit(0).alias("down")).unionByName(after.select(F.col("a").alias("node"), F.lit(0).alias("up"), F.lit(1).alias("down")))
        ends = ends.groupBy("node").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
        edges_now, bent = (x or 0 for x in ends.agg(F.sum("up"), F.count_if((F.col("up") > 0) & (F.col("up") + F.col("down") > 1))).first())
        messages += 2 * edges_now
        # Flat when every node has one parent and no parent has one itself.
        if not bent:
            return after.select(F.col("b").alias("node"), F.col("a").alias("comp")), rounds, messages
        now = after
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")


def _min_label(both: DataFrame, max_rounds: int) -> tuple[DataFrame, int, int]:
    labels = materialise(both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("comp")).withColumnRenamed("a", "node"), "labels")
    messages = both.count()
    for rounds in range(1, max_rounds + 1):
        told = both.join(labels, both["a"] == labels["node"]).select(F.col("b").alias("node"), "comp")
        fresh = materialise(told.unionByName(labels).groupBy("node").agg(F.min("comp").alias("comp")), "labels")
        messages *= 1
        moved = fresh.join(labels.withColumnRenamed("comp", "was"), "node").filter("comp <> was").isEmpty()
        labels = fresh
        if moved:
            return labels, rounds, messages * (rounds + 1)
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")


def _exchange(known: DataFrame, scheme: str, max_rounds: int) -> tuple[DataFrame, int, int]:
    """Schemes on ``known(a, b)``: node a knows member b of its cluster (itself included), held as rows, not as sets."""
    messages = 0
    for rounds in range(1, max_rounds + 1):
        least = known.groupBy("a").agg(F.min("b").alias("m"))
        with_min = known.join(least, "a")
        back = with_min.select(F.col("b").alias("a"), F.col("m").alias("b"))
        to_min = with_min.select(F.col("m").alias("a"), "b")
        if scheme == "cluster_to_min" or rounds % 3:
            sent = to_min.unionByName(back) if scheme == "cluster_to_min" else to_min.unionByName(with_min.select("a", F.col("m").alias("b")))
        else:
            larger = with_min.filter("b >= a")
            sent = larger.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(larger.select(F.col("m").alias("a"), "b"))
        own = known.select("a", F.col("a").alias("b"))
        fresh = materialise(sent.unionByName(own).distinct(), "known")
        count = fresh.count()
        messages += count
        same = count == known.count() and fresh.join(known, ["a", "b"], "left_anti").isEmpty()
        known = fresh
        flat = scheme != "greater_to_min" or rounds % 3 == 0
        if same and flat:
            return known.groupBy("a").agg(F.min("b").alias("comp")).withColumnRenamed("a", "node"), rounds, messages
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")


#: A node of ``full_exchange`` that knows more members than this takes them in before it would send them to each other.
MOST_KNOWN = 16


def _full_exchange(known: DataFrame, max_rounds: int) -> tuple[DataFrame, int, int]:
    """Every node sends all of ``known(a, b)`` that it knows to every member it knows, until nobody learns anything.

    A node that knows more than ``MOST_KNOWN`` members becomes one node with them, at the start of a round; if it then
    knows as many again, it only listens in that round. So a round makes at most ``MOST_KNOWN`` rows of each row, however
    large a component is. Every link is kept, between the nodes that its ends became: ``taken(node, least, into)`` has
    one row a node for each round of that kind, and labels are handed back through these tables. Where a node is claimed
    by several, a hash that changes by round decides, so chains of such nodes shrink by a share, whatever their ids.
    """
    messages, taken = 0, []
    nodes = known.select(F.col("a").alias("node"), F.col("a").alias("least")).distinct()
    sizes = lambda rows: rows.groupBy("a").agg(F.count(F.lit(1)).alias("n"))
    large = F.col("n") > MOST_KNOWN

    def totals(rows: DataFrame) -> tuple[int, int]:
        return tuple(x or 0 for x in sizes(rows).agg(F.sum("n"), F.sum(F.when(large, F.col("n")))).first())

    count, claimed = totals(known)
    for rounds in range(1, max_rounds + 1):
        before, messages, sending = count, messages + claimed, known
        if claimed:
            claims = known.join(sizes(known).filter(large).select("a"), "a").groupBy("b").agg(F.min(F.struct(F.xxhash64(F.col("a"), F.lit(rounds)).alias("h"), "a"))["a"].alias("into"))
            taken.append(materialise(nodes.join(claims.withColumnRenamed("b", "node"), "node", "left").select("node", "least", F.coalesce("into", "node").alias("into")), "taken"))
            nodes = taken[-1].groupBy("into").agg(F.min("least").alias("least")).withColumnRenamed("into", "node")
            left = known.join(taken[-1].select(F.col("node").alias("a"), F.col("into").alias("x")), "a")
            both = left.join(taken[-1].select(F.col("node").alias("b"), F.col("into").alias("y")), "b")
            known = materialise(both.select(F.col("x").alias("a"), F.col("y").alias("b")).distinct(), "known")
            sending = known.join(sizes(known).filter(~large).select("a"), "a")
        sent = sending.join(sending.select("a", F.col("b").alias("c")), "a").select(F.col("b").alias("a"), F.col("c").alias("b"))
        known = materialise(known.unionByName(sent).distinct(), "known")
        merged = claimed > 0
        count, claimed = totals(known)
        messages += count
        if not merged and not claimed and count == before:
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    labels = known.join(nodes.withColumnsRenamed({"node": "b", "least": "m"}), "b").groupBy("a").agg(F.min("m").alias("comp")).withColumnRenamed("a", "node")
    for step in reversed(taken):
        labels = materialise(step.select("node", "into").join(labels.withColumnRenamed("node", "into").hint("merge"), "into").select("node", "comp"), "labels")
    return labels, rounds, messages


def components(edges: DataFrame, scheme: str = "stars", max_rounds: int = 200, info: dict | None = None) -> DataFrame:
    """Component (smallest node) of every node in ``edges(a, b)`` (B7, B7a-d; ``stars`` is the default for scale).

    Self loops keep a single node in the result; null ends are ignored; an empty input gives no rows. ``info`` gets
    ``rounds`` and ``messages`` (M8). Each round is written to the shared folder.
    """
    if scheme not in SCHEMES:
        raise ValueError(f"unknown scheme {scheme}")
    edges = edges.select(F.col("a").cast("long"), F.col("b").cast("long")).filter("a is not null and b is not null")
    info = {} if info is None else info
    if scheme == "stars":
        edges = materialise(edges, "edges")
        labels, info["rounds"], info["messages"] = _stars(edges.filter("a <> b"), max_rounds)
        nodes = edges.select(F.col("a").alias("node")).unionByName(edges.select(F.col("b").alias("node"))).distinct()
        return nodes.join(labels, "node", "left").select("node", F.coalesce("comp", "node").alias("comp"))
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct()
    both = materialise(both.unionByName(both.select("a", F.col("a").alias("b"))).distinct(), "both")
    if scheme == "min_label":
        labels, info["rounds"], info["messages"] = _min_label(both, max_rounds)
    elif scheme == "full_exchange":
        labels, info["rounds"], info["messages"] = _full_exchange(both, max_rounds)
    else:
        labels, info["rounds"], info["messages"] = _exchange(both, scheme, max_rounds)
    return labels
