"""Hierarchical clustering of samples: dendrograms, random parts, aligned trees, spanning trees."""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from textgroups.functions.text import UNIT
from textgroups.functions.vectors import Vectors
from textgroups.operators.assign import MATRIX_BYTES, checked, unit
from textgroups.operators.components import components, spanning_forest
from textgroups.plans.skew import join_lookup, running_totals
from textgroups.plans.storage import materialise

LINKAGES = ("single", "complete", "average", "centroid")
#: Documents that one task clusters at most: their products are a matrix of 200 MB.
MOST_ROWS = 5_000


def pairwise_sim(vecs: Vectors, members: DataFrame | None = None, min_sim: float | None = None) -> DataFrame:
    """(a, b, sim), a < b: products over shared terms, a self-join on the term (H3, O13). Pairs without one are left out."""
    postings = vecs.postings if members is None else vecs.postings.join(F.broadcast(members.select("doc_id")), "doc_id", "left_semi")
    left, right = postings.select("term_id", F.col("doc_id").alias("a"), F.col("wq").alias("x")), postings.select("term_id", F.col("doc_id").alias("b"), F.col("wq").alias("y"))
    dots = left.join(right.hint("merge"), "term_id").filter("a < b").groupBy("a", "b").agg(F.sum(F.col("x") * F.col("y")).alias("dp"))
    out = dots.select("a", "b", (F.col("dp") / float(UNIT * UNIT)).alias("sim"))
    return out if min_sim is None else out.filter(F.col("sim") >= min_sim)


#: Rows of a block of ``dense_pairs``: a task makes the pairs of two blocks.
PAIR_ROWS = 2048


def dense_pairs(points: DataFrame, id_col: str, column: str) -> DataFrame:
    """(a, b, cos), a < b: cosines of all pairs of points, two blocks in a task (O11). Pairs with a null vector have a
    null cosine, pairs with a vector of length zero NaN; vectors of unlike lengths are an error."""
    spark = points.sparkSession
    rows = materialise(points.select(F.col(id_col).cast("long").alias("id"), F.col(column).cast("array<double>").alias("x")), "points")
    blocks = max(1, -(-rows.count() // PAIR_ROWS))
    rows = rows.withColumn("block", F.pmod(F.xxhash64("id"), F.lit(blocks)))
    pairs = spark.range(blocks).select(F.col("id").alias("p")).join(spark.range(blocks).select(F.col("id").alias("q"))).filter("p <= q")
    dealt = rows.join(F.broadcast(pairs.select(F.explode(F.array_distinct(F.array("p", "q"))).alias("block"), "p", "q")), "block")

    def run(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches)).combine_chunks()
        ids, block = table.column("id").to_numpy(), table.column("block").to_numpy()
        vectors = table.column("x").combine_chunks()
        known = vectors.is_valid().to_numpy(zero_copy_only=False)
        flat = vectors.flatten().to_numpy(zero_copy_only=False)
        x = np.zeros((len(ids), len(flat) // max(1, known.sum())))
        x[known] = flat.reshape(int(known.sum()), -1) if known.any() else 0
        length = (x * x).sum(axis=1)
        one, two = (np.flatnonzero(block == k.as_py()) for k in key)
        for i in range(0, len(one), _ROWS):
            some = one[i : i + _ROWS]
            with np.errstate(divide="ignore", invalid="ignore"):
                cos = (x[some] @ x[two].T) / np.sqrt(length[some][:, None] * length[two])
            keep = ids[some][:, None] < ids[two] if key[0] == key[1] else np.ones(cos.shape, bool)
            r, c = np.nonzero(keep)
            a, b = ids[some[r]], ids[two[c]]
            yield pa.record_batch([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b)), pa.array(cos[r, c], mask=~(known[some[r]] & known[two[c]]))], names=["a", "b", "cos"])

    return dealt.select("p", "q", "id", "block", "x").groupBy("p", "q").applyInArrow(run, "a long, b long, cos double")


#: Points that a block holds at most, on average: a task compares two blocks, a few rows at a time.
BLOCK_ROWS = 16_384
_ROWS = 256


def _classes(x: np.ndarray, bound: float) -> np.ndarray:
    """Class of each row of ``x``: rows with a product of ``bound`` or more are linked. No product is kept."""
    some = np.zeros(len(x), bool)
    for i in range(0, len(x), _ROWS):
        near = x[i : i + _ROWS] @ x.T >= bound
        near[np.arange(len(near)), i + np.arange(len(near))] = False
        some[i : i + _ROWS] = near.any(axis=1)
    label, free, left = len(x) + np.arange(len(x)), np.flatnonzero(some), x[some]  # rows without a link are classes
    for c in range(len(x)):
        if not len(free):
            break
        label[free[0]] = c
        front, free, left = left[:1], free[1:], left[1:]
        while len(front) and len(free):
            near = np.zeros(len(free), bool)
            for i in range(0, len(front), _ROWS):
                near |= (left @ front[i : i + _ROWS].T >= bound).any(axis=1)
            if not near.any():
                break
            label[free[near]] = c
            front, free, left = left[near], free[~near], left[~near]
    return label


#: Bytes of the points of a tile, which is one row.
_TILE_BYTES = 1 << 19


def _met_tiles(tiles: DataFrame) -> DataFrame:
    """Every two tiles of unlike blocks, ``rep``, ``x`` and ``rep2``, ``x2``. A task reads its share of the written tiles
    again and again, so nothing is dealt and no copy of the points is written."""
    other = tiles.withColumnsRenamed({c: f"{c}2" for c in tiles.columns})
    return tiles.hint("shuffle_replicate_nl").join(other, F.col("block") < F.col("block2")).select("rep", "x", "rep2", "x2")


def threshold_components(vecs: Vectors, min_sim: float, scheme: str = "stars", info: dict | None = None) -> DataFrame:
    """(node, comp): components of the points of which every pair of similarity ``min_sim`` or more is linked.

    Points are dealt in blocks and written once, in tiles of a block's points. A task finds the classes of its block,
    another all links between the classes of tiles of two blocks; every pair of points is compared, but no pair is
    written, and of a task's links a spanning forest. Classes go by their smallest point, ``scheme`` finds the components
    of their links, and points follow their class.
    """
    v, blocks, bound = vecs.v, max(1, -(-vecs.n // BLOCK_ROWS)), min_sim * UNIT * UNIT
    tile = max(1, min(BLOCK_ROWS, _TILE_BYTES // (4 * max(1, v))))

    def dense(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes = pc.fill_null(pc.list_value_length(batch.column("idx")), 0).to_numpy(zero_copy_only=False)
            x = np.zeros((batch.num_rows, v), np.int32)
            x[np.repeat(np.arange(len(sizes)), sizes), batch.column("idx").flatten().to_numpy()] = batch.column("val").flatten().to_numpy()
            ends = pa.py_buffer((np.arange(len(sizes) + 1) * v * 4).astype(np.int32))
            yield pa.record_batch([batch.column("doc_id"), batch.column("block"), pa.Array.from_buffers(pa.binary(), len(sizes), [None, ends, pa.py_buffer(x.tobytes())])], names=["node", "block", "x"])

    def classes(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("node", ignore_index=True)
        nodes, x = pdf["node"].to_numpy(), np.frombuffer(b"".join(pdf["x"]), np.int32).reshape(len(pdf), v)
        _, first, label = np.unique(_classes(x.astype(np.float64), bound), return_index=True, return_inverse=True)
        reps = nodes[first[label]]
        order = np.argsort(reps, kind="stable")
        nodes, reps, x, starts = nodes[order], reps[order], x[order], range(0, len(pdf), tile)
        return pd.DataFrame({"block": pdf["block"].iloc[0], "node": [nodes[i : i + tile] for i in starts], "rep": [reps[i : i + tile] for i in starts], "x": [x[i : i + tile].tobytes() for i in starts]})

    def links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def side(rep: pa.Scalar, x: pa.Scalar) -> tuple:
            reps = rep.values.to_numpy()
            exact = np.frombuffer(x.as_buffer(), np.int32).reshape(len(reps), v).astype(np.float64)
            return exact, exact.astype(np.float32), np.sqrt((exact * exact).sum(axis=1).max(initial=0)), *np.unique(reps, return_index=True, return_inverse=True)

        for batch in batches:
            for row in zip(*batch.columns, strict=True):
                (x, fast, length, reps, _, label), (y, fast_y, length_y, others, start, _) = side(*row[:2]), side(*row[2:])
                # Single precision cannot be wrong by more than this: rows that may have a link are computed exactly.
                low, met = np.nextafter(np.float32(bound - (v + 4) * 2.0**-23 * length * length_y), np.float32(-np.inf)), []
                for i in range(0, len(x), _ROWS):
                    some = i + np.flatnonzero((fast[i : i + _ROWS] @ fast_y.T >= low).any(axis=1))
                    one, two = np.nonzero(np.logical_or.reduceat(x[some] @ y.T >= bound, start, axis=1))
                    met.append(np.unique(label[some[one]] * len(others) + two))
                cell = np.unique(np.concatenate(met))
                yield pa.record_batch([pa.array(reps[cell // len(others)]), pa.array(others[cell % len(others)])], names=["a", "b"])

    rows = vecs.packed.select("doc_id", "idx", "val", F.pmod(F.xxhash64("doc_id"), F.lit(blocks)).alias("block")).mapInArrow(dense, "node long, block long, x binary")
    tiles = materialise(rows.repartition(blocks, "block").groupBy("block").applyInPandas(classes, "block long, node array<long>, rep array<long>, x binary"), "tiles")
    members = tiles.select(F.explode(F.arrays_zip("node", "rep")).alias("m")).select("m.node", "m.rep")
    loops = members.select(F.col("rep").alias("a"), F.col("rep").alias("b")).distinct()
    if blocks > 1:
        loops = loops.unionByName(materialise(spanning_forest(_met_tiles(tiles.select("block", "rep", "x")).mapInArrow(links, "a long, b long")), "links"))
    comp = components(loops, scheme, info=info)
    return members.join(comp.withColumnRenamed("node", "rep").hint("merge"), "rep").select("node", "comp")


def agglomerate(sim: np.ndarray, k: int = 1, linkage: str = "single") -> tuple[list[tuple[int, int, float, int]], np.ndarray]:
    """Merge the most similar pair until ``k`` clusters are left: (merges (left, right, height, size), labels) (H4, H5).

    A cluster goes by its smallest member; ties go to the smaller pair. s - k merges are made (X7). For ``centroid``,
    ``sim`` holds the products of all pairs, also of a row with itself: a merged cluster's products are the sums of its
    halves', so no vectors are needed. The nearest neighbour of each cluster is kept, so a merge costs O(s) mostly.
    """
    s = len(sim)
    d = np.round(sim.astype(np.float64), 12)
    np.fill_diagonal(d, -np.inf)
    size, alive, owner = np.ones(s), np.ones(s, bool), np.arange(s)
    dots = sim.astype(np.float64) if linkage == "centroid" else None
    best = d.argmax(axis=1)
    value = d[np.arange(s), best]
    merges = []
    for _ in range(s - k):
        top = value.max()
        i = int(np.flatnonzero(value == top)[0])
        j = int(np.flatnonzero(d[i] == top)[0])
        i, j = min(i, j), max(i, j)
        merges.append((i, j, float(top), int(size[i] + size[j])))
        if linkage == "single":
            row = np.maximum(d[i], d[j])
        elif linkage == "complete":
            row = np.minimum(d[i], d[j])
        elif linkage == "average":
            row = (size[i] * d[i] + size[j] * d[j]) / (size[i] + size[j])
        else:
            dots[i] += dots[j]
            dots[:, i] += dots[:, j]
            norms = np.sqrt(dots.diagonal())
            row = dots[i] / np.maximum(norms[i] * norms, 1e-300)
        alive[j] = False
        row = np.where(alive, np.round(row, 12), -np.inf)
        row[i] = -np.inf
        d[i], d[:, i], d[j], d[:, j] = row, row, -np.inf, -np.inf
        size[i] += size[j]
        owner[owner == j] = i
        value[j] = -np.inf
        stale = np.flatnonzero(alive & ((best == i) | (best == j)))
        for x in {i, *stale.tolist()}:
            best[x] = d[x].argmax()
            value[x] = d[x, best[x]]
        nearer = alive & (row > value)
        best[nearer], value[nearer] = i, row[nearer]
    return merges, np.unique(owner, return_inverse=True)[1]


def cut_tree(merges: list[tuple[int, int, float, int]], s: int, k: int) -> np.ndarray:
    """Labels after the first s - k merges."""
    owner = np.arange(s)
    for left, right, *_ in merges[: max(0, s - k)]:
        owner[owner == right] = left
    return np.unique(owner, return_inverse=True)[1]


#: A term that more than 1/_DENSE of the rows hold goes through a dense product, others through their pairs of rows.
_DENSE = 10
#: Pairs of rows that the sparse part of a product matrix holds at once.
_PAIRS = 4_000_000


def _gram(pdf: pd.DataFrame, block: int = 8192) -> np.ndarray:
    """Products of all pairs of rows (idx, val), exact.

    Frequent terms are multiplied densely, in blocks; rare ones, which would be mostly zeros there, add up over the
    pairs of rows that share them. Memory follows the rows only.
    """
    sizes, n = pdf["idx"].map(len).to_numpy(), len(pdf)
    out = np.zeros((n, n))
    if not sizes.sum():
        return out
    row, idx, val = np.repeat(np.arange(n), sizes), np.concatenate(pdf["idx"].to_list()), np.concatenate(pdf["val"].to_list()).astype(np.float64)
    terms, idx, df = np.unique(idx, return_inverse=True, return_counts=True)
    order = np.argsort(idx, kind="stable")
    row, idx, val = row[order], idx[order], val[order]
    frequent = df * _DENSE > n
    dense = frequent[idx]
    place = np.cumsum(frequent) - 1
    drow, dterm, dval = row[dense], place[idx[dense]], val[dense]
    for first in range(0, int(frequent.sum()), block):
        a, b = np.searchsorted(dterm, [first, first + block])
        x = np.zeros((min(block, int(frequent.sum()) - first), n))
        x[dterm[a:b] - first, drow[a:b]] = dval[a:b]
        out += x.T @ x
    row, idx, val = row[~dense], idx[~dense], val[~dense]
    begin, upto = np.searchsorted(idx, idx, side="left"), np.cumsum(df[idx])
    first = 0
    while first < len(row):
        done = upto[first - 1] if first else 0
        last = max(first + 1, int(np.searchsorted(upto, done + _PAIRS, side="right")))
        some = df[idx[first:last]]
        one = np.repeat(np.arange(first, last), some)
        two = np.arange(len(one)) - np.repeat(np.cumsum(some) - some, some) + begin[one]
        out += np.bincount(row[one] * n + row[two], val[one] * val[two], n * n).reshape(n, n)
        first = last
    return out


def local_trees(vecs: Vectors, parts: DataFrame, linkage: str = "single") -> DataFrame:
    """(part, step, left, right, height, size): the dendrogram of each part, in one task a part (H7)."""
    rows = vecs.packed.join(F.broadcast(parts), "doc_id")

    def tree(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("rk")
        merges, _ = agglomerate(_gram(pdf) / UNIT / UNIT, 1, linkage)
        ids = pdf["doc_id"].to_numpy()
        return pd.DataFrame([(pdf["part"].iloc[0], i, ids[a], ids[b], h, n) for i, (a, b, h, n) in enumerate(merges)], columns=["part", "step", "left", "right", "height", "size"])

    return rows.groupBy("part").applyInPandas(tree, "part long, step int, left long, right long, height double, size long")


def _local_clusters(vecs: Vectors, parts: DataFrame, k: int, linkage: str, levels: bool = False) -> DataFrame:
    """(part, local, doc_id[, path]): labels of each part's tree cut at ``k``; ``path`` numbers tree nodes from the root."""
    rows = vecs.packed.join(F.broadcast(parts), "doc_id")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("rk")
        _, labels = agglomerate(_gram(pdf) / UNIT / UNIT, min(k, len(pdf)), linkage)
        return pd.DataFrame({"part": pdf["part"].to_numpy(), "local": labels.astype(np.int64), "doc_id": pdf["doc_id"].to_numpy()})

    return rows.groupBy("part").applyInPandas(run, "part long, local long, doc_id long")


def align_trees(vecs: Vectors, clusters: DataFrame, k: int, align: str = "cut") -> tuple[DataFrame, np.ndarray]:
    """One set of ``k`` clusters from the parts' clusters (H8): (doc_id, cluster_id) and the centres.

    ``cut``: starting from the first part, each part's clusters are matched one to one with the clusters so far, the
    most similar centroids first, and their sums are added. ``topdown``: the clusters are split in two by their
    centroids again and again in each part and halves are matched with halves. Only M k centroids come to the driver.
    """
    joined = vecs.postings.join(F.broadcast(clusters), "doc_id")
    got = joined.groupBy("part", "local", "term_id").agg(F.sum("wq").alias("s")).toArrow().to_pandas()
    parts = {p: np.zeros((vecs.v, k)) for p in sorted(got["part"].unique())}
    for p, rows in got.groupby("part"):
        parts[p][rows["term_id"], rows["local"]] = rows["s"]

    def order(sums: np.ndarray, members: list[int]) -> list[int]:
        """Leaves from a recursive two-way split, the heavier half first."""
        if len(members) < 2:
            return members
        c = unit(sums[:, members])
        _, labels = agglomerate(c.T @ c / UNIT / UNIT, 2, "average")
        halves = [[m for m, x in zip(members, labels, strict=True) if x == h] for h in (0, 1)]
        halves.sort(key=lambda h: (-float((sums[:, h].sum(axis=1) ** 2).sum()), h[0]))
        return order(sums, halves[0]) + order(sums, halves[1])

    total, match = None, {}
    for p, sums in parts.items():
        if total is None:
            total = sums.copy()
            match[p] = np.arange(k)
            continue
        own, base = unit(sums), unit(total)
        if align == "topdown":
            to = np.empty(k, np.int64)
            to[order(sums, list(range(k)))] = order(total, list(range(k)))
        else:
            cos = np.round(own.T @ base / UNIT / UNIT, 9)
            to = np.full(k, -1)
            taken = np.zeros(k, bool)
            for i in np.argsort(-cos, axis=None, kind="stable"):
                x, y = divmod(int(i), k)
                if to[x] < 0 and not taken[y]:
                    to[x], taken[y] = y, True
        match[p] = to
        for x in range(k):
            total[:, to[x]] += sums[:, x]
    table = [(int(p), x, int(y)) for p, to in match.items() for x, y in enumerate(to)]
    labels = clusters.join(F.broadcast(clusters.sparkSession.createDataFrame(table, "part long, local long, cluster_id long")), ["part", "local"]).select("doc_id", "cluster_id")
    return labels, unit(total if total is not None else np.zeros((vecs.v, k)))


class Node(NamedTuple):
    """A node of a part's merge tree; ``left`` and ``right`` are -1 for a leaf of the kept top."""

    left: int
    right: int
    height: float
    size: int
    idx: np.ndarray
    val: np.ndarray


def tree_tops(vecs: Vectors, parts: DataFrame, leaves: int, linkage: str) -> DataFrame:
    """The top of each part's merge tree, with ``leaves`` leaves at most: rows (part, node, left, right, height, size, idx,
    val) of its nodes, leaves with their vectors' sums, and rows (part, node, doc_id) of the documents below (H7)."""
    rows = vecs.packed.join(parts.hint("merge"), "doc_id")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        if len(pdf) > MOST_ROWS:
            raise ValueError(f"a part of {len(pdf)} documents is beyond {MOST_ROWS}: use more parts")
        pdf = pdf.sort_values("rk")
        part, n = int(pdf["part"].iloc[0]), len(pdf)
        merges, _ = agglomerate(_gram(pdf) / UNIT / UNIT, 1, linkage)
        label = cut_tree(merges, n, min(leaves, n))
        kept = int(label.max()) + 1
        cells = np.concatenate([np.zeros(0, np.int64), *pdf["idx"]]) | np.repeat(label, pdf["idx"].map(len)).astype(np.int64) << 32
        cell, inverse = np.unique(cells, return_inverse=True)
        sums = np.bincount(inverse, np.concatenate([np.zeros(0), *pdf["val"]]), len(cell)).astype(np.int64)
        ends, size = np.searchsorted(cell >> 32, np.arange(kept + 1)), np.bincount(label)
        out = [(part, i, -1, -1, 1.0, int(size[i]), (cell[a:b] & 0xFFFFFFFF).tolist(), sums[a:b].tolist(), None) for i, (a, b) in enumerate(zip(ends, ends[1:]))]
        at = {int(i): int(label[i]) for i in range(n)}  # node that a cluster's name (its first member) stands for
        for left, right, height, count in merges[n - kept :]:
            x, y, at[left] = at[left], at[right], len(out)
            out.append((part, len(out), x, y, float(height), int(count), None, None, None))
        out += [(part, int(x), None, None, None, None, None, None, int(d)) for x, d in zip(label, pdf["doc_id"], strict=True)]
        frame = pd.DataFrame(out, columns=["part", "node", "left", "right", "height", "size", "idx", "val", "doc_id"])
        return frame.astype({c: "Int64" for c in ("left", "right", "size", "doc_id")})

    return rows.groupBy("part").applyInPandas(run, "part long, node long, left long, right long, height double, size long, idx array<int>, val array<long>, doc_id long")


def trees_of(nodes: pa.Table) -> dict[int, list[Node]]:
    """The parts' trees from the rows of ``tree_tops``, in the order of part and node; an inner node's vector is the sum of
    its halves."""
    trees: dict[int, list[Node]] = {}
    for r in nodes.drop(["idx", "val"]).append_column("at", pa.array(np.arange(nodes.num_rows))).to_pylist():
        tree = trees.setdefault(r["part"], [])
        if r["left"] < 0:
            idx, val = (nodes.column(c)[r["at"]].values.to_numpy(zero_copy_only=False).astype(np.int64) for c in ("idx", "val"))
        else:
            x, y = tree[r["left"]], tree[r["right"]]
            idx, inverse = np.unique(np.concatenate([x.idx, y.idx]), return_inverse=True)
            val = np.bincount(inverse, np.concatenate([x.val, y.val]), len(idx)).astype(np.int64)
        tree.append(Node(r["left"], r["right"], r["height"], r["size"], idx, val))
    return trees


def align_trees_down(trees: dict[int, list[Node]], k: int, v: int) -> dict[tuple[int, int], int]:
    """Cluster of each leaf (part, node): the parts' trees aligned from their roots down (H8).

    A global node holds one node of each part, at first all roots. The global node whose halves are least similar (mean
    height of its parts' nodes, weighed by size) is split next: the largest part's halves are its two sides, every other
    part's halves go to the sides so that the sum of the cosines with what is there is largest, and a part's leaf goes
    to the more similar side; until there are ``k``. A side is one vector at a time, never a matrix of all.
    """

    def cos(node: Node, side: np.ndarray) -> float:
        length = float(np.sqrt((node.val.astype(np.float64) ** 2).sum() * (side * side).sum()))
        return round(float(side[node.idx] @ node.val) / length, 9) if length else 0.0

    def split(members: dict[int, int]) -> tuple[dict[int, int], dict[int, int]]:
        order = sorted(members, key=lambda p: (trees[p][members[p]].left < 0, -trees[p][members[p]].size, p))
        sides: tuple[dict[int, int], dict[int, int]] = ({}, {})
        held = np.zeros(v), np.zeros(v)
        for p in order:
            node = trees[p][members[p]]
            if node.left < 0:
                one = trees[p][members[p]]
                put = [(0 if cos(one, held[0]) >= cos(one, held[1]) else 1, members[p])]
            else:
                x, y = trees[p][node.left], trees[p][node.right]
                same = cos(x, held[0]) + cos(y, held[1]) >= cos(y, held[0]) + cos(x, held[1])
                put = [(0, node.left), (1, node.right)] if same else [(0, node.right), (1, node.left)]
            for side, at in put:
                sides[side][p] = at
                held[side][trees[p][at].idx] += trees[p][at].val
        return sides

    def weakness(members: dict[int, int]) -> float | None:
        inner = [trees[p][x] for p, x in members.items() if trees[p][x].left >= 0]
        return round(sum(n.height * n.size for n in inner) / sum(n.size for n in inner), 9) if inner else None

    clusters = [{p: len(t) - 1 for p, t in sorted(trees.items())}] if trees else []
    heights = [weakness(c) for c in clusters]
    while len(clusters) < k:
        open_ = [(h, i) for i, h in enumerate(heights) if h is not None]
        if not open_:
            break
        i = min(open_)[1]
        halves = split(clusters[i])
        clusters[i : i + 1], heights[i : i + 1] = halves, map(weakness, halves)
    out = {}
    for c, members in enumerate(clusters):
        for p, x in members.items():
            below = [x]
            while below:
                at = below.pop()
                node = trees[p][at]
                if node.left < 0:
                    out[p, at] = c
                else:
                    below += [node.left, node.right]
    return out


def parthac(vecs: Vectors, sample: DataFrame, k: int, parts: int, linkage: str = "single", align: str = "tree") -> tuple[DataFrame, np.ndarray | None]:
    """Hierarchical clustering over random parts with aligned trees (B5): (doc_id, cluster_id) and, but for ``tree``, the
    centres. ``sample(doc_id, rk)`` may be everything, in parts of up to MOST_ROWS documents.

    ``tree``: the tops of the local merge trees (2 k leaves each) are aligned from their roots down. ``cut`` and
    ``topdown``: the parts' clusters at k are matched (``align_trees``).
    """
    from textgroups.operators.sampling import random_parts

    dealt = random_parts(sample, parts)
    if align != "tree":
        return align_trees(vecs, _local_clusters(vecs, dealt, k, linkage), k, align)
    found = materialise(tree_tops(vecs, dealt, 2 * k, linkage), "trees")
    nodes = found.filter("doc_id is null")
    if (cells := nodes.agg(F.sum(F.size("idx"))).first()[0] or 0) * 12 > MATRIX_BYTES:
        raise ValueError(f"{cells} cells of tree nodes are too many for the driver: use fewer parts")
    trees = trees_of(nodes.drop("doc_id").orderBy("part", "node").toArrow())  # of a checked size
    table = [(int(p), int(x), c) for (p, x), c in align_trees_down(trees, k, vecs.v).items()]
    of = vecs.packed.sparkSession.createDataFrame(table, "part long, node long, cluster_id long")
    return found.filter("doc_id is not null").join(F.broadcast(of), ["part", "node"]).select("doc_id", "cluster_id"), None


def spanning_tree(gram: np.ndarray, ids: np.ndarray) -> list[tuple[int, int, int]]:
    """Maximum spanning tree (a, b, product) of a product matrix by Prim; the order (product, then smaller ids) is
    total, so the tree is unique."""
    n = len(ids)
    if n < 2:
        return []
    inside = np.zeros(n, bool)
    inside[0] = True
    gram = gram.astype(np.int64)
    best = gram[0].copy()
    link = np.zeros(n, np.int64)
    out = []
    for _ in range(n - 1):
        free = np.flatnonzero(~inside)
        free = free[best[free] == best[free].max()]
        low, high = np.minimum(ids[free], ids[link[free]]), np.maximum(ids[free], ids[link[free]])
        j = free[np.lexsort((high, low))[0]]
        a, b = sorted((int(ids[j]), int(ids[link[j]])))
        out.append((a, b, int(best[j])))
        inside[j] = True
        dots = gram[j]
        pair = lambda o: (np.minimum(ids, ids[o]), np.maximum(ids, ids[o]))
        (l1, h1), (l0, h0) = pair(np.full(n, j)), pair(link)
        better = ~inside & ((dots > best) | ((dots == best) & ((l1 < l0) | ((l1 == l0) & (h1 < h0)))))
        best[better], link[better] = dots[better], j
    return out


def forest(edges: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """Maximum spanning forest of edges (a, b, product) by Kruskal, in the total order."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    out = []
    for a, b, w in sorted(set(edges), key=lambda e: (-e[2], e[0], e[1])):
        x, y = root(a), root(b)
        if x != y:
            parent[max(x, y)] = min(x, y)
            out.append((a, b, w))
    return out


def mst(vecs: Vectors, members: DataFrame, parts: int = 4, fan_in: int = 4) -> DataFrame:
    """(a, b, dp): the spanning tree of ``members(doc_id, rk)`` from trees of part pairs.

    Every pair of parts is one task that runs Prim; trees are merged ``fan_in`` at a time by Kruskal until one is left,
    each level written. A task holds two parts, a merge at most ``fan_in`` trees of fewer edges than members.
    """
    spark = vecs.packed.sparkSession
    rows = vecs.packed.join(members.hint("merge"), "doc_id").withColumn("part", F.col("rk") % parts)
    one = spark.range(parts).select(F.col("id").alias("p"))
    table = one.select("p", F.explode(F.sequence(F.least(F.col("p") + 1, F.lit(parts - 1)), F.lit(parts - 1))).alias("q")).filter("p < q" if parts > 1 else "true")
    table = table.withColumn("pair", (F.row_number().over(Window.orderBy("p", "q")) - 1).cast("long"))
    table = table.select("pair", F.explode(F.array_distinct(F.array("p", "q"))).alias("part"))
    left = max(1, parts * (parts - 1) // 2)
    dealt = rows.join(F.broadcast(table), "part")

    def prim(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("doc_id")
        return pd.DataFrame([(pdf["pair"].iloc[0], *e) for e in spanning_tree(_gram(pdf), pdf["doc_id"].to_numpy())], columns=["pair", "a", "b", "dp"])

    schema = "pair long, a long, b long, dp long"
    trees = materialise(dealt.groupBy("pair").applyInPandas(prim, schema), "trees")

    def kruskal(pdf: pd.DataFrame) -> pd.DataFrame:
        kept = forest(list(zip(pdf["a"].tolist(), pdf["b"].tolist(), pdf["dp"].tolist(), strict=True)))
        return pd.DataFrame([(pdf["pair"].iloc[0], *e) for e in kept], columns=["pair", "a", "b", "dp"])

    while left > 1:
        left = -(-left // fan_in)
        trees = materialise(trees.withColumn("pair", F.floor(F.col("pair") / fan_in)).groupBy("pair").applyInPandas(kruskal, schema), "trees")
    return trees.select("a", "b", "dp")


def cut_mst(tree: list[tuple[int, int, int]], ids: list[int], k: int | None = None, threshold: float | None = None) -> dict[int, int]:
    """Cluster of each id after the k - 1 weakest edges (or those below a similarity) are cut; numbered by order of ids."""
    ranked = sorted(tree, key=lambda e: (-e[2], e[0], e[1]))
    kept = ranked[: max(0, len(ids) - k)] if k is not None else [e for e in ranked if e[2] / UNIT / UNIT >= threshold]
    parent = {i: i for i in ids}

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a, b, _ in kept:
        x, y = root(a), root(b)
        parent[max(x, y)] = min(x, y)
    number: dict[int, int] = {}
    return {i: number.setdefault(root(i), len(number)) for i in ids}


def mst_link(vecs: Vectors, members: DataFrame, k: int | None = None, threshold: float | None = None, parts: int = 4, fan_in: int = 4) -> DataFrame:
    """Single-link clusters (doc_id, cluster_id) of ``members(doc_id, rk)`` through the spanning tree.

    The k - 1 weakest edges (or those below a similarity) are cut, what is left are components; clusters are numbered by
    their first member. Edges and members stay tables; only the k - 1 cut edges go to all tasks.
    """
    members = materialise(members.select("doc_id", "rk"), "members")
    tree = mst(vecs, members, parts, fan_in)
    if k is not None:
        weak = tree.orderBy("dp", F.desc("a"), F.desc("b")).limit(max(0, k - 1))
        kept = tree.join(F.broadcast(weak), ["a", "b"], "left_anti")
    else:
        kept = tree.filter(F.col("dp") / float(UNIT) / UNIT >= threshold)
    loops = members.select(F.col("doc_id").alias("a"), F.col("doc_id").alias("b"))
    comp = materialise(components(kept.select("a", "b").unionByName(loops)).join(members.withColumnRenamed("doc_id", "node").hint("merge"), "node"), "comp")
    first = comp.groupBy("comp").agg(F.min("rk").alias("first"), F.count(F.lit(1)).alias("n")).withColumn("_all", F.lit(0)).withColumn("_b", F.floor(F.col("first") / 1000))
    number = running_totals(materialise(first, "first"), ["_all"], "_b", [F.col("first")], F.lit(0), "cluster_id", "_z")
    return join_lookup(comp, materialise(number.select("comp", "n", "cluster_id"), "number"), "comp", "n").select(F.col("node").alias("doc_id"), "cluster_id")


def link_in_one_task(vecs: Vectors, members: DataFrame, k: int) -> tuple[pa.Table, np.ndarray]:
    """Labels and unit centroids of ``mst_link`` for a small sample, in one job: (doc_id, cluster_id) and the matrix.

    One task holds the members' product matrix, so the caller checks their number; what comes back is a row a member
    and a vector a cluster.
    """
    rows = vecs.packed.join(F.broadcast(members), "doc_id").select("doc_id", "rk", "idx", "val").repartition(1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        pdf = pa.Table.from_batches(got).to_pandas().sort_values("doc_id")
        tree = spanning_tree(_gram(pdf), pdf["doc_id"].to_numpy())
        of = cut_mst(tree, pdf.sort_values("rk")["doc_id"].tolist(), k)
        label = pdf["doc_id"].map(of).to_numpy()
        sizes = pdf["idx"].map(len).to_numpy()
        idx, val = np.concatenate(pdf["idx"].to_list()), np.concatenate(pdf["val"].to_list()).astype(np.int64)
        cell, inverse = np.unique(np.repeat(label, sizes).astype(np.int64) << 32 | idx, return_inverse=True)
        sums = np.bincount(inverse, val, len(cell)).astype(np.int64)
        ends = np.searchsorted(cell >> 32, np.arange(int(label.max()) + 2)).astype(np.int32)
        none = lambda n, kind: pa.nulls(n, kind)
        lists = pa.list_(pa.int32()), pa.list_(pa.int64())
        names = ["doc_id", "cluster_id", "idx", "sums"]
        yield pa.record_batch([pa.array(pdf["doc_id"].to_numpy()), pa.array(label.astype(np.int64)), none(len(pdf), lists[0]), none(len(pdf), lists[1])], names=names)
        groups = len(ends) - 1
        yield pa.record_batch([none(groups, pa.int64()), pa.array(np.arange(groups)), pa.ListArray.from_arrays(ends, pa.array((cell & 0xFFFFFFFF).astype(np.int32))), pa.ListArray.from_arrays(ends, pa.array(sums))], names=names)

    got = rows.mapInArrow(run, "doc_id long, cluster_id long, idx array<int>, sums array<long>").toArrow()
    known = got.column("doc_id").is_valid()
    matrix = np.zeros((vecs.v, k))
    for r in got.filter(pc.invert(known)).select(["cluster_id", "idx", "sums"]).to_pylist():
        matrix[r["idx"], r["cluster_id"]] = r["sums"]
    return got.filter(known).select(["doc_id", "cluster_id"]), unit(matrix)


def cluster_centers(vecs: Vectors, labels: DataFrame, k: int) -> np.ndarray:
    """Unit centroids of labelled documents (H9), a matrix of a checked size."""
    checked(k, vecs.v)
    got = vecs.postings.join(F.broadcast(labels), "doc_id").groupBy("cluster_id", "term_id").agg(F.sum("wq").alias("s")).toArrow()
    out = np.zeros((vecs.v, k))
    out[got.column("term_id").to_numpy(), got.column("cluster_id").to_numpy()] = got.column("s").to_numpy()
    return unit(out)


def sample_clusters(vecs: Vectors, sample: DataFrame, k: int, linkage: str = "single") -> DataFrame:
    """(doc_id, cluster_id) of a sample by the sequential algorithm in one task (H4), of up to MOST_ROWS documents."""
    if (s := sample.count()) > MOST_ROWS:
        raise ValueError(f"a sample of {s} documents is beyond one task's {MOST_ROWS}: use hac='parts', or 'mst' for single link")
    rows = vecs.packed.join(F.broadcast(sample), "doc_id").repartition(1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        if got:
            pdf = pa.Table.from_batches(got).to_pandas().sort_values("rk")
            _, labels = agglomerate(_gram(pdf) / UNIT / UNIT, min(k, len(pdf)), linkage)
            yield pa.record_batch([pa.array(pdf["doc_id"].to_numpy()), pa.array(labels.astype(np.int64))], names=["doc_id", "cluster_id"])

    return rows.select("doc_id", "rk", "idx", "val").mapInArrow(run, "doc_id long, cluster_id long")
