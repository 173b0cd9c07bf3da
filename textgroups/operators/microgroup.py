"""Many micro-clusters first, then links between them, then one assignment (proposal a: A0-A15)."""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textgroups.functions.text import UNIT
from textgroups.functions.vectors import Vectors
from textgroups.operators import assign, tables
from textgroups.operators.assign import Totals, assign_nearest, totals, unit, vectors_of
from textgroups.operators.sampling import pick_centers

ZERO_RULES = ("either", "both", "off", "cosine")
#: Links between micro-clusters are held on the driver up to so many micro-clusters (m * m / 2 pairs).
MOST_MICRO = 5000
#: Matrices of its size that a build by matrix holds at once on the driver: centres, sums and copies without the empty ones.
_COPIES = 4


class Micro(NamedTuple):
    """Micro-clusters in the order of the draw: centre documents, counts, sums, square sums, lowest similarities."""

    centers: np.ndarray
    stats: Totals

    @property
    def m(self) -> int:
        return self.centers.shape[1]

    @property
    def least(self) -> np.ndarray:
        return self.stats.least

    @property
    def rss(self) -> float:
        return cf_rss(self.stats)

    def links(self, zero_rule: str = "either", clamp: bool = True) -> Links:
        return micro_similarity(self.centers, self.least, zero_rule, clamp)

    def head(self, spark) -> DataFrame:
        """(mc_id, n, ss, min_sim) (DM6)."""
        s = self.stats
        return spark.createDataFrame(pa.table({"mc_id": np.arange(self.m), "n": s.count.astype(np.int64), "ss": s.square / UNIT / UNIT, "min_sim": s.least}))

    def sums(self, spark) -> DataFrame:
        """(mc_id, term_id, s)."""
        t, c = np.nonzero(self.stats.sums)
        return spark.createDataFrame(pa.table({"mc_id": c, "term_id": t, "s": self.stats.sums[t, c].astype(np.int64)}))


class MicroResult(NamedTuple):
    assign: DataFrame
    centers: np.ndarray | DataFrame
    micro: Micro | MicroTable
    groups: np.ndarray
    info: dict


def build_micro(vecs: Vectors, n_micro: int, seed: int = 42, keep_empty: bool = False) -> Micro:
    """Draw, assign and add up in one pass (A1-A3). An empty micro-cluster is dropped (A3e) or kept with lowest
    similarity 1; a micro-cluster that holds its centre alone has lowest similarity 1 by itself (A3s)."""
    if n_micro > MOST_MICRO:
        raise ValueError(f"links of more than {MOST_MICRO} micro-clusters are not held on the driver")
    centers = vectors_of(vecs, pick_centers(vecs.packed.select("doc_id"), min(n_micro, vecs.n), seed, n=vecs.n))
    got = totals(vecs.packed, centers)
    if keep_empty:
        none = got.count == 0
        got.least[none] = 1.0
        return Micro(centers, got)
    some = got.count > 0
    return Micro(centers[:, some], Totals(got.sums[:, some], got.count[some], got.square[some], got.least[some]))


def initial_threshold(least: np.ndarray) -> float:
    """Mean of the lowest similarities (A4)."""
    return float(np.mean(least)) if len(least) else 0.0


class Links(NamedTuple):
    """All pairs a < b with centre cosine, similarity (cosine less both lowest similarities) and kind.

    kind 2: positive similarity; 1: clamped to zero, but the cosine reaches the lowest similarities as the zero rule
    asks; 0: no link.
    """

    a: np.ndarray
    b: np.ndarray
    cos: np.ndarray
    sim: np.ndarray
    kind: np.ndarray

    def frame(self, spark) -> DataFrame:
        return spark.createDataFrame(pa.table(self._asdict()))


def micro_similarity(centers: np.ndarray, least: np.ndarray, zero_rule: str = "either", clamp: bool = True) -> Links:
    """Similarity of every pair (A5, A7); ``clamp=False`` keeps the sign (A5r); ``cosine`` links by centre cosine only."""
    return links_of_products(centers.T @ centers, least, zero_rule, clamp)


def links_of_products(dots: np.ndarray, least: np.ndarray, zero_rule: str = "either", clamp: bool = True) -> Links:
    """The same from the products of all pairs of centres."""
    if zero_rule not in ZERO_RULES:
        raise ValueError(f"unknown zero rule {zero_rule}")
    m = len(dots)
    gram = np.round(dots / UNIT / UNIT, 12)
    a, b = np.triu_indices(m, 1)
    cos = gram[a, b]
    raw = np.round(cos - least[a] - least[b], 12)
    if zero_rule == "cosine":
        return Links(a, b, cos, cos, np.where(cos > 0, 2, 0))
    if not clamp:
        return Links(a, b, cos, raw, np.full(len(a), 2))
    reach = (cos >= least[a], cos >= least[b])
    zero = {"either": reach[0] | reach[1], "both": reach[0] & reach[1], "off": np.zeros(len(a), bool)}[zero_rule]
    return Links(a, b, cos, np.maximum(raw, 0), np.where(raw > 0, 2, np.where(zero, 1, 0)))


def link_edges(links: Links, s: float, strict: bool = False) -> np.ndarray:
    """Which pairs are linked at a threshold (A6, A7): zero-rule pairs always, positive ones from the threshold on."""
    reach = links.sim > s if strict else links.sim >= s
    return (links.kind == 1) | ((links.kind == 2) & reach)


def group(links: Links, linked: np.ndarray, m: int, link: str = "first") -> np.ndarray:
    """Group of each micro-cluster, groups numbered by their first member.

    ``first`` (A8b): a micro-cluster joins the group of the first earlier one it is linked with. ``closure`` (A8a): the
    groups are the classes of the transitive closure.
    """
    parent = np.arange(m)
    if link == "first":
        np.minimum.at(parent, links.b[linked], links.a[linked])
        while (up := parent[parent]).tolist() != parent.tolist():  # pointer jumping
            parent = up
    else:
        for x, y in zip(links.a[linked].tolist(), links.b[linked].tolist(), strict=True):
            while parent[x] != x:
                parent[x] = parent[parent[x]]
                x = parent[x]
            while parent[y] != y:
                parent[y] = parent[parent[y]]
                y = parent[y]
            parent[max(x, y)] = min(x, y)
        while (up := parent[parent]).tolist() != parent.tolist():
            parent = up
    return np.unique(parent, return_inverse=True)[1]


def count_groups(links: Links, s: float, m: int, link: str = "first", strict: bool = False) -> int:
    return int(group(links, link_edges(links, s, strict), m, link).max(initial=-1)) + 1


def threshold_search(links: Links, m: int, k: int, s0: float, how: str = "bisect", link: str = "first", step: float = 0.9, rounds: int = 60) -> tuple[float, int, int]:
    """(threshold, groups, trials) nearest to ``k`` groups by steps (A9a) or bisection.

    More groups are wanted: the threshold rises; fewer: it falls (X6).
    """
    best, s, trials = None, s0, 0
    low, high = -1.0, float(links.sim.max(initial=0)) + 1.0
    direction = 0
    for trials in range(1, rounds + 1):
        g = count_groups(links, s, m, link)
        if best is None or abs(g - k) < abs(best[1] - k):
            best = (s, g)
        if g == k:
            break
        if how == "bisect":
            low, high = (s, high) if g < k else (low, s)
            s = (low + high) / 2
        else:
            turn = 1 if g < k else -1
            if direction and turn != direction:
                break
            direction = turn
            s = s / step if turn > 0 else s * step
    return (*best, trials)


def total_order(links: Links) -> np.ndarray:
    """Pairs from the strongest on: positive ones by similarity, zero-rule ones and the rest by cosine (A10 ``rank``)."""
    weight = np.where(links.kind == 2, links.sim, links.cos)
    return np.lexsort((links.b, links.a, -links.cos, -weight, -links.kind))


def link_by_rank(links: Links, m: int, k: int, link: str) -> np.ndarray:
    """The shortest head of the total order that leaves ``k`` groups."""
    order = total_order(links)
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))
    linked = np.zeros(len(order), bool)
    if m <= k:
        return linked
    if link == "first":
        critical = np.full(m, len(order))
        np.minimum.at(critical, links.b, place)
        return place <= np.sort(critical[1:])[m - k - 1]
    parent = list(range(m))

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    left = m
    for i in order.tolist():
        x, y = root(int(links.a[i])), root(int(links.b[i]))
        if x != y:
            parent[max(x, y)] = min(x, y)
            left -= 1
        linked[i] = True
        if left == k:
            break
    return linked


def exact_threshold(links: Links, m: int, k: int, link: str = "first") -> tuple[float, int]:
    """(threshold, groups) nearest to ``k`` groups without trials: the group count is a step function of the threshold
    that jumps at the critical values only (A9c)."""
    values = np.unique(links.sim[links.kind == 2])
    tried = np.concatenate([[0.0], values, [values.max(initial=0) + 1]])
    if link == "first":
        always = np.zeros(m, bool)
        always[links.b[links.kind == 1]] = True
        critical = np.full(m, -1.0)
        np.maximum.at(critical, links.b[links.kind == 2], links.sim[links.kind == 2])
        free = np.sort(critical[~always])
        counts = np.searchsorted(free, tried, side="left")
    else:
        counts = np.array([count_groups(links, s, m, link) for s in tried])
    i = int(np.lexsort((tried, np.abs(counts - k)))[0])
    return float(tried[i]), int(counts[i])


def group_centers(micro: Micro, groups: np.ndarray, center: str = "mean") -> np.ndarray:
    """Centres of groups: the members' linear sums added up (A11), or the mean of the centre documents."""
    g = int(groups.max(initial=-1)) + 1
    source = micro.stats.sums if center == "mean" else micro.centers
    out = np.zeros((source.shape[0], g))
    for i, x in enumerate(groups):
        out[:, x] += source[:, i]
    return unit(out)


def cf_rss(stats: Totals) -> float:
    """RSS of the micro-clusters from their counts and sums alone."""
    return stats.rss()


class MicroTable(NamedTuple):
    """Micro-clusters whose vectors stay tables; what is here of each is a few numbers."""

    centers: DataFrame
    added: DataFrame
    count: np.ndarray
    square: np.ndarray
    least: np.ndarray
    rss: float

    @property
    def m(self) -> int:
        return len(self.count)

    def head(self, spark) -> DataFrame:
        return spark.createDataFrame(pa.table({"mc_id": np.arange(self.m), "n": self.count.astype(np.int64), "ss": self.square / UNIT / UNIT, "min_sim": self.least}))

    def sums(self, spark) -> DataFrame:
        return self.added.select(F.col("center_id").alias("mc_id"), "term_id", "s").filter("s <> 0")

    def links(self, zero_rule: str = "either", clamp: bool = True) -> Links:
        return links_of_products(tables.products(self.centers, self.m), self.least, zero_rule, clamp)


def build_micro_table(vecs: Vectors, n_micro: int, seed: int = 42, keep_empty: bool = False, shuffle: bool = False) -> MicroTable:
    """``build_micro`` without a matrix: the micro-clusters are renumbered over those that are not dropped. Documents meet
    the centres in one pass if these have few terms, else (or if asked for) by a shuffle."""
    if n_micro > MOST_MICRO:
        raise ValueError(f"links of more than {MOST_MICRO} micro-clusters are not held on the driver")
    n_micro = min(n_micro, vecs.n)
    centers = tables.chosen(vecs, pick_centers(vecs.packed.select("doc_id"), n_micro, seed, n=vecs.n))
    found = None if shuffle else tables.add_up_sparse(vecs, centers, n_micro)
    sums, head = found or tables.add_up(vecs, centers)[1:]
    count, square, least = np.zeros(n_micro), np.zeros(n_micro), np.full(n_micro, float(UNIT * UNIT))
    for r in head.select("center_id", "n", "ss", "low").collect():
        count[r["center_id"]], square[r["center_id"]], least[r["center_id"]] = r["n"], r["ss"], r["low"]
    some = np.arange(n_micro) if keep_empty else np.flatnonzero(count > 0)
    number = vecs.packed.sparkSession.createDataFrame(pa.table({"center_id": some.astype(np.int64), "mc": np.arange(len(some))}))
    renumber = lambda df: df.join(F.broadcast(number), "center_id").drop("center_id").withColumnRenamed("mc", "center_id")
    return MicroTable(renumber(centers), renumber(sums), count[some], square[some], least[some] / UNIT / UNIT, tables.rss_of_head(head))


def choose_groups(links: Links, least: np.ndarray, k: int, link: str, threshold: str, unreachable: str) -> tuple[np.ndarray, dict]:
    """(group of each micro-cluster, what the threshold and the literal relation gave) (A4-A10)."""
    m, trials = len(least), 0
    s0 = initial_threshold(least)
    if threshold in ("exact", "rank"):
        s, reached = exact_threshold(links, m, k, link)
    else:
        s, reached, trials = threshold_search(links, m, k, s0, threshold, link)
    policy = "threshold"
    linked = link_edges(links, s)
    if threshold == "rank":
        policy, linked = "rank", link_by_rank(links, m, k, link)
    elif reached != min(k, m):
        if unreachable == "error":
            raise ValueError(f"no threshold leaves {k} groups, the nearest count is {reached}")
        policy = unreachable
        linked = link_by_rank(links, m, k, link) if unreachable == "rank" else linked
    groups = group(links, linked, m, link)
    found = int(groups.max(initial=-1)) + 1
    return groups, {"s0": s0, "s_link": s, "groups_at_s0": count_groups(links, s0, m, link), "groups_literal": reached, "k_reached": found == k, "policy_used": policy, "trials": trials, "groups": found, "n_micro": m}


def microgroup(vecs: Vectors, k: int, n_micro: int, *, seed: int = 42, link: str = "first", zero_rule: str = "either", clamp: bool = True, threshold: str = "exact", unreachable: str = "rank", final_rounds: int = 1, center: str = "mean", keep_empty: bool = False, strategy: str = "auto") -> MicroResult:
    """Proposal (a) (A0): two passes over the documents, whatever the number of micro-clusters.

    ``threshold="rank"`` cuts the total order of all pairs whether or not a threshold leaves ``k`` groups: the two differ
    where one does, since it links all zero-rule pairs. ``unreachable`` (A10): if no threshold leaves ``k`` groups, cut the total order of all pairs (``rank``), take the
    nearest count that a threshold gives (``nearest``), or fail (``error``). ``info`` always says what the literal
    relation gave. ``strategy`` as in ``lloyd``: with the same labels, centres are a matrix or stay a table.
    """
    micro = build(vecs, n_micro, seed, keep_empty, strategy)
    return regroup(vecs, micro, k, strategy=strategy, link=link, zero_rule=zero_rule, clamp=clamp, threshold=threshold, unreachable=unreachable, final_rounds=final_rounds, center=center)


def build(vecs: Vectors, n_micro: int, seed: int = 42, keep_empty: bool = False, strategy: str = "auto") -> Micro | MicroTable:
    """Micro-clusters by a matrix of centres, or with vectors that stay tables where that would be too large (A1-A3)."""
    if tables.by_table(strategy, _COPIES * n_micro, vecs.v):
        return build_micro_table(vecs, n_micro, seed, keep_empty, strategy == "shuffle")
    return build_micro(vecs, n_micro, seed, keep_empty)


def regroup(vecs: Vectors, micro: Micro | MicroTable, k: int, *, link: str = "first", zero_rule: str = "either", clamp: bool = True, threshold: str = "exact", unreachable: str = "rank", final_rounds: int = 1, center: str = "mean", strategy: str = "auto") -> MicroResult:
    """The method from given micro-clusters on."""
    groups, info = choose_groups(micro.links(zero_rule, clamp), micro.least, k, link, threshold, unreachable)
    if isinstance(micro, MicroTable):
        of = vecs.packed.sparkSession.createDataFrame(pa.table({"center_id": np.arange(len(groups)), "g": groups.astype(np.int64)}))
        source = micro.added if center == "mean" else micro.centers.withColumnRenamed("cq", "s")
        added = source.join(F.broadcast(of), "center_id").groupBy(F.col("g").alias("center_id"), "term_id").agg(F.sum("s").alias("s"))
        centers = tables.unit_table(tables.materialise(added, "sums"))
        if tables.by_table(strategy, info["groups"], vecs.v):
            for _ in range(final_rounds - 1):
                now = tables.add_up(vecs, centers)
                centers = tables.unit_table(now.sums, centers, now.head)
            labels = assign_nearest(vecs, centers, "shuffle").withColumnRenamed("center_id", "cluster_id")
            return MicroResult(labels, centers, micro, groups, info | {"passes": 1 + final_rounds, "cf_rss": micro.rss})
        centers = assign.centre_matrix(centers, vecs.v, info["groups"])
    else:
        centers = group_centers(micro, groups, center)
    for _ in range(final_rounds - 1):  # A12r
        now = totals(vecs.packed, centers)
        fresh = unit(now.sums)
        centers = np.where(now.count > 0, fresh, centers)
    labels = assign_nearest(vecs, centers).withColumnRenamed("center_id", "cluster_id")
    return MicroResult(labels, centers, micro, groups, info | {"passes": 1 + final_rounds, "cf_rss": micro.rss})


def rss_of(vecs: Vectors, centers: np.ndarray | DataFrame) -> float:
    """RSS of the assignment to ``centers``, a matrix or a table."""
    if isinstance(centers, np.ndarray):
        return totals(vecs.packed, centers).rss()
    if assign.fits(k := (centers.agg(F.max("center_id")).first()[0] or 0) + 1, vecs.v):
        return totals(vecs.packed, assign.centre_matrix(centers, vecs.v, k)).rss()
    return tables.add_up(vecs, centers).rss()


def sweep_micro(vecs: Vectors, k: int, ratios: tuple[float, ...] = (5, 3, 2.25, 2), seed: int = 42) -> list[dict]:
    """The method at several numbers of micro-clusters per group."""
    out = []
    for r in ratios:
        got = microgroup(vecs, k, int(r * k), seed=seed, threshold="rank")
        out.append({"ratio": r, "n_micro": got.info["n_micro"], "rss": rss_of(vecs, got.centers), **got.info})
    return out


def micro_points_euclidean(points: DataFrame, k: int, n_micro: int, seed: int = 42, id_col: str = "vec_id", column: str = "embedding") -> DataFrame:
    """The point form (A14): radius (largest distance) instead of the lowest similarity, gap between spheres as the
    link measure, smallest gaps first until ``k`` groups are left; then one assignment to the groups' means."""
    from textgroups.operators.lloyd import add_points, lloyd_euclidean

    _, centers = lloyd_euclidean(points, n_micro, 0, seed, id_col, column)
    n, sums, far = add_points(points.select(F.col(id_col).alias("doc_id"), F.col(column).cast("array<double>").alias("x")), centers)
    ids = np.flatnonzero(n)
    centers, sums, n, radius = centers[ids], sums[ids], n[ids], np.sqrt(far[ids])
    a, b = np.triu_indices(len(ids), 1)
    gap = np.sqrt(((centers[a] - centers[b]) ** 2).sum(axis=1)) - radius[a] - radius[b]
    links = Links(a, b, -gap, -gap, np.full(len(a), 2))
    groups = group(links, link_by_rank(links, len(ids), k, "first"), len(ids), "first")
    means = np.stack([sums[groups == g].sum(axis=0) / n[groups == g].sum() for g in range(groups.max() + 1)])

    def label(batches):
        for batch in batches:
            x = batch.column("x").flatten().to_numpy().reshape(batch.num_rows, -1)
            best = np.round(-2 * x @ means.T + (means * means).sum(axis=1), 9).argmin(axis=1)
            yield pa.record_batch([batch.column("doc_id"), pa.array(best.astype(np.int64))], names=["doc_id", "cluster_id"])

    return points.select(F.col(id_col).cast("long").alias("doc_id"), F.col(column).cast("array<double>").alias("x")).mapInArrow(label, "doc_id long, cluster_id long")
