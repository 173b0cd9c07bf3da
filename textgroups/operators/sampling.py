"""Draws of centres, samples and parts in the order of a seeded hash (DM15)."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from textgroups.plans.skew import running_totals

SEED = 42


def order_key(ids: Column, seed: int = SEED) -> Column:
    return F.md5(F.concat_ws(":", F.lit(str(seed)), ids.cast("string")))


def sample_size(n: int, k: int) -> int:
    """Square root of k n, rounded up, not above n (H1)."""
    s = math.isqrt(k * n)
    return min(n, s + (s * s < k * n))


def sample_size_of(n: Column, k: Column) -> Column:
    """``sample_size`` of columns; exact while n k is below 2^52."""
    return F.least(n, F.ceil(F.sqrt(n.cast("double") * k)).cast("long"))


def draw_sample(ids: DataFrame, s: int, seed: int = SEED, method: str = "hash", id_col: str = "doc_id", stratum: str | None = None, n: int | None = None) -> DataFrame:
    """(doc_id, rk): the first ``s`` ids in hash order, rank from 0 (A1, H2; other draws: H2b).

    ``hash``: rows above a threshold that surely holds enough are left out before the sort, if ``n`` is known.
    ``bernoulli``: each id with probability s/n. ``reservoir``: every partition's first s, then the first s of them.
    ``stratified``: the same share of each value of ``stratum``.
    """
    keyed = ids.select(F.col(id_col).alias("doc_id"), order_key(F.col(id_col), seed).alias("h"), *([stratum] if stratum else []))
    if method == "bernoulli":
        cut = f"{int(min(1.0, s / max(1, n or ids.count())) * 0xFFFFFFFF):08x}"
        drawn = keyed.filter(F.substring("h", 1, 8) < cut)
    elif method == "stratified":
        share = s / max(1, n or ids.count())
        by = Window.partitionBy(stratum)
        drawn = keyed.withColumn("i", F.row_number().over(by.orderBy("h"))).withColumn("c", F.count(F.lit(1)).over(by)).filter(F.col("i") <= F.ceil(F.col("c") * share))
    else:
        if n and method == "hash" and n > 20 * s:
            reach = min(1.0, (s + 8 * math.sqrt(s) + 8) / n)
            likely = keyed.filter(F.substring("h", 1, 8) <= f"{int(reach * 0xFFFFFFFF):08x}")
            keyed = likely if likely.count() >= s else keyed
        drawn = keyed.orderBy("h", "doc_id").limit(s)
    # At most s rows (in expectation for the random draws) are ranked.
    return drawn.select("doc_id", (F.row_number().over(Window.orderBy("h", "doc_id")) - 1).cast("long").alias("rk"))


def pick_centers(ids: DataFrame, m: int, seed: int = SEED, id_col: str = "doc_id", n: int | None = None) -> DataFrame:
    """(center_id, doc_id) of ``m`` random documents (A1)."""
    return draw_sample(ids, m, seed, id_col=id_col, n=n).select(F.col("rk").alias("center_id"), "doc_id")


def everything(ids: DataFrame, seed: int = SEED, id_col: str = "doc_id") -> DataFrame:
    """(doc_id, rk) of all ids in hash order: the draw of a whole collection, ranked bucket by bucket."""
    keyed = ids.select(F.col(id_col).alias("doc_id"), order_key(F.col(id_col), seed).alias("h")).withColumn("b", F.substring("h", 1, 4)).withColumn("_all", F.lit(0))
    ranked = running_totals(keyed, ["_all"], "b", [F.col("h"), F.col("doc_id")], F.lit(0), "rk", "_z", F.substring("b", 1, 2))
    return ranked.select("doc_id", "rk")


def random_parts(sample: DataFrame, parts: int, exact_capacity: bool = True) -> DataFrame:
    """``sample(doc_id, rk)`` with ``part``: parts differ by one row at most (H6), or by hash for very large samples.

    To draw each document's part with a probability proportional to the places that the parts have left is to deal a
    shuffled deck that holds every part's number once for each of its places. ``rk`` is a random order, so dealing the
    numbers in turn by ``rk`` has the same distribution, needs no state from row to row, and repeats by the seed.
    """
    return sample.withColumn("part", F.col("rk") % parts if exact_capacity else F.pmod(F.xxhash64("doc_id"), F.lit(parts)))


def split_sample(ids: DataFrame, sample: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(members of the sample, the others)."""
    return ids.join(sample.select("doc_id"), "doc_id", "left_semi"), ids.join(sample.select("doc_id"), "doc_id", "left_anti")
