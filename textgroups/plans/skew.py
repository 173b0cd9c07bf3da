"""Plans that stay even when one key holds a third of all rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: A key is heavy if it holds at least 1/HEAVY_SHARE of all rows, so there are at most HEAVY_SHARE heavy keys.
HEAVY_SHARE = 2000


def join_lookup(rows: DataFrame, lookup: DataFrame, key: str, weight: str) -> DataFrame:
    """Inner join of ``rows`` with ``lookup`` (one row per key; ``weight`` = rows of that key).

    Keys that hold at least 1/HEAVY_SHARE of the rows are joined by broadcast: by their definition there are no more
    than HEAVY_SHARE of them, whatever the size of the data. All others go through an ordinary shuffle join, in which
    no key can hold more than 1/HEAVY_SHARE of the rows. Where all keys are heavy or none is, only that join is planned.
    ``rows`` and ``lookup`` are read twice: pass written tables.
    """
    total, least, most = (x or 0 for x in lookup.agg(F.sum(weight), F.min(weight), F.max(weight)).first())
    if least * HEAVY_SHARE >= total:
        return rows.join(F.broadcast(lookup), key)
    if most * HEAVY_SHARE < total:
        return rows.join(lookup.hint("merge"), key)
    heavy_if = F.col(weight) * HEAVY_SHARE >= F.lit(total)
    heavy, light = lookup.filter(heavy_if), lookup.filter(~heavy_if)
    by_broadcast = rows.join(F.broadcast(heavy), key)
    rest = rows.join(F.broadcast(heavy.select(key)), key, "left_anti")
    return by_broadcast.unionByName(rest.join(light.hint("merge"), key).select(*by_broadcast.columns))


def _before(totals: DataFrame, group: list[str], bucket: str, coarse: Column | None) -> DataFrame:
    """(group, bucket, _n0, _s0): rows and values of the buckets before each one."""
    if coarse is None:
        earlier = Window.partitionBy(*group).orderBy(bucket).rowsBetween(Window.unboundedPreceding, -1)
        return totals.select(*group, bucket, F.coalesce(F.sum("_n").over(earlier), F.lit(0)).alias("_n0"), F.coalesce(F.sum("_s").over(earlier), F.lit(0)).alias("_s0"))
    totals = totals.withColumn("_k", coarse)
    above = _before(totals.groupBy(*group, "_k").agg(F.sum("_n").alias("_n"), F.sum("_s").alias("_s")), group, "_k", None)
    inside = _before(totals, [*group, "_k"], bucket, None).withColumnsRenamed({"_n0": "_n1", "_s0": "_s1"})
    return inside.join(above, [*group, "_k"]).select(*group, bucket, (F.col("_n0") + F.col("_n1")).alias("_n0"), (F.col("_s0") + F.col("_s1")).alias("_s0"))


def running_totals(rows: DataFrame, group: list[str], bucket: str, order: list[Column], value: Column, position: str, before: str, coarse: Column | None = None) -> DataFrame:
    """Running position and running sum within each group, without bringing a group to one task.

    ``bucket`` must rise with ``order``. A row gets ``position`` (rows of its group before it) and ``before`` (sum of
    ``value`` of those rows). Totals of each (group, bucket) are added up first, then rows are ordered within their
    bucket only, so the largest task is a bucket and not a group. Where a group may have many buckets, ``coarse``, which
    must rise with the bucket, parts them in the same way, so that no task orders them all. Groups and buckets must be
    free of nulls.
    """
    rows = rows.withColumn("_v", value)
    totals = rows.groupBy(*group, bucket).agg(F.count(F.lit(1)).alias("_n"), F.sum("_v").alias("_s"))
    offsets = _before(totals, group, bucket, coarse)
    inside = Window.partitionBy(*group, bucket).orderBy(*order)
    upto = inside.rowsBetween(Window.unboundedPreceding, -1)
    local = rows.select("*", (F.row_number().over(inside) - 1).cast("long").alias("_i"), F.coalesce(F.sum("_v").over(upto), F.lit(0)).alias("_c"))
    joined = local.join(offsets, [*group, bucket])
    return joined.select(*[c for c in rows.columns if c != "_v"], (F.col("_n0") + F.col("_i")).alias(position), (F.col("_s0") + F.col("_c")).alias(before))
