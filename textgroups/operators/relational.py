"""Operators around clusterings: profiles, windows, set operations, joins in time."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import NumericType

from textgroups.plans.skew import join_lookup, running_totals
from textgroups.plans.storage import materialise

#: Rows of a group that one task goes through in a moving window.
CHUNK_ROWS = 100_000


def profile(assign: DataFrame, docs: DataFrame) -> DataFrame:
    """Per cluster: size, mean text length, lowest, mean and highest similarity."""
    rows = assign.join(docs.select("doc_id", "n_chars"), "doc_id")
    return rows.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"), F.avg("n_chars").alias("mean_chars"), F.min("sim").alias("min_sim"), F.avg("sim").alias("mean_sim"), F.max("sim").alias("max_sim"))


def cube_profile(rows: DataFrame, *keys: str) -> DataFrame:
    """Counts over all combinations of keys, with the grouping id."""
    return rows.cube(*keys).agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("gid"))


def rollup_profile(rows: DataFrame, *keys: str) -> DataFrame:
    return rows.rollup(*keys).agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("gid"))


def grouping_sets_profile(rows: DataFrame, sets: list[tuple[str, ...]], *keys: str) -> DataFrame:
    return rows.groupingSets([[F.col(c) for c in s] for s in sets], *[F.col(k) for k in keys]).agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("gid"))


def top_per_group(rows: DataFrame, group: str, order: list[Column], n: int, rank: str = "rank") -> DataFrame:
    """The first ``n`` rows of each group."""
    return rows.withColumn(rank, F.row_number().over(Window.partitionBy(group).orderBy(*order))).filter(F.col(rank) <= n)


def best_pair(edges: DataFrame) -> DataFrame:
    """The most similar pair."""
    return edges.orderBy(F.desc("sim"), "a", "b").limit(1)


def merge_labels(fixed: DataFrame, found: DataFrame) -> DataFrame:
    return fixed.unionByName(found)


def moved(before: DataFrame, after: DataFrame) -> DataFrame:
    """Labels of the later round that the earlier one doesn't have."""
    return after.select("doc_id", "cluster_id").exceptAll(before.select("doc_id", "cluster_id"))


def stable(before: DataFrame, after: DataFrame) -> DataFrame:
    return after.select("doc_id", "cluster_id").intersect(before.select("doc_id", "cluster_id"))


def band_join(left: DataFrame, right: DataFrame, on: str, other: str, width: float) -> DataFrame:
    """Pairs with ``|left.on - right.other| <= width`` (O26): an equi-join on buckets of the width, then the condition."""
    a = left.withColumn("_b", F.floor(F.col(on) / width))
    b = right.withColumn("_b", F.explode(F.array(*[F.floor(F.col(other) / width) + i for i in (-1, 0, 1)])))
    return a.join(b, "_b").filter(F.abs(F.col(on) - F.col(other)) <= width).drop("_b")


def interval_join(points: DataFrame, spans: DataFrame, at: str, start: str, end: str, unit_seconds: int = 86400) -> DataFrame:
    """Points inside spans of time, ends included (O26): spans are dealt to the days that they touch."""
    epoch = lambda c: F.floor(F.unix_timestamp(F.col(c).cast("timestamp")) / unit_seconds)
    a = points.withColumn("_d", epoch(at))
    b = spans.withColumn("_d", F.explode(F.sequence(epoch(start), epoch(end))))
    return a.join(b, "_d").filter((F.col(at) >= F.col(start)) & (F.col(at) <= F.col(end))).drop("_d")


def placed(rows: DataFrame, group: str, order: list[Column], bucket: Column, value: Column | None = None, coarse: int = 64) -> DataFrame:
    """``rows`` with ``at`` (rows of the group before it), ``before`` (sum of ``value`` of those) and ``n`` (rows of the
    group) (O23, O24). A group is ordered bucket by bucket; ``bucket`` is a whole number that rises with ``order``."""
    rows = materialise(rows.withColumn("_b", bucket.cast("long")), "rows")
    sizes = rows.groupBy(group).agg(F.count(F.lit(1)).alias("n"))
    ranked = running_totals(rows, [group], "_b", order, value if value is not None else F.lit(0), "at", "before", F.floor(F.col("_b") / coarse))
    return join_lookup(materialise(ranked.drop("_b"), "placed"), materialise(sizes, "sizes"), group, "n")


def tiles(tiles_: int) -> Column:
    """ntile of a ``placed`` row."""
    size, more = F.floor(F.col("n") / tiles_), F.col("n") % tiles_
    large = more * (size + 1)
    return (F.when(F.col("at") < large, F.floor(F.col("at") / (size + 1))).otherwise(more + F.floor((F.col("at") - large) / F.greatest(size, F.lit(1)))) + 1).cast("int")


def group_quantiles(rows: DataFrame, group: str, value: str, bucket: Column, shares: dict[str, float]) -> DataFrame:
    """(group, one column a share): exact quantiles with linear interpolation, no group in one task."""
    ranked = placed(rows.select(group, value), group, [F.col(value)], bucket)
    out = []
    for name, share in shares.items():
        place = (F.col("n") - 1) * share
        weight = F.when(F.col("at") == F.floor(place), 1 - (place - F.floor(place))).otherwise(place - F.floor(place))
        out.append(F.sum(F.when((F.col("at") == F.floor(place)) | ((F.col("at") == F.floor(place) + 1) & (place > F.floor(place))), F.col(value) * weight)).alias(name))
    return ranked.groupBy(group).agg(*out)


def moving_mean(rows: DataFrame, by: str, order: list[Column], value: str, width: int, bucket: Column) -> DataFrame:
    """``rows`` with ``moving``: mean of ``value`` over a row and the ``width`` - 1 rows before it in its group.

    Every bucket also gets the last ``width`` - 1 rows before it, by their places, so no group is in one task.
    """
    ranked = placed(rows, by, order, bucket)
    cut = ranked.withColumn("_c", F.floor(F.col("at") / CHUNK_ROWS)).withColumn("_own", F.lit(True))
    tail = cut.filter(F.col("at") % CHUNK_ROWS >= CHUNK_ROWS - width + 1).withColumn("_c", F.col("_c") + 1).withColumn("_own", F.lit(False))
    w = Window.partitionBy(by, "_c").orderBy("at").rowsBetween(1 - width, 0)
    return cut.unionByName(tail).withColumn("moving", F.avg(value).over(w)).filter("_own").drop("_c", "_own", "at", "before", "n")


def asof_join(left: DataFrame, right: DataFrame, at: str, by: list[str], values: list[str], span: str | float = "day") -> DataFrame:
    """Each left row with the latest right row of its group not after it (O26); a right row at the same time counts.

    Both sides go in one stream per group and ``span``, which gives the last value seen within the span; a row that has
    seen none takes the last one of the spans before. The largest task is a span of a group. ``span``: a unit of time, or
    a width where ``at`` is a number (a unit of time then stands for 1000).
    """
    number = isinstance(left.schema[at].dataType, NumericType)
    width = span if not isinstance(span, str) else 1000
    spanned = F.floor(F.col(at) / width) if number else F.date_trunc(str(span), at)
    keep = [c for c in left.columns if c not in (*by, at)]
    last = right.groupBy(*by, spanned.alias("_s")).agg(F.max_by(F.struct(*values), F.col(at)).alias("_l"))
    a = left.select(*by, at, *keep, *[F.lit(None).cast(right.schema[v].dataType).alias(v) for v in values], F.lit(1).alias("_side"))
    b = right.select(*by, at, *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in keep], *values, F.lit(0).alias("_side"))
    w = Window.partitionBy(*by, "_s").orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn("_s", spanned)
    seen = both.withColumn("_v", F.last(F.when(F.col("_side") == 0, F.struct(*values)), ignorenulls=True).over(w)).filter("_side = 1").drop("_side", *values)
    # One row a group and span: the last value of the spans before each one.
    spans = left.select(*by, spanned.alias("_s")).distinct().join(last, [*by, "_s"], "full")
    earlier = Window.partitionBy(*by).orderBy("_s").rowsBetween(Window.unboundedPreceding, -1)
    before = spans.select(*by, "_s", F.last("_l", ignorenulls=True).over(earlier).alias("_e"))
    joined = seen.join(before, [*by, "_s"], "left").withColumn("_v", F.coalesce("_v", "_e"))
    return joined.select(*by, at, *keep, *[F.col("_v")[v].alias(v) for v in values])


def exact_copies(docs: DataFrame) -> DataFrame:
    """(h, n): texts that occur more than once."""
    return docs.groupBy(F.md5("text").alias("h")).agg(F.count(F.lit(1)).alias("n")).filter("n > 1")


def behaviour_vectors(orders: DataFrame, lineitem: DataFrame, part: DataFrame) -> DataFrame:
    """(o_custkey, p_type, qty): what each customer buys."""
    rows = lineitem.select("l_orderkey", "l_partkey", "l_quantity").join(orders.select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return rows.join(part.select("p_partkey", "p_type"), F.col("l_partkey") == F.col("p_partkey")).groupBy("o_custkey", "p_type").agg(F.sum("l_quantity").alias("qty"))


def by_region(rows: DataFrame, customer: DataFrame, nation: DataFrame, region: DataFrame, key: str = "o_custkey") -> DataFrame:
    """Rows of customers with their region (O29); nations and regions are fixed small tables."""
    star = customer.select("c_custkey", "c_nationkey").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.join(star.select("c_custkey", "r_name"), F.col(key) == F.col("c_custkey")).drop("c_custkey")


def event_windows(events: DataFrame, kind: str = "tumbling", size: str = "1 day", slide: str = "6 hours", gap: str = "30 minutes") -> DataFrame:
    """Counts and sums over windows of time (O30). Sessions are per user."""
    ts = F.col("ts").cast("timestamp")
    if kind == "session":
        w, keys = F.session_window(ts, gap), ["user_id"]
    else:
        w, keys = (F.window(ts, size) if kind == "tumbling" else F.window(ts, size, slide)), ["event_type"]
    return events.groupBy(w.alias("w"), *keys).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *keys, "n", "total")


def pricing(lineitem: DataFrame) -> DataFrame:
    """Totals by return flag and status."""
    net = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    return lineitem.groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("qty"), F.sum(net).alias("net"), F.count(F.lit(1)).alias("n"))
