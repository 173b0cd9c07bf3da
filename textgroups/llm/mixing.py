"""Mixing sources to target weights by a low-discrepancy schedule (operator 1).

Slots of the mix are the points frac((k + 1/2) * golden ratio); each point falls into one source's share of the
cumulative weights, and the slots of a source are ranked in schedule order. A source's documents, shuffled by a hash,
form a line of words; the line repeated is cut into blocks of equally many words, and the slot of rank r takes block r.
The last block of a source is cut at its target. Points that fall to a source beyond its target are not used, and what
the points have not reached is appended behind them, so each source gives its target rounded down, to the word.

Weights 5, 2, 1 repeat over the sources in code point order, null last; targets share 150 % of all words, stop at twice
their source's words, and the excess goes to the others by weight. Defined results: a null text has no words and gives
nothing; repeated rows are documents of their own; null ids and null sources are ordinary values; a source without
words has target 0; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from textgroups.llm.words import WORD
from textgroups.plans.skew import running_totals
from textgroups.plans.storage import materialise

WEIGHTS = (5, 2, 1)
FACTOR = 1.5
CAP = 2
BLOCK_WORDS = 1024
GOLDEN = 0.6180339887498949
#: Cells that the unit interval is cut into for the join of points and sources.
CELLS = 4096
#: Documents of one source and bucket, about: the most that one task orders at once.
BUCKET_ROWS = 2_000


def word_count(text: Column) -> Column:
    """Words of a text, null: 0."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame) -> DataFrame:
    """(source, weight, source_size, target) of ``sizes(source, size)``.

    Sources fill in the order of cap / weight; the first level at which the next source stays below its cap holds for
    all that are not full. The windows run over one row per source.
    """
    totals = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    weights = F.array(*[F.lit(w) for w in WEIGHTS])
    weighed = totals.withColumn("weight", F.element_at(weights, ((F.row_number().over(by_name) - 1) % len(WEIGHTS) + 1).cast("int")).cast("long"))
    ratio = F.col("source_size") / F.col("weight")
    by_ratio = Window.orderBy(ratio.asc(), F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy()
    left = F.sum("source_size").over(every) * FACTOR - F.coalesce(F.sum("source_size").over(by_ratio), F.lit(0)) * CAP
    open_weight = F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(by_ratio), F.lit(0))
    level = weighed.withColumn("level", left / open_weight).withColumn("full", F.col("level") * F.col("weight") > F.col("source_size") * CAP)
    water = F.min(F.when(~F.col("full"), F.struct(ratio, F.col("level")))).over(every)["level"]
    return level.select("source", "weight", "source_size", F.least(F.coalesce(water * F.col("weight"), F.col("source_size") * 2.0), F.col("source_size") * float(CAP)).alias("target"))


def lines(sizes: DataFrame) -> DataFrame:
    """``sizes`` with ``place`` and ``start``: rank of the document and words before it on its source's shuffled line."""
    rows = sizes.count()
    digits = 1
    while 16**digits * BUCKET_ROWS < rows and digits < 7:
        digits += 1
    tagged = sizes.withColumn("_h", F.md5(F.concat_ws("#", F.lit("mix"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))).withColumn("_b", F.substring("_h", 1, digits)).withColumn("_src", source_key(F.col("source")))
    placed = running_totals(tagged, ["_src"], "_b", [F.col("_h"), F.col("doc_id"), F.col("size")], F.col("size"), "place", "start", F.substring("_b", 1, digits // 2))
    return placed.drop("_h", "_b")


def source_key(source: Column) -> Column:
    """A key that is never null: null and the text 'null' stay apart."""
    return F.coalesce(F.concat(F.lit("="), source), F.lit("-"))


def schedule(targets: DataFrame, block: int = BLOCK_WORDS) -> DataFrame:
    """The mix in order: (slot, _src, rank, words). Rank r of a source stands for the block r of its repeated line."""
    spark = targets.sparkSession
    shares = Window.orderBy(F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0)
    ends = targets.select(source_key(F.col("source")).alias("_src"), F.floor("target").cast("long").alias("words"), F.sum("target").over(shares).alias("upto"), "target", F.sum("target").over(Window.partitionBy()).alias("all")).filter("words > 0")
    ends = ends.select("_src", "words", ((F.col("upto") - F.col("target")) / F.col("all")).alias("low"), F.when(F.col("upto") >= F.col("all"), F.lit(2.0)).otherwise(F.col("upto") / F.col("all")).alias("high"))
    ends = ends.withColumn("blocks", F.ceil(F.col("words") / block).cast("long"))
    ends = materialise(ends, "shares")
    slots = ends.agg(F.sum("blocks")).first()[0] or 0
    points = spark.range(slots).select(F.col("id").alias("k"), ((F.col("id") + 0.5) * GOLDEN).alias("x")).select("k", (F.col("x") - F.floor("x")).alias("u"))
    points = points.withColumn("cell", F.floor(F.col("u") * CELLS))
    cells = ends.withColumn("cell", F.explode(F.sequence(F.floor(F.col("low") * CELLS), F.least(F.floor(F.col("high") * CELLS), F.lit(CELLS - 1)))))
    hit = points.join(cells, "cell").filter("u >= low and u < high").select("k", "_src", "blocks", "words", F.floor(F.col("k") / BUCKET_ROWS).alias("_b"))
    ranked = running_totals(hit, ["_src"], "_b", [F.col("k")], F.lit(0), "rank", "_zero", F.floor(F.col("_b") / BUCKET_ROWS)).filter("rank < blocks").select(F.col("k").alias("slot"), "_src", "rank", "words")
    ranked = materialise(ranked, "ranked")
    got = ranked.groupBy("_src").agg(F.count(F.lit(1)).alias("got"))
    short = ends.join(got, "_src", "left").withColumn("got", F.coalesce("got", F.lit(0))).filter("got < blocks")
    # The points miss a source's share by a few blocks at most (their discrepancy), so few are numbered here.
    tail = short.select("_src", F.explode(F.sequence("got", F.col("blocks") - 1)).alias("rank"), "words")
    tail = tail.select((F.row_number().over(Window.orderBy("rank", "_src")) - 1 + slots).cast("long").alias("slot"), "_src", "rank", "words")
    every = ranked.unionByName(tail)
    return every.select("slot", "_src", "rank", F.least(F.lit(block).cast("long"), F.col("words") - F.col("rank") * block).alias("words"))


def mix_blocks(docs: DataFrame, block: int = BLOCK_WORDS) -> DataFrame:
    """Pieces of documents with the slot that takes them.

    (doc_id, source, size, source_size, target, place, slot, rank, pass, first, words): ``words`` words of the document
    from its word ``first`` on stand in this slot; a document that no slot takes has one row with ``words`` 0. Lines and
    slots are written on the way: in one plan the driver holds every exchange of both, twice over, at once.
    """
    sizes = materialise(docs.select(F.col("doc_id").cast("long"), F.col("source").cast("string"), word_count(F.col("text")).alias("size")), "sizes")
    targets = materialise(source_targets(sizes), "targets")
    keyed = targets.withColumn("_src", source_key(F.col("source"))).drop("source")
    placed = materialise(lines(sizes), "lines").join(F.broadcast(keyed) if targets.count() <= 100_000 else keyed, "_src")
    repeats = placed.withColumn("pass", F.explode(F.sequence(F.lit(0), F.lit(CAP - 1))))
    begin = F.col("start") + F.col("pass") * F.col("source_size")
    upto = F.least(begin + F.col("size"), F.floor("target"))
    repeats = repeats.withColumn("begin", begin).withColumn("upto", upto).withColumn("rank", F.when(F.col("begin") < F.col("upto"), F.sequence(F.floor(F.col("begin") / block), F.floor((F.col("upto") - 1) / block))))
    pieces = repeats.filter("rank is not null").withColumn("rank", F.explode("rank"))
    wanted = materialise(schedule(targets, block).withColumnRenamed("words", "slot_words"), "slots")
    taken = pieces.join(wanted, ["_src", "rank"], "left")
    from_word = F.greatest(F.col("begin"), F.col("rank") * block)
    to_word = F.least(F.col("upto"), F.col("rank") * block + F.coalesce("slot_words", F.lit(0)))
    columns = ["doc_id", "source", "size", "source_size", "target", "place", "slot", "rank", "pass"]
    some = taken.select(*columns, (from_word - F.col("begin")).alias("first"), F.greatest(to_word - from_word, F.lit(0)).alias("words"))
    none = repeats.filter("rank is null and pass = 0").select(*[F.lit(None).cast("long").alias(c) if c in ("slot", "rank") else F.col(c) for c in columns], F.lit(0).cast("long").alias("first"), F.lit(0).cast("long").alias("words"))
    return some.unionByName(none)


def mixture(docs: DataFrame, block: int = BLOCK_WORDS) -> DataFrame:
    """One row per document: doc_id, size, source_size, target, taken (words the mix takes), source, first_slot (the first
    slot that takes of it, null: none)."""
    pieces = mix_blocks(docs, block)
    keys = ["doc_id", "source", "place", "size", "source_size", "target"]
    taken = pieces.groupBy(*keys).agg(F.sum("words").cast("long").alias("taken"), F.min(F.when(F.col("words") > 0, F.col("slot"))).alias("first_slot"))
    return taken.select("doc_id", "size", "source_size", "target", "taken", "source", "first_slot")


def mixed_documents(docs: DataFrame, block: int = BLOCK_WORDS) -> DataFrame:
    """The documents of the mix as whole texts, each as often as the mix takes it (0, 1 or 2 times, to the nearest).

    Each row comes back with its own columns; a document that the mix cuts counts as taken from half of its words on.
    """
    times = mixture(docs, block).filter("size > 0").select("doc_id", "source", "size", F.floor(F.col("taken") / F.col("size") + 0.5).cast("int").alias("times"))
    times = times.groupBy("doc_id", "source", "size").agg(F.sum("times").alias("times"), F.count(F.lit(1)).alias("rows")).filter("times > 0")
    times = materialise(times, "times")
    rows = docs.select(F.struct("*").alias("row"), F.col("doc_id").cast("long").alias("id"), F.col("source").cast("string").alias("src"), word_count(F.col("text")).alias("words"))
    joined = rows.join(times.hint("merge"), rows["id"].eqNullSafe(times["doc_id"]) & rows["src"].eqNullSafe(times["source"]) & (rows["words"] == times["size"]))
    each = F.ceil(F.col("times") / F.col("rows")).cast("int")  # equal rows share what the mix takes of them
    return joined.select("row", F.explode(F.sequence(F.lit(1), each)).alias("copy")).select("row.*")
