"""Near copies by shared word shingles (the near-dedup stage of the pipeline, on the fuzzy keys of operator 10).

Two texts are linked if their sets of 5-word shingles have a Jaccard similarity of 0.8 or more. A set's SimHash
fingerprint has TABLES * SEGMENTS segments of 23 bits; SEGMENTS segments of a table are decoded together to the PROBES
most likely combinations of Golay codewords, each of which is a key of 12 * SEGMENTS bits. Sets that share a key are
candidates, and every link is verified on the whole sets. Measured on random sets, a pair at exactly 0.8 shares a key with
a chance of 0.95, at 0.85 of 0.99, from 0.9 on nearly always. Two unrelated sets share one of 36 bits with a chance of
1e-8; for more than 10^9 sets use SEGMENTS = 4, which leaves fewer chance candidates than documents.

The tables are gone through in turns. In a bucket that holds more than one component of the links found so far, the sets
outside its largest component are compared with one set of that, and the links are added; after the first few tables most
copies are in their component and cost nothing any more. What is outside at the end is compared with all sets of its
buckets that are in another component, in blocks of sets: a task holds two blocks and gives the links it finds, so no row
is made for a pair that is none. Pairs within a component need no comparison, so components are those of all verified
candidates. Work is linear in a large group of close copies; where many of its members stand outside the largest
component, the comparison of blocks grows with their number times the group's size.

Defined results: a null or empty text, or one without words, has the empty set, and empty sets are linked to each other;
fewer words than a shingle are one shingle; rows of one set are linked; null ids never become a component id unless all
ids of the component are null; rows that repeat an id and a text count as one; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import lru_cache, reduce

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textgroups.llm.rows import keep_unmarked, sized, text_key
from textgroups.llm.simhash import SEGMENT_BITS, bit_sums, labels, soft_keys
from textgroups.llm.words import as_text, let_go, slices
from textgroups.operators.components import components, spanning_forest
from textgroups.plans.skew import join_lookup
from textgroups.plans.storage import materialise

SHINGLE, SIMILARITY = 5, 0.8
TABLES, SEGMENTS, PROBES, SEED = 20, 3, 6, 43
#: Turns in which the tables are gone through; the first one takes a third of what each other one takes.
TURNS = 4
#: Sets and characters of a block that is compared with another one, about.
BLOCK_ROWS, BLOCK_CHARS = 256, 4 << 20
SLICE_BYTES, _DECODED = 2 << 20, 128


def shingles(text: str, shingle: int = SHINGLE) -> np.ndarray:
    """Sorted 64-bit hashes of the different shingles of a text."""
    words = text.encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    line = b" ".join(words)
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(sizes + 1) - 1
    first, last, k = (ends - sizes).tolist(), ends.tolist(), min(shingle, len(words))
    digest = xxhash.xxh64_intdigest
    return np.unique(np.fromiter((digest(line[a:b], SEED) for a, b in zip(first, last[k - 1 :])), np.uint64, len(words) - k + 1))


def reaches(shared: np.ndarray | int, one: np.ndarray | int, two: np.ndarray | int):
    """Whether sets of ``one`` and ``two`` shingles with ``shared`` common ones reach SIMILARITY."""
    return 10 * shared >= round(10 * SIMILARITY) * (one + two - shared)


def similar(one: np.ndarray, two: np.ndarray) -> bool:
    if min(len(one), len(two)) < SIMILARITY * max(len(one), len(two)):
        return False
    return bool(reaches(len(np.intersect1d(one, two, assume_unique=True)), len(one), len(two)))


def fuzzy_keys(sets: list[np.ndarray], tables: int = TABLES) -> np.ndarray:
    """One row of tables * PROBES keys for each set."""
    bits = tables * SEGMENTS * SEGMENT_BITS
    out = [np.zeros((0, tables * PROBES), np.int64)]
    for i in range(0, len(sets), _DECODED):
        out.append(soft_keys(np.array([bit_sums(s, bits) for s in sets[i : i + _DECODED]]), tables, SEGMENTS, PROBES))
    return np.concatenate(out)


def prints(docs: DataFrame, tables: int = TABLES) -> DataFrame:
    """(id, tx, fp, keys): a hash of the text, a hash of its set, and the set's keys (none for the empty set)."""
    rows = docs.select(F.col("doc_id").cast("long").alias("id"), text_key(F.col("text")).alias("tx"), "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "text", SLICE_BYTES):
                sets = [shingles(t.as_py()) for t in as_text(batch.column("text"))]
                some = [s for s in sets if len(s)]
                fp = np.fromiter((xxhash.xxh64_intdigest(s.tobytes(), SEED) if len(s) else 0 for s in sets), np.uint64, len(sets))
                ends = np.concatenate([[0], np.cumsum([tables * PROBES if len(s) else 0 for s in sets])]).astype(np.int32)
                keys = pa.ListArray.from_arrays(ends, pa.array(fuzzy_keys(some, tables).ravel()))
                yield pa.record_batch([batch.column("id"), batch.column("tx"), pa.array(fp.view(np.int64)), keys], names=["id", "tx", "fp", "keys"])
        let_go()

    return rows.mapInArrow(run, "id long, tx long, fp long, keys array<long>")


def verified(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """Those of the written ``pairs(a, b)`` whose texts reach SIMILARITY; ``texts`` has one row (fp, text) for each set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = lru_cache(64)(shingles)
        for batch in batches:
            good = pa.array([similar(held(x.as_py()), held(y.as_py())) for x, y in zip(as_text(batch.column("text_a")), as_text(batch.column("text_b")))], pa.bool_())
            yield batch.select(["a", "b"]).filter(good)
        let_go()

    for side in ("b", "a"):
        uses = pairs.groupBy(side).agg(F.count(F.lit(1)).alias("n"))
        lookup = texts.select(F.col("fp").alias(side), F.col("text").alias("text_" + side)).join(uses.hint("merge"), side)
        pairs = join_lookup(pairs, materialise(lookup, "texts"), side, "n").drop("n")
        pairs = materialise(pairs, "pairs") if side == "b" else pairs
    return materialise(pairs.select("a", "b", "text_a", "text_b").mapInArrow(run, "a long, b long"), "verified")


def _outside(members: DataFrame, known: DataFrame | None) -> DataFrame:
    """(key, fp, comp, main, lead, n) of the buckets of the written ``members(key, fp)`` that hold more than one component
    of the written ``known(fp, comp)``: ``main`` is the largest one and ``lead`` a set of it."""
    if known is None:
        held = members.select("key", "fp", F.col("fp").alias("comp"))
    else:
        held = materialise(members.select("key", "fp").join(known.hint("merge"), "fp", "left").select("key", "fp", F.coalesce("comp", "fp").alias("comp")), "held")
    parts = held.groupBy("key", "comp").agg(F.count(F.lit(1)).alias("n"), F.min("fp").alias("lead"))
    main = parts.groupBy("key").agg(F.max_by(F.struct("comp", "lead"), F.struct("n", "comp")).alias("main"), F.sum("n").alias("n"), F.count(F.lit(1)).alias("parts"))
    main = main.filter("parts > 1").select("key", "n", F.col("main.comp").alias("main"), F.col("main.lead").alias("lead"))
    return materialise(join_lookup(held, materialise(main, "main"), "key", "n"), "outside")


def _compared(one: list[np.ndarray], two: list[np.ndarray]) -> Iterator[tuple[int, int]]:
    """(i, j) of the sets of two blocks that reach SIMILARITY."""
    size = np.array([len(s) for s in two])
    known, inverse = np.unique(np.concatenate(two), return_inverse=True)
    starts = np.concatenate([[0], np.cumsum(size)[:-1]])
    for i, s in enumerate(one):
        at = np.minimum(np.searchsorted(known, s), len(known) - 1)
        mark = np.zeros(len(known), np.int64)
        mark[at[known[at] == s]] = 1
        shared = np.add.reduceat(mark[inverse], starts)
        yield from ((i, int(j)) for j in np.flatnonzero(reaches(shared, len(s), size)))


def _by_blocks(outside: DataFrame, texts: DataFrame) -> DataFrame:
    """Links (a, b) between the sets outside the largest component of a bucket and all sets of another component there.

    Buckets with the same largest component are one group, so a set that stands in many of them is compared once. The
    strays of a group and all its sets are cut into blocks by a hash; a pair of blocks is a row of numbers until the
    texts are joined to it, and only links leave its task.
    """
    rows = outside.select(F.col("main").alias("group"), "fp", "comp", (F.col("comp") != F.col("main")).alias("stray")).distinct()
    rows = rows.join(texts.select("fp", F.length("text").alias("chars")).hint("merge"), "fp").withColumn("side", F.xxhash64("group", "stray"))
    rows = materialise(rows, "rows")
    parts = rows.groupBy("group", "stray", "side").agg(F.count(F.lit(1)).alias("n"), F.sum("chars").alias("chars"))
    # Two sets alone have met already.
    many = parts.groupBy("group").agg(F.sum("n").alias("sets")).filter("sets > 2").select("group")
    parts = parts.join(many.hint("merge"), "group", "left_semi")
    parts = materialise(parts.withColumn("blocks", F.greatest(F.ceil(F.col("n") / BLOCK_ROWS), F.ceil(F.col("chars") / BLOCK_CHARS)).cast("long")), "parts")
    dealt = join_lookup(rows.select("side", "fp", "comp"), parts.select("side", "n", "blocks"), "side", "n")
    dealt = dealt.select(F.xxhash64("side", F.pmod(F.xxhash64("fp", F.lit(7)), "blocks")).alias("block"), "fp", "comp")
    numbered = parts.select("group", "stray", "side", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("i"))
    numbered = numbered.select("group", "stray", F.xxhash64("side", "i").alias("block"))
    left = numbered.filter("stray").select("group", F.col("block").alias("one"))
    meets = left.join(numbered.select("group", "stray", F.col("block").alias("two")).hint("merge"), "group").filter("not stray or one <= two")
    meets = materialise(meets.select("one", "two", F.xxhash64("one", "two").alias("pair")), "meets")
    ends = meets.select("pair", F.col("one").alias("block"), F.lit(0).alias("end")).unionByName(meets.select("pair", F.col("two").alias("block"), F.lit(1).alias("end")))
    held = materialise(dealt.join(ends.hint("merge"), "block").select("pair", "end", "fp", "comp"), "held")
    uses = held.groupBy("fp").agg(F.count(F.lit(1)).alias("n"))
    lookup = materialise(texts.select("fp", "text").join(uses.hint("merge"), "fp"), "texts")
    full = join_lookup(held, lookup, "fp", "n").select("pair", "end", "fp", "comp", "text")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        held = lru_cache(4 * BLOCK_ROWS)(shingles)
        first, second = (np.flatnonzero(pdf["end"].to_numpy() == e) for e in (0, 1))
        fp, comp, texts = pdf["fp"].to_numpy(), pdf["comp"].to_numpy(), pdf["text"].to_list()
        found = _compared([held(texts[x]) for x in first], [held(texts[x]) for x in second]) if len(first) and len(second) else []
        ends = ((first[i], second[j]) for i, j in found)
        return pd.DataFrame([(min(fp[x], fp[y]), max(fp[x], fp[y])) for x, y in ends if comp[x] != comp[y]], columns=["a", "b"], dtype="int64")

    return materialise(full.groupBy("pair").applyInPandas(run, "a long, b long").distinct(), "block-links")


def _turns(tables: int) -> list[tuple[int, int]]:
    """(first, past the last) table of each turn."""
    cuts = sorted({round(tables * x / (3 * TURNS - 2)) for x in (0, *range(1, 3 * TURNS - 1, 3))})
    return list(zip(cuts, cuts[1:]))


def links(distinct: DataFrame, texts_of: Callable[[DataFrame], DataFrame], tables: int = TABLES) -> DataFrame:
    """Edges (a, b) between different sets of the written ``distinct(fp, keys)``: stars of the components of all links found.
    ``texts_of`` adds their texts to sets (fp). Components are built once a turn, from the last ones and the new links."""
    stars, tried, known, buckets, held = None, None, None, [], None
    for first, last in _turns(tables):
        some = F.slice("keys", F.lit(first * PROBES + 1), F.lit((last - first) * PROBES))
        keys = distinct.select("fp", F.explode(some).alias("key"))
        shared = keys.groupBy("key").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
        members = materialise(join_lookup(keys, materialise(shared, "shared"), "key", "n").select("key", "fp"), "members")
        buckets.append(members)
        found = _outside(members, known).filter("comp <> main")
        pairs = found.select(F.least("fp", "lead").alias("a"), F.greatest("fp", "lead").alias("b")).distinct()
        pairs = materialise(pairs if tried is None else pairs.join(tried.hint("merge"), ["a", "b"], "left_anti"), "pairs")
        if known is not None and pairs.isEmpty():
            continue
        sets = pairs.select(F.col("a").alias("fp")).unionByName(pairs.select(F.col("b").alias("fp"))).distinct()
        fresh = materialise(texts_of(sets if held is None else sets.join(held.select("fp").hint("merge"), "fp", "left_anti")), "texts")
        held = fresh if held is None else held.unionByName(fresh)
        good = verified(pairs, held)
        tried = pairs if tried is None else tried.unionByName(pairs)
        known = components(good if stars is None else stars.unionByName(good)).withColumnRenamed("node", "fp")
        known = materialise(known, "known")
        stars = known.select(F.col("comp").alias("a"), F.col("fp").alias("b"))
    # A key names its table, so the buckets of all turns can be looked at together.
    outside = _outside(reduce(DataFrame.unionByName, buckets), known).select("main", "fp", "comp")
    outside = materialise(outside.distinct(), "outside")
    if outside.isEmpty():
        return stars
    sets = outside.select("fp").distinct().join(held.select("fp").hint("merge"), "fp", "left_anti")
    return stars.unionByName(_by_blocks(outside, held.unionByName(materialise(texts_of(sets), "texts"))))


def keep_one(docs: DataFrame, tables: int = TABLES) -> DataFrame:
    """One document of each group stays, that of the smallest id (of its texts the one with the least hash); rows whose
    id is null stay all."""
    rows = materialise(prints(docs, tables), "prints")
    distinct = rows.groupBy("fp").agg(F.any_value("keys").alias("keys"), F.min("id").alias("least"), F.count(F.lit(1)).alias("n"))
    distinct = materialise(distinct, "distinct")

    def texts_of(sets: DataFrame) -> DataFrame:
        wanted = rows.select("fp", "tx").join(sets.hint("merge"), "fp", "left_semi").groupBy("fp").agg(F.min("tx").alias("tx"))
        found = docs.select(text_key(F.col("text")).alias("tx"), "text").join(sized(materialise(wanted, "wanted")), "tx")
        return found.groupBy("fp").agg(F.any_value("text").alias("text"))

    by_set = labels(distinct.drop("keys"), spanning_forest(links(distinct, texts_of, tables)))
    found = materialise(join_lookup(rows.select("id", "tx", "fp"), by_set, "fp", "n").filter("id is not null"), "found")
    stay = found.filter("id = component_id").groupBy("id", "comp").agg(F.min("tx").alias("tx")).select("id", "tx", F.lit(True).alias("stays"))
    texts = found.groupBy("id", "tx").agg(F.count(F.lit(1)).alias("times")).join(stay.hint("merge"), ["id", "tx"], "left")
    marks = materialise(texts.filter("stays is null or times > 1").select("id", "tx", F.col("stays").isNotNull().alias("stays")), "marks")
    return keep_unmarked(docs, marks)
