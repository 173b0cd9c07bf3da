"""Vectors of documents and points: long and packed form (DM2, DM3, O10-O12)."""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from textgroups.functions.text import UNIT, doc_freq, term_freq, tokens, weigh, words
from textgroups.plans.skew import join_lookup, running_totals
from textgroups.plans.storage import materialise


class Vectors(NamedTuple):
    """Unit vectors in fixed-point numbers, written once and read by every round.

    ``packed(doc_id, idx, val)`` holds all documents, also those without a term; ``terms(term, term_id)`` is None for
    points. ``n`` documents, ``v`` dimensions.
    """

    packed: DataFrame
    terms: DataFrame | None
    n: int
    v: int

    @property
    def postings(self) -> DataFrame:
        """(doc_id, term_id, wq)."""
        return unpack(self.packed)


def pack(postings: DataFrame) -> DataFrame:
    """(doc_id, idx, val), terms in order."""
    pairs = F.array_sort(F.collect_list(F.struct("term_id", "wq")))
    return postings.groupBy("doc_id").agg(pairs.alias("p")).select("doc_id", F.transform("p", lambda x: x["term_id"].cast("int")).alias("idx"), F.transform("p", lambda x: x["wq"].cast("long")).alias("val"))


def unpack(packed: DataFrame) -> DataFrame:
    return packed.select("doc_id", F.explode(F.arrays_zip("idx", "val")).alias("p")).select("doc_id", F.col("p.idx").alias("term_id"), F.col("p.val").alias("wq"))


#: Terms go to the tasks by broadcast up to so many (about 100 bytes each), beyond it postings are shuffled by term.
BROADCAST_TERMS = 1_000_000


def _by_broadcast(docs: DataFrame, terms: DataFrame) -> DataFrame:
    """(doc_id, p) of all documents. The texts are dealt by id once; words are met with the terms, counted and gathered
    where their text lies."""
    dealt = docs.repartition("doc_id").select("doc_id", F.explode_outer(words(F.col("text"))).alias("term"))
    counted = dealt.join(F.broadcast(terms), "term", "left").groupBy("doc_id", "term_id", "df").agg(F.count(F.lit(1)).alias("tf"))
    return counted.groupBy("doc_id").agg(F.collect_list(F.when(F.col("term_id").isNotNull(), F.struct("term_id", "tf", "df"))).alias("p"))


def _by_shuffle(docs: DataFrame, terms: DataFrame) -> DataFrame:
    """The same through a join on the term; terms of very many documents are sent to all tasks instead."""
    tf = materialise(term_freq(tokens(docs)), "tf")
    found = join_lookup(tf, terms, "term", "df").groupBy("doc_id").agg(F.collect_list(F.struct("term_id", "tf", "df")).alias("p"))
    every = docs.select("doc_id").distinct().join(found.hint("merge"), "doc_id", "left")
    return every.select("doc_id", F.coalesce("p", F.array().cast(found.schema["p"].dataType)).alias("p"))


def text_vectors(docs: DataFrame, min_df: int = 2, max_df: int | None = None, id_col: str = "doc_id", **weights) -> Vectors:
    """tf-idf vectors of ``docs(id, text)``, one row an id.

    Term ids are ranks in the order of the terms' md5, counted bucket by bucket, so no task sees the whole vocabulary.
    A term's documents are counted within the rows first; the postings themselves are shuffled only where the terms are
    too many to be sent to all tasks.
    """
    docs = docs.select(F.col(id_col).alias("doc_id"), "text")
    once = docs.select("doc_id", F.explode(F.array_distinct(words(F.col("text")))).alias("term"))
    df = doc_freq(once, min_df, max_df)
    keyed = df.withColumn("_h", F.md5("term")).withColumn("_b", F.substring("_h", 1, 2)).withColumn("_all", F.lit(0))
    keyed = materialise(keyed, "df")
    terms = running_totals(keyed, ["_all"], "_b", [F.col("_h"), F.col("term")], F.lit(0), "term_id", "_z").select("term", "df", F.col("term_id").cast("int"))
    terms = materialise(terms, "terms")
    n, v = docs.count(), terms.count()
    gathered = _by_broadcast(docs, terms) if v <= BROADCAST_TERMS else _by_shuffle(docs, terms)
    return Vectors(materialise(weigh(gathered, n, **weights), "packed"), terms, n, v)


def point_vectors(points: DataFrame, id_col: str = "vec_id", column: str = "embedding") -> Vectors:
    """Dense points as vectors with all dimensions (DM3)."""
    val = F.transform(F.col(column), lambda x: F.round(x.cast("double") * UNIT).cast("long"))
    packed = points.select(F.col(id_col).cast("long").alias("doc_id"), F.transform(F.sequence(F.lit(0), F.size(column) - 1), lambda i: i.cast("int")).alias("idx"), val.alias("val"))
    packed = materialise(packed, "packed")
    size = packed.agg(F.count(F.lit(1)), F.max(F.size("idx"))).first()
    return Vectors(packed, None, size[0], size[1] or 0)


def cos_sim(a: Column, b: Column) -> Column:
    """Cosine of two dense arrays."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, p: s + p)
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def map_dot(a: Column, b: Column) -> Column:
    """Product of two maps of weights."""
    return F.aggregate(F.map_entries(a), F.lit(0.0), lambda s, e: s + e["value"].cast("double") * F.coalesce(F.try_element_at(b, e["key"]).cast("double"), F.lit(0.0)))


def cos_sparse(a: Column, b: Column) -> Column:
    """Cosine of two maps of weights."""
    return map_dot(a, b) / F.sqrt(map_dot(a, a) * map_dot(b, b))


def as_map(idx: Column, val: Column) -> Column:
    """A packed vector as a map of weights."""
    return F.map_from_arrays(idx, val)


def euclid(a: Column, b: Column) -> Column:
    """Euclidean distance of two dense arrays."""
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda p, q: p.cast("double") - q.cast("double")), F.lit(0.0), lambda s, d: s + d * d))
