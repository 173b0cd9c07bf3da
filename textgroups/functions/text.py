"""Text to weighted term vectors (DM2, O5-O9). Weights are fixed-point numbers, so sums don't depend on their order."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Fixed-point unit of weights.
UNIT = 1 << 20
SEPARATOR = r"[^\p{L}\p{N}]+"


def words(text: Column, pattern: str = SEPARATOR, lower: bool = True) -> Column:
    """The words of a text as an array; null has none."""
    text = F.coalesce(text, F.lit(""))
    return F.filter(F.split(F.lower(text) if lower else text, pattern), lambda t: t != "")


def tokens(docs: DataFrame, pattern: str = SEPARATOR, lower: bool = True, stop: DataFrame | None = None, ngram: int = 1, id_col: str = "doc_id") -> DataFrame:
    """(doc_id, pos, term) (O5); ``stop(term)`` (a small list) is left out before n-grams are built."""
    out = docs.select(F.col(id_col).alias("doc_id"), F.posexplode(words(F.col("text"), pattern, lower)).alias("pos", "term"))
    if stop is not None:
        out = out.join(F.broadcast(stop), "term", "left_anti")
    if ngram > 1:
        after = Window.partitionBy("doc_id").orderBy("pos")
        parts = [F.col("term"), *[F.lead("term", i).over(after) for i in range(1, ngram)]]
        out = out.withColumn("_last", parts[-1]).select("doc_id", "pos", F.concat_ws(" ", *parts).alias("term"), "_last").filter("_last is not null")
    return out.select("doc_id", "pos", "term")


def term_freq(toks: DataFrame) -> DataFrame:
    """(doc_id, term, tf)."""
    return toks.groupBy("doc_id", "term").agg(F.count(F.lit(1)).alias("tf"))


def doc_freq(tf: DataFrame, min_df: int = 2, max_df: int | None = None, max_terms: int | None = None) -> DataFrame:
    """(term, df) within a band of document frequencies."""
    df = tf.groupBy("term").agg(F.count(F.lit(1)).alias("df")).filter(F.col("df") >= min_df)
    df = df.filter(F.col("df") <= max_df) if max_df else df
    return df.orderBy(F.desc("df"), "term").limit(max_terms) if max_terms else df


def _tf(tf: Column, mode: str, most: Column | None) -> Column:
    return {"raw": tf, "log1p": F.log1p(tf), "binary": F.lit(1.0), "augmented": 0.5 + 0.5 * tf / (most if most is not None else tf)}[mode]


def _idf(df: Column, n: int, mode: str) -> Column:
    return {"plain": F.log(F.lit(float(n)) / df), "smooth": F.log((1.0 + n) / (1.0 + df)) + 1, "none": F.lit(1.0)}[mode]


def weigh(rows: DataFrame, n: int, tf_mode: str = "raw", idf_mode: str = "plain", norm: str = "l2") -> DataFrame:
    """(doc_id, idx, val) of ``rows(doc_id, p)``, p an array of (term_id, tf, df): weights as in ``tfidf``, within the row."""
    most = F.array_max(F.transform("p", lambda x: x["tf"])) if tf_mode == "augmented" else None
    weight = lambda x: _tf(x["tf"], tf_mode, most) * _idf(x["df"], n, idf_mode)
    weighed = rows.select("doc_id", F.filter(F.transform(F.array_sort("p"), lambda x: F.struct(x["term_id"].cast("int").alias("t"), weight(x).alias("w"))), lambda x: x["w"] > 0).alias("p"))
    length = F.lit(1.0) if norm == "none" else F.sqrt(F.aggregate("p", F.lit(0.0), lambda s, x: s + x["w"] * x["w"]))
    # The length is a lambda's argument, so it is worked out once a row and not once a term.
    val = F.transform(F.array(length), lambda l: F.transform("p", lambda x: F.round(x["w"] / l * UNIT).cast("long")))[0]  # noqa: E741
    return weighed.select("doc_id", F.transform("p", lambda x: x["t"]).alias("idx"), val.alias("val"))


def tfidf(tf: DataFrame, df: DataFrame, n: int, tf_mode: str = "raw", idf_mode: str = "plain", norm: str = "l2") -> DataFrame:
    """(doc_id, term, tf, w, wq) (O8): w = tf * ln(n / df), wq = w over the document's length in units of 1/2^20."""
    most = F.max("tf").over(Window.partitionBy("doc_id")) if tf_mode == "augmented" else None
    weighted = tf.join(df, "term").withColumn("w", _tf(F.col("tf"), tf_mode, most) * _idf(F.col("df"), n, idf_mode)).filter("w > 0")
    if norm == "none":
        return weighted.select("doc_id", "term", "tf", "w", F.round(F.col("w") * UNIT).cast("long").alias("wq"))
    length = F.sqrt(F.sum(F.col("w") * F.col("w")).over(Window.partitionBy("doc_id")))
    return weighted.select("doc_id", "term", "tf", "w", F.round(F.col("w") / length * UNIT).cast("long").alias("wq"))


def hash_tf(toks: DataFrame, bits: int = 18) -> DataFrame:
    """(doc_id, term_id, tf): terms as one of 2^bits buckets by their md5, no vocabulary needed."""
    bucket = F.conv(F.substring(F.md5("term"), 1, 15), 16, 10).cast("long") % (1 << bits)
    return toks.select("doc_id", bucket.alias("term_id")).groupBy("doc_id", "term_id").agg(F.count(F.lit(1)).alias("tf"))


def strip_html(html: Column) -> Column:
    """Text of a page: scripts, styles and tags out, the common entities resolved."""
    plain = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    plain = F.regexp_replace(plain, r"(?s)<[^>]*>", " ")
    for entity, c in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&")):
        plain = F.replace(plain, F.lit(entity), F.lit(c))
    return plain


def join_turns(conversations: DataFrame) -> DataFrame:
    """(doc_id, text): the turns of a conversation, in their order, as one text."""
    turns = F.array_sort(F.collect_list(F.struct("turn", "text")))
    return conversations.groupBy(F.col("conv_id").alias("doc_id")).agg(F.array_join(F.transform(turns, lambda t: t["text"]), "\n").alias("text"))
