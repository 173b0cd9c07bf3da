"""Token counts through a digest cache (operator 6).

A cache row is (tokenizer digest, content digest, tokens). Documents are reduced to content digests, met with the cache
by a join, and only the first row of each distinct miss is encoded; its count is appended, so a later run over the same
content with the same tokenizer encodes nothing. Defined results: a null text is the empty text (0 tokens); repeated
rows share one count; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import public_tokenizers
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textgroups.llm.words import as_text, slices
from textgroups.plans.skew import join_lookup
from textgroups.plans.storage import materialise, workspace

MODEL = "piece_bpe_32k.model"
LIMIT = 4096
#: The keys of what needs encoding, or of the rest, are broadcast up to so many bytes; else both sides are shuffled.
BROADCAST_BYTES = 64 << 20
ROW_BYTES = 96


@lru_cache(maxsize=4)
def _counter(path: str):
    if path.endswith(".model"):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        return lambda texts: [len(x) for x in model.encode(texts, num_threads=1)]
    from tokenizers import Tokenizer

    encoder = Tokenizer.from_file(path)
    encoder.no_truncation()
    encoder.no_padding()
    return lambda texts: [len(encoder.encode(t, add_special_tokens=False).ids) for t in texts]


def tokenizer_digest(path: str) -> str:
    """Digest of the tokenizer file: another file is another tokenizer version."""
    with open(path, "rb") as f:
        return hashlib.sha256(f.read()).hexdigest()


def _content(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.withColumn("_d", F.unhex(F.sha2(text, 256))).withColumn("_bytes", F.octet_length(text).cast("long"))


def encode_counts(rows: DataFrame, path: str) -> DataFrame:
    """(digest, n_tokens) of ``rows(_d, text)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = _counter(path)
        for batch in batches:
            for part in slices(batch, "text"):
                counts = np.fromiter(count(as_text(part.column("text")).to_pylist()), np.int64, part.num_rows)
                yield pa.record_batch([part.column("_d"), pa.array(counts)], names=["digest", "n_tokens"])

    return rows.select("_d", "text").mapInArrow(run, "digest binary, n_tokens long")


class TokenCache:
    """Stored counts: Parquet rows (tokenizer, digest, n_tokens) below ``path``, in a folder of each tokenizer digest."""

    def __init__(self, spark, path: str, tokenizer: str):
        self.spark, self.path = spark, f"{path}/tokenizer={tokenizer}"

    def read(self) -> DataFrame:
        where = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
        known = where.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(where)
        schema = "digest binary, n_tokens long"
        return self.spark.read.schema(schema).parquet(self.path) if known else self.spark.createDataFrame([], schema)

    def append(self, counts: DataFrame) -> None:
        counts.write.mode("append").parquet(self.path)


def count_tokens(docs: DataFrame, tokenizer: str | None = None, cache_path: str | None = None, limit: int = LIMIT) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_tokens, over_limit. ``cache_path`` keeps the counts between runs."""
    spark = docs.sparkSession
    path = tokenizer or public_tokenizers.path(MODEL)
    cache = TokenCache(spark, cache_path or workspace(spark, "token-cache"), tokenizer_digest(path))
    docs = _content(docs.select(F.col("doc_id").cast("long"), "text"))
    rows = materialise(docs.select("doc_id", "_d", "_bytes"), "content")
    first = rows.groupBy("_d").agg(F.min("doc_id").alias("_id"), F.count(F.lit(1)).alias("n"))
    known = cache.read()
    misses = materialise(first.join(known, first["_d"] == known["digest"], "left_anti"), "misses")
    same = (docs["_d"] == misses["_d"]) & docs["doc_id"].eqNullSafe(misses["_id"])
    every, missing = rows.count(), misses.count()
    if (every - missing) * ROW_BYTES <= BROADCAST_BYTES:
        rest = materialise(rows.join(misses, (rows["_d"] == misses["_d"]) & rows["doc_id"].eqNullSafe(misses["_id"]), "left_anti").select("_d", F.col("doc_id").alias("_id")), "rest")
        todo = docs.join(F.broadcast(rest), (docs["_d"] == rest["_d"]) & docs["doc_id"].eqNullSafe(rest["_id"]), "left_anti")
    elif missing * ROW_BYTES <= BROADCAST_BYTES:
        todo = docs.join(F.broadcast(misses), same, "left_semi")
    else:
        todo = docs.join(misses.hint("merge"), same, "left_semi")
    cache.append(encode_counts(todo, path))
    # A batch that was run again may have stored a count twice; only this batch's digests are looked at.
    counts = cache.read().join(first.select(F.col("_d").alias("digest")), "digest", "left_semi").dropDuplicates(["digest"])
    sized = materialise(first.select(F.col("_d").alias("digest"), "n").join(counts, "digest").withColumnRenamed("digest", "_d"), "counted")
    out = join_lookup(rows, sized, "_d", "n")
    return out.select("doc_id", F.col("_bytes").alias("n_bytes"), "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
