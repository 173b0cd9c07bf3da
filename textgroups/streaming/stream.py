"""Documents and events that arrive in streams."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from textgroups.functions.text import UNIT, words
from textgroups.operators.assign import nearest_in_batch, unit


class Frozen:
    """Centres, vocabulary and document frequencies of a fitted model, for documents that come later.

    ``terms(term, df, term_id)`` must be small enough to broadcast (checked against ``most_terms``).
    """

    def __init__(self, terms: DataFrame, centers: np.ndarray, n: int, most_terms: int = 5_000_000):
        if terms.count() > most_terms:
            raise ValueError("the vocabulary is too large to be broadcast")
        self.terms, self.centers, self.n = terms, centers, n


def vectorise(docs: DataFrame, model: Frozen) -> DataFrame:
    """(doc_id, idx, val) of new documents by the frozen vocabulary, inside the row (no shuffle, so streams can use it)."""
    known = model.terms.select("term", "term_id", "df").toArrow().combine_chunks()  # of a checked size
    held = docs.sparkSession.sparkContext.broadcast((known.column("term").combine_chunks(), known.column("term_id").to_numpy(), np.log(model.n / known.column("df").to_numpy())))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        terms, ids, idf = held.value
        for batch in batches:
            found = batch.column("words")
            place = pc.index_in(found.flatten(), value_set=terms)
            owner = np.repeat(np.arange(batch.num_rows), np.diff(found.offsets.to_numpy()))
            real = place.is_valid().to_numpy(zero_copy_only=False)
            at = place.fill_null(0).to_numpy(zero_copy_only=False)
            real &= idf[at] > 0
            cell, tf = np.unique(owner[real] << 32 | ids[at[real]].astype(np.int64), return_counts=True)
            weight_of = np.zeros(int(ids.max(initial=-1)) + 1)
            weight_of[ids] = idf
            row, idx = cell >> 32, cell & 0xFFFFFFFF
            w = tf * weight_of[idx]
            length = np.sqrt(np.bincount(row, w * w, batch.num_rows))
            val = np.floor(w / length[row] * UNIT + 0.5).astype(np.int64)
            ends = np.searchsorted(row, np.arange(batch.num_rows + 1)).astype(np.int32)
            yield pa.record_batch([batch.column("doc_id"), pa.ListArray.from_arrays(ends, pa.array(idx.astype(np.int32))), pa.ListArray.from_arrays(ends, pa.array(val))], names=["doc_id", "idx", "val"])

    return docs.select("doc_id", words(F.col("text")).alias("words")).mapInArrow(run, "doc_id long, idx array<int>, val array<long>")


def stream_assign(docs: DataFrame, model: Frozen) -> DataFrame:
    """(doc_id, cluster_id, sim) of arriving documents against frozen centres (O31); works on streams and batches."""
    held = docs.sparkSession.sparkContext.broadcast(model.centers)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            best, dots = nearest_in_batch(batch, held.value)
            yield pa.record_batch([batch.column("doc_id"), pa.array(best[:, 0].astype(np.int64)), pa.array(dots[:, 0] / UNIT / UNIT)], names=["doc_id", "cluster_id", "sim"])

    return vectorise(docs, model).mapInArrow(run, "doc_id long, cluster_id long, sim double")


def stream_cf(labelled: DataFrame, delay: str = "1 hour", size: str = "1 day") -> DataFrame:
    """Counts and sums of similarity per window and cluster of ``labelled(ts, cluster_id, sim)``; rows later than the
    watermark are dropped (O32)."""
    return labelled.withWatermark("ts", delay).groupBy(F.window("ts", size).alias("w"), "cluster_id").agg(F.count(F.lit(1)).alias("n"), F.sum("sim").alias("sum_sim"), F.sum(F.col("sim") * F.col("sim")).alias("ss_sim")).select(F.col("w.start").alias("start"), "cluster_id", "n", "sum_sim", "ss_sim")


def stream_minibatch(docs: DataFrame, model: Frozen, path: str):
    """A writer that moves the centres with every micro-batch (O33): sums of the batch are added to the running sums.

    State of batch i is written to ``path/i`` once; a batch that is run again starts from the state before it.
    """
    spark = docs.sparkSession

    def state(i: int) -> tuple[np.ndarray, np.ndarray]:
        if i < 0:
            return model.centers.copy(), np.ones(model.centers.shape[1])
        got = spark.read.parquet(f"{path}/{i}").toPandas()
        sums, n = np.zeros_like(model.centers), np.zeros(model.centers.shape[1])
        body = got[got["term_id"] >= 0]
        sums[body["term_id"], body["center_id"]] = body["s"]
        head = got[got["term_id"] < 0]
        n[head["center_id"]] = head["s"]
        return sums, n

    def fold(batch: DataFrame, i: int) -> None:
        from textgroups.operators.assign import totals

        sums, n = state(i - 1)
        got = totals(vectorise(batch, model), unit(sums))
        sums, n = sums + got.sums, n + got.count
        t, c = np.nonzero(sums)
        table = pa.table({"center_id": np.concatenate([c, np.arange(len(n))]), "term_id": np.concatenate([t, np.full(len(n), -1)]), "s": np.concatenate([sums[t, c], n])})
        spark.createDataFrame(table).write.mode("overwrite").parquet(f"{path}/{i}")

    return docs.writeStream.foreachBatch(fold)


def dedupe_stream(rows: DataFrame, keys: list[str], delay: str = "1 hour") -> DataFrame:
    """First row of each key within the watermark."""
    return rows.withWatermark("ts", delay).dropDuplicatesWithinWatermark(keys)


def cf_state(labelled: DataFrame) -> DataFrame:
    """Running (count, sum, square sum) per cluster as custom state, one row per cluster and update."""

    def update(key, batches, state):
        n, s, ss = state.get if state.exists else (0, 0.0, 0.0)
        for pdf in batches:
            n, s, ss = n + len(pdf), s + float(pdf["sim"].sum()), ss + float((pdf["sim"] ** 2).sum())
        state.update((n, s, ss))
        yield pd.DataFrame({"cluster_id": [key[0]], "n": [n], "sum_sim": [s], "ss_sim": [ss]})

    out, kept = "cluster_id long, n long, sum_sim double, ss_sim double", "n long, s double, ss double"
    return labelled.groupBy("cluster_id").applyInPandasWithState(update, out, kept, "update", "NoTimeout")


def interval_stream_join(events: DataFrame, labels: DataFrame, seconds: int = 3600) -> DataFrame:
    """Events joined with labels of the same user that came up to ``seconds`` before; both sides have watermarks."""
    a = events.withWatermark("ts", "1 hour").alias("e")
    b = labels.withWatermark("label_ts", "1 hour").alias("l")
    return a.join(b, F.expr(f"e.user_id = l.label_user and l.label_ts <= e.ts and e.ts <= l.label_ts + interval {seconds} seconds"))


def read_documents(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    """Stream of Parquet files of a directory."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


__all__ = ["Frozen", "vectorise", "stream_assign", "stream_cf", "stream_minibatch", "dedupe_stream", "cf_state", "interval_stream_join", "read_documents"]
