"""Language identification by a byte convolutional network (operator 9).

A text's UTF-8 bytes (A-Z lower-cased) are cut into windows of WINDOW bytes, all of them, the last one padded with
zeros. The network embeds bytes, runs filters of several widths over the window, takes each filter's largest value
(ReLU, max pooling) and a softmax over the languages; a text's verdict is the mean of its windows' log-probabilities,
weighted by their bytes. Training is plain numpy on the driver, over a bounded sample of labelled windows: at most
SAMPLE_WINDOWS, spread evenly over the languages and chosen by a hash of the document id. To apply the network, the
convolutions are folded into tables: the response of a filter is the sum of one table row per pair of bytes.

Defined results: a null text, or one without a letter, is ``und`` with score 0; null languages are never learned; with
no labelled row at all every text is ``und``; repeated rows get the same verdict; an empty table gives no rows; extra
columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textgroups.llm.words import as_text, slices

WINDOW = 256
WIDTHS = (2, 3, 4)
FILTERS = 16
EMBEDDING = 8
#: The bound of the training sample.
SAMPLE_WINDOWS = 6000
EPOCHS, BATCH, RATE = 12, 100, 4e-3
UNKNOWN = "und"
_CHUNK = 1024


class Network(NamedTuple):
    languages: list[str]
    embedding: np.ndarray  # 256 x e
    filters: list[np.ndarray]  # width x e x f
    biases: list[np.ndarray]
    weights: np.ndarray  # all filters x languages
    offset: np.ndarray


def _forward(net: Network, x: np.ndarray):
    """Pooled values of windows x (n x WINDOW), with what the gradients need."""
    e = net.embedding[x]
    cols, tops, where = [], [], []
    for w, b in zip(net.filters, net.biases, strict=True):
        k, dim, f = w.shape
        length = x.shape[1] - k + 1
        col = np.lib.stride_tricks.sliding_window_view(e, k, axis=1).transpose(0, 1, 3, 2).reshape(-1, k * dim)
        y = (col @ w.reshape(k * dim, f)).reshape(len(x), length, f)
        at = y.argmax(axis=1)
        top = np.take_along_axis(y, at[:, None, :], axis=1)[:, 0, :] + b
        cols.append(col.reshape(len(x), length, k * dim))
        tops.append(top)
        where.append(at)
    return cols, np.concatenate(tops, axis=1), where


def _log_softmax(z: np.ndarray) -> np.ndarray:
    z = z - z.max(axis=1, keepdims=True)
    return z - np.log(np.exp(z).sum(axis=1, keepdims=True))


def train(windows: np.ndarray, labels: list[str], seed: int = 11, epochs: int = EPOCHS) -> Network:
    """Fit the network to windows (n x WINDOW, uint8) by Adam; the order of the rows does not matter."""
    languages = sorted(set(labels))
    order = np.lexsort((np.array([zlib.crc32(r.tobytes()) for r in windows], np.int64),)) if len(windows) else []
    windows, target = windows[order], np.array([languages.index(x) for x in labels])[order]
    rng = np.random.default_rng(seed)
    params = [rng.normal(0, 0.5, (256, EMBEDDING)).astype(np.float32)]
    for k in WIDTHS:
        params += [rng.normal(0, (k * EMBEDDING) ** -0.5, (k, EMBEDDING, FILTERS)).astype(np.float32), np.zeros(FILTERS, np.float32)]
    params += [rng.normal(0, 0.1, (len(WIDTHS) * FILTERS, len(languages))).astype(np.float32), np.zeros(len(languages), np.float32)]
    first, second = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
    step = 0
    for epoch in range(epochs):
        for part in np.array_split(rng.permutation(len(windows)), max(1, len(windows) // BATCH)):
            net = Network(languages, params[0], params[1:-2:2], params[2:-2:2], params[-2], params[-1])
            x = windows[part]
            cols, top, where = _forward(net, x)
            pooled = np.maximum(top, 0)
            p = np.exp(_log_softmax(pooled @ net.weights + net.offset))
            p[np.arange(len(part)), target[part]] -= 1
            p /= len(part)
            grads = [np.zeros_like(params[0])]
            back = (p @ net.weights.T) * (top > 0)
            for i, (w, at) in enumerate(zip(net.filters, where, strict=True)):
                k = w.shape[0]
                d = back[:, i * FILTERS : (i + 1) * FILTERS]
                rows = np.arange(len(x))[:, None]
                picked = cols[i][rows, at]  # n x f x (k e)
                grads += [np.einsum("nf,nfc->cf", d, picked).reshape(w.shape), d.sum(axis=0)]
                into = d[:, :, None, None] * w.transpose(2, 0, 1)[None]  # n x f x k x e
                used = x[rows[:, :, None], at[:, :, None] + np.arange(k)]
                np.add.at(grads[0], used.ravel(), into.reshape(-1, EMBEDDING))
            grads += [pooled.T @ p, p.sum(axis=0)]
            step += 1
            rate = RATE * (0.5 if epoch > epochs // 2 else 1)
            for j, g in enumerate(grads):
                first[j] = 0.9 * first[j] + 0.1 * g
                second[j] = 0.999 * second[j] + 0.001 * g * g
                params[j] = params[j] - rate * (first[j] / (1 - 0.9**step)) / (np.sqrt(second[j] / (1 - 0.999**step)) + 1e-7)
    return Network(languages, params[0], params[1:-2:2], params[2:-2:2], params[-2], params[-1])


class Reader:
    """The network folded into tables, for whole texts."""

    def __init__(self, net: Network):
        self.net = net
        self.tables = []
        for w in net.filters:
            k = w.shape[0]
            single = [net.embedding @ w[j] for j in range(k)]
            pairs = [(j, (single[j][:, None, :] + single[j + 1][None, :, :]).reshape(65536, -1).astype(np.float32)) for j in range(0, k - 1, 2)]
            self.tables.append((k, pairs, single[k - 1].astype(np.float32) if k % 2 else None))

    def pooled(self, windows: np.ndarray) -> np.ndarray:
        out = np.empty((len(windows), len(self.tables) * FILTERS), np.float32)
        for i in range(0, len(windows), _CHUNK):
            x = windows[i : i + _CHUNK]
            pair = x[:, :-1].astype(np.int32) << 8 | x[:, 1:]
            for t, ((k, pairs, last), bias) in enumerate(zip(self.tables, self.net.biases, strict=True)):
                length = x.shape[1] - k + 1
                y = np.take(pairs[0][1], pair[:, :length], axis=0)
                for j, table in pairs[1:]:
                    y += np.take(table, pair[:, j : j + length], axis=0)
                if last is not None:
                    y += np.take(last, x[:, k - 1 : k - 1 + length], axis=0)
                out[i : i + _CHUNK, t * FILTERS : (t + 1) * FILTERS] = y.max(axis=1) + bias
        return np.maximum(out, 0)

    def read(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(position of the language, probability) of each text."""
        windows, owner, weight = cut(texts)
        scores = _log_softmax(self.pooled(windows) @ self.net.weights + self.net.offset) * weight[:, None]
        total = np.zeros((len(texts), len(self.net.languages)))
        np.add.at(total, owner, scores)
        total /= np.maximum(np.bincount(owner, weight, len(texts)), 1)[:, None]
        p = np.exp(_log_softmax(total))
        return p.argmax(axis=1), p.max(axis=1)


def cut(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(windows, their texts, their bytes) over all bytes of the texts; an empty text has no window."""
    texts = pc.ascii_lower(texts)
    _, ends, data = texts.buffers()
    offsets = np.frombuffer(ends, np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
    octets = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    sizes = np.diff(offsets)
    number = -(-sizes // WINDOW)
    owner = np.repeat(np.arange(len(texts)), number)
    within = np.arange(len(owner)) - np.repeat(np.cumsum(number) - number, number)
    weight = np.minimum(WINDOW, sizes[owner] - within * WINDOW)
    out = np.zeros((len(owner), WINDOW), np.uint8)
    out[np.arange(WINDOW)[None, :] < weight[:, None]] = octets[offsets[0] : offsets[-1]]
    return out, owner, weight.astype(np.float64)


def sample(labelled: DataFrame, bound: int = SAMPLE_WINDOWS) -> tuple[np.ndarray, list[str]]:
    """Windows and languages of at most ``bound`` documents of ``labelled(doc_id, text, lang)``.

    Each language gives an equal share; documents are drawn by a hash of id and text, each gives one window whose
    place is drawn by the same hash, so no part of a text is preferred.
    """
    sizes = {r["lang"]: r["n"] for r in labelled.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "lang").limit(bound).collect()}
    if not sizes:
        return np.zeros((0, WINDOW), np.uint8), []
    share = max(1, bound // len(sizes))
    key = F.xxhash64("doc_id", "text")
    unit = F.pmod(key, F.lit(1 << 30)) / float(1 << 30)
    rate = F.element_at(F.create_map(*[x for lang, n in sizes.items() for x in (F.lit(lang), F.lit(0.9 * share / n))]), F.col("lang"))
    octets = F.encode(F.translate("text", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), "UTF-8")  # as cut() lowers
    start = F.pmod(F.shiftrightunsigned(key, 31), F.greatest(F.octet_length(octets) - WINDOW // 2, F.lit(1))).cast("int")
    drawn = labelled.filter(unit < rate).select("lang", F.substring(octets, start + 1, F.lit(WINDOW)).alias("w")).limit(bound).collect()
    windows = np.zeros((len(drawn), WINDOW), np.uint8)
    for i, r in enumerate(drawn):
        windows[i, : len(r["w"])] = np.frombuffer(bytes(r["w"]), np.uint8)
    return windows, [r["lang"] for r in drawn]


def held_out(doc_id, folds: int = 5, fold: int = 0):
    """True for the rows that are kept from training (null ids count as the text '')."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(folds)) == fold


def predict(docs: DataFrame, net: Network) -> DataFrame:
    """(doc_id, lang_pred, score) of every whole text. The network has a fixed size and goes with the tasks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader = Reader(net) if net.languages else None
        names = np.array([*net.languages, UNKNOWN], object)
        for batch in batches:
            for part in slices(batch, "text"):
                texts = as_text(part.column("text"))
                lettered = pc.match_substring_regex(texts, r"\p{L}").to_numpy(zero_copy_only=False)
                best, p = reader.read(texts) if reader else (np.zeros(len(texts), int), np.zeros(len(texts)))
                best = np.where(lettered & (reader is not None), best, len(net.languages))
                yield pa.record_batch([part.column("doc_id"), pa.array(names[best], pa.string()), pa.array(np.where(lettered, p, 0.0))], names=["doc_id", "lang_pred", "score"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, lang_pred string, score double")


def identify(docs: DataFrame, bound: int = SAMPLE_WINDOWS) -> DataFrame:
    """One row per document: doc_id, held_out, lang_pred, score; held-out rows are never learned from."""
    labelled = docs.select(F.col("doc_id").cast("long"), F.col("text"), F.col("lang")).filter(F.col("lang").isNotNull() & (F.coalesce(F.octet_length("text"), F.lit(0)) > 0) & ~held_out(F.col("doc_id")))
    windows, labels = sample(labelled, bound)
    net = train(windows, labels) if labels else Network([], *[np.zeros(0)] * 5)
    return predict(docs, net).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
