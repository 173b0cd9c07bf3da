"""Interpolated modified Kneser-Ney language model (operator 3).

The model is a bigram model over lower-cased words with one end token per text and a start context. It is counted over
all training rows in three passes, each a map that adds up what its task has seen and deals it to hash shards as
compressed blocks, and a reduce that merges one shard in memory and stores sorted arrays in the shared folder:

1. vocabulary: sorted 64-bit word hashes with counts; a word's id is its position over all shards;
2. bigrams: sorted 64-bit hashes of id pairs (a bijective mix, so no two pairs meet) with counts;
3. per word: followers seen once, twice, more often (for the back-off weight of the word as a context) and different
   predecessors (for the lower-order probability).

Scoring maps the arrays into memory (``numpy.memmap``), each when it is first asked for, so workers of a machine share
one copy in the page cache and no model goes through the driver. A folder that is mounted on all machines is mapped where
it lies; from any other store that pyarrow opens, a worker copies the shards it needs to its own disk first.

Defined results: a null or empty text is its end token alone; repeated rows count and are scored each; with no training
rows every text scores 0 (one unknown event of probability 1 a token); an empty table gives no rows; extra columns are
ignored; null ids count as the text '' in the fold rule.
"""

from __future__ import annotations

import hashlib
import io
import os
import tempfile
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyarrow import fs
from pyspark.sql import functions as F

from textgroups.llm.words import _mix, as_text, hash_strings, slices, split_words
from textgroups.plans.storage import input_bytes, local_path, workspace

#: Input bytes a shard, about; shards are merged in memory one at a time.
SHARD_BYTES = 24 << 20
#: Different keys that a map task holds before it deals them out.
HELD_KEYS = 3_000_000
#: Arrays that a worker has mapped at once, of each kind; systems bound the maps of a process at about 65 000.
MOST_MAPS = 8192
END_HASH, START = np.uint64(0x5851F42D4C957F2D), np.uint64(0xFFFFFFFF)
_UNKNOWN = np.uint64(0xFFFFFFFE)
#: The optimizer's estimate for a plan that it knows nothing about is beyond this.
_UNKNOWN_BYTES = 1 << 55
FOLDS, HELD_OUT = 5, 1


def held_out(doc_id):
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(FOLDS)) == HELD_OUT


def _pack(*arrays: np.ndarray) -> bytes:
    """Arrays of equal length as one compressed block; the bytes of each array are laid out by significance."""
    planes = b"".join(np.ascontiguousarray(a.view(np.uint8).reshape(len(a), a.itemsize).T).tobytes() for a in arrays)
    return zstandard.ZstdCompressor(level=1).compress(planes)


def _unpack(block: bytes, n: int, *kinds: type) -> list[np.ndarray]:
    octets = np.frombuffer(zstandard.ZstdDecompressor().decompress(block), np.uint8)
    out, at = [], 0
    for kind in kinds:
        width = np.dtype(kind).itemsize
        out.append(np.ascontiguousarray(octets[at : at + n * width].reshape(width, n).T).view(kind).ravel())
        at += n * width
    return out


def _summed(keys: np.ndarray, *values: np.ndarray) -> tuple[np.ndarray, ...]:
    """Different keys in order with the sums of their values."""
    order = np.argsort(keys, kind="stable")
    keys = keys[order]
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)
    return keys[first], *[np.add.reduceat(v[order], first) if len(first) else v for v in values]


def _delta(keys: np.ndarray) -> np.ndarray:
    return np.diff(keys, prepend=np.zeros(1, keys.dtype))


def _deal(shard: np.ndarray, keys: np.ndarray, *values: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Blocks of the sorted keys by shard."""
    order = np.argsort(shard, kind="stable")
    cuts = np.searchsorted(shard[order], np.arange(int(shard.max()) + 2 if len(shard) else 1))
    for s in np.flatnonzero(np.diff(cuts)):
        at = order[cuts[s] : cuts[s + 1]]
        yield pa.record_batch([pa.array([int(s)], pa.int32()), pa.array([len(at)], pa.int64()), pa.array([_pack(_delta(keys[at]), *[v[at] for v in values])], pa.binary())], names=["shard", "n", "block"])


def _save(folder: str, name: str, array: np.ndarray) -> None:
    """Whole or not at all, so that a task that is run again only repeats its file."""
    if local_path(folder) is None:  # an object of such a store is there once it is complete
        held = io.BytesIO()
        np.save(held, array)
        store, path = fs.FileSystem.from_uri(folder)
        with store.open_output_stream(f"{path}/{name}.npy") as f:
            f.write(held.getbuffer())
        return
    path = f"{local_path(folder)}/{name}.npy"
    part = f"{path}.{os.getpid()}.{os.urandom(4).hex()}"
    with open(part, "wb") as f:
        np.save(f, array)
    os.replace(part, path)


def _open(folder: str, name: str) -> np.ndarray | None:
    """The array, mapped; None where no key fell into its shard."""
    at = local_path(folder)
    path = f"{at}/{name}.npy" if at is not None else _copied(*fs.FileSystem.from_uri(folder), name)
    return np.load(path, mmap_mode="r") if path and os.path.exists(path) else None


def _copied(store: fs.FileSystem, folder: str, name: str) -> str | None:
    """A copy of a stored array on this machine, made once."""
    if store.get_file_info(f"{folder}/{name}.npy").type == fs.FileType.NotFound:
        return None
    own = os.path.join(tempfile.gettempdir(), "ngram-" + hashlib.md5(folder.encode()).hexdigest())
    path = f"{own}/{name}.npy"
    if not os.path.exists(path):
        os.makedirs(own, exist_ok=True)
        part = f"{path}.{os.getpid()}.{os.urandom(4).hex()}"
        with store.open_input_stream(f"{folder}/{name}.npy") as f, open(part, "wb") as out:
            while block := f.read(1 << 24):
                out.write(block)
        os.replace(part, path)
    return path


class Shards:
    """The arrays of one kind by shard, mapped when they are first asked for."""

    def __init__(self, folder: str, name: str, empty: Callable[[int], np.ndarray]):
        found = lambda s: x if (x := _open(folder, f"{name}-{s}")) is not None else empty(s)
        self._of = lru_cache(MOST_MAPS)(found)

    def __getitem__(self, s: int) -> np.ndarray:
        return self._of(int(s))


def _top(hashes: np.ndarray, bits: int) -> np.ndarray:
    return (hashes >> np.uint64(64 - bits)).astype(np.int64) if bits else np.zeros(len(hashes), np.int64)


class Vocabulary:
    """Sorted word hashes and counts, shard after shard."""

    def __init__(self, folder: str, bits: int):
        self.bits = bits
        self.hashes = Shards(folder, "words", lambda s: np.zeros(0, np.uint64))
        self.bases = _open(folder, "bases")
        self.folder = folder

    def ids(self, hashes: np.ndarray) -> np.ndarray:
        """Ids of word hashes, _UNKNOWN where a word was never seen."""
        return _find(self.hashes, self.bits, hashes, lambda s, at: (self.bases[s] + at).astype(np.uint64), _UNKNOWN)


def _find(shards: Shards, bits: int, hashes: np.ndarray, value: Callable[[int, np.ndarray], np.ndarray], missing) -> np.ndarray:
    """``value(shard, positions)`` of each hash; the needles go through the arrays in their order."""
    order = np.argsort(hashes)
    ranked = hashes[order]
    cuts = np.searchsorted(_top(ranked, bits), np.arange((1 << bits) + 1))
    got = np.full(len(hashes), missing)
    for s in np.flatnonzero(np.diff(cuts)):
        part, array = ranked[cuts[s] : cuts[s + 1]], shards[s]
        if len(array):
            at = np.minimum(np.searchsorted(array, part), len(array) - 1)
            hit = array[at] == part
            found = np.full(len(part), missing)
            found[hit] = value(int(s), at[hit])
            got[cuts[s] : cuts[s + 1]] = found
    out = np.empty_like(got)
    out[order] = got
    return out


def _tokens(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, positions in the hashes, hashes) of the tokens of each text, the end token included."""
    starts, codes, distinct = split_words(texts, lower=True)
    hashes = np.concatenate([hash_strings(distinct), [END_HASH]])
    n = len(starts) - 1
    out = np.full(len(codes) + n, len(hashes) - 1, np.int64)
    real = np.ones(len(out), bool)
    real[starts[1:] + np.arange(n)] = False
    out[real] = codes
    return starts + np.arange(n + 1), out, hashes


def _pairs(starts: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Packed (previous token, token); the first one of a text follows START."""
    before = np.concatenate([[START], ids[:-1]]) if len(ids) else ids
    before[starts[:-1]] = START
    return before << np.uint64(32) | ids


def _counted(docs: DataFrame, keys_of: Callable[[pa.Array], tuple[np.ndarray, np.ndarray]], shard_of: Callable[[np.ndarray], np.ndarray]) -> DataFrame:
    """(shard, n, block) rows of all keys of the texts with their counts, added up within tasks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        size = 0

        def flush() -> Iterator[pa.RecordBatch]:
            keys, counts = _summed(np.concatenate([k for k, _ in held]), np.concatenate([c for _, c in held]))
            yield from _deal(shard_of(keys), keys, counts.astype(np.uint32))

        for batch in batches:
            for part in slices(batch, "text"):
                keys, counts = keys_of(as_text(part.column("text")))
                held.append((keys, counts))
                size += len(keys)
                if size > HELD_KEYS:
                    yield from flush()
                    held, size = [], 0
        if size:
            yield from flush()

    return docs.select("text").mapInArrow(run, "shard int, n long, block binary")


def _merged(rows: DataFrame, shards: int, kinds: tuple[type, ...], finish: Callable[[int, np.ndarray, list[np.ndarray]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """Every shard's blocks merged; ``finish(shard, keys, sums)`` stores it and says what goes on."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blocks: dict[int, list[tuple[int, bytes]]] = {}
        for batch in batches:
            for s, n, block in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                blocks.setdefault(s, []).append((n, block))
        for s in sorted(blocks):
            parts = [_unpack(block, n, np.uint64, *kinds) for n, block in blocks.pop(s)]
            keys = np.concatenate([np.cumsum(p[0]) for p in parts])
            values = [np.concatenate([p[i + 1] for p in parts]).astype(np.int64) for i in range(len(kinds))]
            del parts
            keys, *values = _summed(keys, *values)
            yield from finish(s, keys, values)

    return rows.repartitionById(shards, F.col("shard")).mapInArrow(run, schema)


def narrow(counts: np.ndarray) -> np.ndarray:
    """Counts in 32 bits where all of a shard fit, else in 64."""
    return counts.astype(np.uint32 if counts.max(initial=0) < 1 << 32 else np.uint64)


def discounts(n: list[int]) -> list[float]:
    """Discounts of counts 1, 2 and 3 or more from the numbers of counts 1 to 4; bounded where a number is missing."""
    n1, n2, n3, n4 = n
    y = n1 / (n1 + 2 * n2) if n1 + 2 * n2 else 0.5
    raw = [1 - 2 * y * n2 / n1 if n1 else y, 2 - 3 * y * n3 / n2 if n2 else 2 * y, 3 - 4 * y * n4 / n3 if n3 else 3 * y]
    return [min(max(d, 0.05 * (i + 1)), 0.95 * (i + 1)) for i, d in enumerate(raw)]


def _of_counts(counts: np.ndarray) -> list[int]:
    found = np.bincount(np.minimum(counts, 5), minlength=6)
    return [int(x) for x in found[1:5]]


def fit(training: DataFrame, folder: str | None = None) -> dict:
    """Count the model over ``training(text)`` and store it; returns its description (a few numbers)."""
    spark = training.sparkSession
    folder = folder or workspace(spark, "ngram")
    if (at := local_path(folder)) is not None:
        os.makedirs(at, exist_ok=True)
    size = input_bytes(training.select("text"))
    if size >= _UNKNOWN_BYTES:
        size = (training.agg(F.sum(F.octet_length("text"))).first()[0] or 0) // 2
    bits = max(0, int(np.ceil(np.log2(max(1, size / SHARD_BYTES)))))
    shards = 1 << bits

    def words_of(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        _, codes, hashes = _tokens(texts)
        return _summed(hashes, np.bincount(codes, minlength=len(hashes)).astype(np.int64))

    def used(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return keys[counts > 0], counts[counts > 0]

    def store_words(s: int, keys: np.ndarray, values: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        _save(folder, f"words-{s}", keys)
        _save(folder, f"counts-{s}", values[0])
        yield pa.record_batch([pa.array([s]), pa.array([len(keys)]), pa.array([int(values[0].sum())])], names=["s", "v", "n"])

    counted = _counted(training, lambda t: used(*words_of(t)), lambda k: _top(k, bits))
    vocabulary = _merged(counted, shards, (np.uint32,), store_words, "s long, v long, n long").toArrow()  # a row a shard
    sizes = np.zeros(shards + 1, np.int64)
    sizes[vocabulary.column("s").to_numpy() + 1] = vocabulary.column("v").to_numpy()
    _save(folder, "bases", np.cumsum(sizes))
    model = {"folder": folder, "bits": bits, "v": int(sizes.sum()), "n": int(vocabulary.column("n").to_numpy().sum())}
    if model["v"] >= int(_UNKNOWN):
        raise ValueError("word ids need more than 32 bits: train on fewer texts a model")
    if not model["n"]:
        return model

    def pairs_of(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        starts, codes, hashes = _tokens(texts)
        keys = _pairs(starts, _vocabulary(folder, bits).ids(hashes)[codes])
        return _summed(keys, np.ones(len(keys), np.int64))

    def by_word(tag: int, ids: np.ndarray, *values: np.ndarray) -> Iterator[pa.RecordBatch]:
        """Per-word sums for the shard of the word; tag 0: the word as a context, 1: the word as a follower."""
        ids, *values = _summed(ids, *values)
        bases = _vocabulary(folder, bits).bases
        shard = np.searchsorted(bases, ids.astype(np.int64), side="right") - 1
        shard[ids >= _UNKNOWN] = 0
        tagged = ids << np.uint64(1) | np.uint64(tag)
        zero = [np.zeros(len(ids), np.uint32)] * (3 - len(values))
        yield from _deal(shard, tagged, *[v.astype(np.uint32) for v in values], *zero)

    def store_pairs(s: int, keys: np.ndarray, values: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        counts = values[0]
        hashes = _mix(keys)
        order = np.argsort(hashes)
        _save(folder, f"pairs-{s}", hashes[order])
        _save(folder, f"pair-counts-{s}", narrow(counts[order]))
        tops = [np.array([x]) for x in _of_counts(counts)]
        none = np.array([_UNKNOWN])  # stands for no word: what all pairs are counted under
        yield from by_word(0, none, *tops[:3])
        yield from by_word(1, none, tops[3])
        one, two = counts == 1, counts == 2
        yield from by_word(0, keys >> np.uint64(32), one.astype(np.int64), two.astype(np.int64), (~one & ~two).astype(np.int64))
        yield from by_word(1, keys & np.uint64(0xFFFFFFFF), np.ones(len(keys), np.int64))

    def store_sums(s: int, keys: np.ndarray, values: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        bases = _vocabulary(folder, bits).bases
        ids, follower = keys >> np.uint64(1), (keys & np.uint64(1)).astype(bool)
        known, start, every = ids < _UNKNOWN, ids == START, ids == _UNKNOWN
        sums = np.zeros((4, int(bases[s + 1] - bases[s])), np.uint32)
        context, follows = known & ~follower, known & follower
        for i in range(3):
            sums[i, (ids[context].astype(np.int64) - bases[s])] = values[i][context]
        sums[3, (ids[follows].astype(np.int64) - bases[s])] = values[0][follows]
        _save(folder, f"sums-{s}", sums)
        begin = [int(v[start].sum()) for v in values]
        pair_tops = [*(int(v[every & ~follower].sum()) for v in values), int(values[0][every & follower].sum())]
        row = (*begin, int(sums[3].sum(dtype=np.int64)), int((sums[3] > 2).sum()), *_of_counts(sums[3]), *pair_tops)
        yield pa.record_batch([pa.array([x]) for x in row], names=names)

    names = ["s1", "s2", "s3", "follows", "more", "t1", "t2", "t3", "t4", "p1", "p2", "p3", "p4"]

    pairs = _merged(_counted(training, pairs_of, lambda k: _top(_mix(k), bits)), shards, (np.uint32,), store_pairs, "shard int, n long, block binary")
    sums = _merged(pairs, shards, (np.uint32,) * 3, store_sums, ", ".join(f"{n} long" for n in names)).agg(*[F.sum(n) for n in names]).first()
    model |= {"start": list(sums[:3]), "follows": sums[3], "tops1": list(sums[5:9]), "more1": sums[4], "tops2": list(sums[9:13])}
    model["d1"], model["d2"] = discounts(model["tops1"]), discounts(model["tops2"])
    return model


@lru_cache(maxsize=2)
def _vocabulary(folder: str, bits: int) -> Vocabulary:
    return Vocabulary(folder, bits)


class Model:
    """The stored model, mapped into memory."""

    def __init__(self, about: dict):
        self.about = about
        folder = about["folder"]
        self.vocabulary = _vocabulary(folder, about["bits"])
        none = lambda s: np.zeros(0, np.uint64)
        self.counts, self.pairs, self.pair_counts = (Shards(folder, name, none) for name in ("counts", "pairs", "pair-counts"))
        self.sums = Shards(folder, "sums", lambda s: np.zeros((4, len(self.counts[s])), np.uint32))
        self.docs = int(self.counts_of(self.vocabulary.ids(np.array([END_HASH])))[0])
        d1, a = about["d1"], about
        n1, n2 = a["tops1"][:2]
        self.base = (d1[0] * n1 + d1[1] * n2 + d1[2] * a["more1"]) / a["follows"] / (a["v"] + 1)

    def _dense(self, ids: np.ndarray, of: Callable[[int, np.ndarray], np.ndarray], rows: int) -> np.ndarray:
        """Values of known ids from the arrays by id; zero for others."""
        out = np.zeros((rows, len(ids)), np.int64)
        bases = self.vocabulary.bases
        shard = np.where(ids < _UNKNOWN, np.searchsorted(bases, ids.astype(np.int64), side="right") - 1, -1)
        for s in np.unique(shard[shard >= 0]):
            at = np.flatnonzero(shard == s)
            out[:, at] = of(int(s), ids[at].astype(np.int64) - bases[s])
        return out

    def counts_of(self, ids: np.ndarray) -> np.ndarray:
        return self._dense(ids, lambda s, at: self.counts[s][at], 1)[0]

    def sums_of(self, ids: np.ndarray) -> np.ndarray:
        return self._dense(ids, lambda s, at: self.sums[s][:, at], 4)

    def lower(self, follows: np.ndarray) -> np.ndarray:
        """Probability of a word by the number of its different predecessors."""
        d = np.array([0, *self.about["d1"]])[np.minimum(follows, 3)]
        return (follows - d) / self.about["follows"] + self.base

    def score(self, texts: pa.Array) -> dict[str, np.ndarray]:
        starts, codes, hashes = _tokens(texts)
        ids = self.vocabulary.ids(hashes)
        counts, sums = self.counts_of(ids), self.sums_of(ids)
        a = self.about
        lower = self.lower(sums[3])
        d = a["d2"]
        weight = d[0] * sums[0] + d[1] * sums[1] + d[2] * sums[2]
        # As a context; one more place for the start of a text. Unknown words have no followers.
        seen, weight = np.append(counts, self.docs), np.append(weight, np.dot(d, a["start"]))
        before = np.concatenate([[len(hashes)], codes[:-1]])
        before[starts[:-1]] = len(hashes)
        pair, inverse = np.unique(_pairs(starts, ids[codes]), return_inverse=True)
        number = _find(self.pairs, a["bits"], _mix(pair), lambda s, at: self.pair_counts[s][at].astype(np.int64), np.int64(0))[inverse]
        total = seen[before]
        safe = np.maximum(total, 1)
        off = np.array([0, *d])[np.minimum(number, 3)]
        p = np.where(total > 0, (number - off + weight[before] * lower[codes]) / safe, lower[codes])
        base = np.log10((counts + 0.5) / (a["n"] + 0.5 * (a["v"] + 1)))[codes]
        add = lambda x: np.add.reduceat(x, starts[:-1]) if len(starts) > 1 else np.zeros(0, x.dtype)
        return {"n_tokens": np.diff(starts), "n_known": add((counts > 0).astype(np.int64)[codes]), "base_score": add(base), "score": add(np.log10(p))}


@lru_cache(maxsize=1)
def _model(folder: str, about: tuple) -> Model:
    return Model(dict(about) | {k: list(v) for k, v in about if isinstance(v, tuple)})


def score(docs: DataFrame, model: dict) -> DataFrame:
    """(doc_id, n_tokens, n_known, train_tokens, base_score, score) of every whole text."""
    about = tuple((k, tuple(v) if isinstance(v, list) else v) for k, v in model.items())
    names = ["n_tokens", "n_known", "base_score", "score"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                texts = as_text(part.column("text"))
                if model["n"]:
                    got = _model(model["folder"], about).score(texts)
                else:
                    n = np.diff(_tokens(texts)[0])
                    got = {"n_tokens": n, "n_known": 0 * n, "base_score": 0.0 * n, "score": 0.0 * n}
                yield pa.record_batch([part.column("doc_id"), *[pa.array(got[x]) for x in names]], names=["doc_id", *names])

    scored = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, n_tokens long, n_known long, base_score double, score double")
    return scored.select("doc_id", "n_tokens", "n_known", F.lit(model["n"]).cast("long").alias("train_tokens"), "base_score", "score")


def score_held_out(docs: DataFrame, folder: str | None = None) -> DataFrame:
    """Learn from the rows outside the held-out fold, score all; adds ``held_out`` and ``perplexity``."""
    model = fit(docs.filter(~held_out(F.col("doc_id"))).select("text"), folder)
    scored = score(docs, model)
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score", F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens")).alias("perplexity"))
