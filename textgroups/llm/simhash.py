"""SimHash near-dedup with Golay-code fuzzy hashing (operator 10).

Fingerprints of 64 bits are cut into segments of 23, 23 and 18 bits (the last one padded with zeros to 23). The binary
Golay code (23, 12) is perfect, so a segment has one nearest codeword (at most 3 bits away); taking every codeword
within 4 bits gives one or six codeword indices, and two segments that differ in at most one bit share at least one.
If two fingerprints differ in at most 2 bits, then in one of the segment pairs (1, 2), (2, 3), (3, 1) the first
segments are equal and the second ones differ in at most one bit. So (pair, first segment, codeword index of the second)
is a key that linked fingerprints share: about 16 keys for a fingerprint, of 30 or 35 bits each.

Candidates are joined on the key and verified. Keys that more than BUCKET_LIMIT different fingerprints share take an
exact way without pairs: two fingerprints are within 2 bits exactly if they, or two of their one-bit neighbours, are
equal, so each fingerprint is linked to the smallest one on each of its 65 neighbours; work stays linear in the bucket.

Defined results: a null or empty text, or one without words, has fingerprint zero and is linked like any other; fewer
words than a shingle are one shingle; repeated rows and ids are linked by their fingerprints; null ids never become a
component id unless all ids of the component are null; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from itertools import combinations, product

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textgroups.llm.words import _mix, as_text
from textgroups.operators.components import components, spanning_forest
from textgroups.plans.skew import join_lookup
from textgroups.plans.storage import materialise

SHINGLE, SEED, MAX_BITS = 3, 42, 2
#: Keys with more different fingerprints than this are linked over one-bit neighbours.
BUCKET_LIMIT = 16
#: Generator polynomial of the Golay code: x^11 + x^10 + x^6 + x^5 + x^4 + x^2 + 1.
GENERATOR = 0b110001110101
_STEP = 1 << 18
#: Bits of a Golay codeword, and the most bits that soft decoding turns.
SEGMENT_BITS, SOFT_WEIGHT = 23, 5


def fingerprint(text: str, shingle: int = SHINGLE) -> int:
    """Fingerprint of one text, as an unsigned number."""
    words = text.encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    line = b" ".join(words)
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(sizes + 1) - 1
    first, last = (ends - sizes).tolist(), ends.tolist()
    k = min(shingle, len(words))
    digest, counts, n = xxhash.xxh64_digest, np.zeros(64, np.int64), len(words) - k + 1
    for i in range(0, n, _STEP):
        joined = b"".join([digest(line[a:b], SEED) for a, b in zip(first[i : min(n, i + _STEP)], last[i + k - 1 : min(n, i + _STEP) + k - 1], strict=True)])
        counts += np.unpackbits(np.frombuffer(joined, np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * counts > n).tobytes(), "big")


def fingerprints(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """(doc_id, fp): fp holds the 64 bits as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = np.fromiter((fingerprint(t.as_py(), shingle) for t in as_text(batch.column("text"))), np.uint64, batch.num_rows)
            yield pa.record_batch([batch.column("doc_id"), pa.array(values.view(np.int64))], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, fp long")


def _remainder(word: int) -> int:
    for bit in range(22, 10, -1):
        if word >> bit & 1:
            word ^= GENERATOR << (bit - 11)
    return word


@lru_cache(1)
def golay_tables() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Syndrome of the upper 12 bits of a word, error patterns (up to weight 4) of each syndrome, and their number.

    The code is systematic: a codeword's index is its upper 12 bits, its remainder modulo the generator is zero.
    """
    upper = np.array([_remainder(i << 11) for i in range(4096)], np.int64)
    single = [_remainder(1 << i) for i in range(23)]
    lists: list[list[int]] = [[] for _ in range(2048)]
    for weight in range(5):
        for bits in combinations(range(23), weight):
            s = 0
            for b in bits:
                s ^= single[b]
            lists[s].append(sum(1 << b for b in bits))
    patterns, number = np.zeros((2048, max(map(len, lists))), np.int64), np.array([len(x) for x in lists])
    for s, x in enumerate(lists):
        patterns[s, : len(x)] = x
    return upper, patterns, number


def codeword_indices(segment: np.ndarray, tables: tuple[np.ndarray, np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """(position, index): the indices of all codewords within 4 bits of each 23-bit segment."""
    upper, patterns, number = tables
    syndrome = upper[segment >> 11] ^ (segment & 2047)
    count = number[syndrome]
    at = np.repeat(np.arange(len(segment)), count)
    within = np.arange(len(at)) - np.repeat(np.cumsum(count) - count, count)
    return at, (segment[at] ^ patterns[syndrome[at], within]) >> 11


def keys_of(fp: np.ndarray, tables: tuple[np.ndarray, np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """(position, key) of all fuzzy keys of the fingerprints."""
    segments = [(fp >> np.uint64(41)).astype(np.int64), (fp >> np.uint64(18) & np.uint64(0x7FFFFF)).astype(np.int64), (fp & np.uint64(0x3FFFF)).astype(np.int64)]
    at, keys = [], []
    for pair in range(3):
        where, index = codeword_indices(segments[(pair + 1) % 3], tables)
        at.append(where)
        keys.append((pair << 35) | (segments[pair][where] << 12) | index)
    return np.concatenate(at), np.concatenate(keys)


def fuzzy_keys(distinct: DataFrame) -> DataFrame:
    """(key, fp) rows of different fingerprints."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = golay_tables()
        for batch in batches:
            fp = batch.column(0).to_numpy(zero_copy_only=False)
            for i in range(0, len(fp), 1 << 16):
                part = fp[i : i + (1 << 16)]
                at, keys = keys_of(part.view(np.uint64), tables)
                yield pa.record_batch([pa.array(keys), pa.array(part[at])], names=["key", "fp"])

    return distinct.select("fp").mapInArrow(run, "key long, fp long")


@lru_cache(1)
def _patterns() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """By syndrome: the error patterns of up to SOFT_WEIGHT bits, their bit places (SEGMENT_BITS: none), and which are real."""
    single = [_remainder(1 << (SEGMENT_BITS - 1 - i)) for i in range(SEGMENT_BITS)]
    lists: list[list[tuple[int, ...]]] = [[] for _ in range(2048)]
    for weight in range(SOFT_WEIGHT + 1):
        for places in combinations(range(SEGMENT_BITS), weight):
            s = 0
            for i in places:
                s ^= single[i]
            lists[s].append(places)
    most = max(map(len, lists))
    words, places = np.zeros((2048, most), np.int64), np.full((2048, most, SOFT_WEIGHT), SEGMENT_BITS, np.int64)
    for s, found in enumerate(lists):
        for j, at in enumerate(found):
            words[s, j] = sum(1 << (SEGMENT_BITS - 1 - i) for i in at)
            places[s, j, : len(at)] = at
    return words, places, np.arange(most) < np.array([len(x) for x in lists])[:, None]


def bit_sums(hashes: np.ndarray, bits: int) -> np.ndarray:
    """For each of ``bits`` fingerprint bits: the hashes that have it set less those that don't, over the root of their number."""
    words = -(-bits // 64)
    seeds = _mix(np.arange(1, words + 1, dtype=np.uint64))
    places = np.arange(8 * words, dtype=np.int64) * 256
    counts = np.zeros(8 * words * 256, np.int64)
    for i in range(0, len(hashes), 4096):
        octets = _mix(hashes[i : i + 4096, None] ^ seeds).view(np.uint8)
        counts += np.bincount((octets + places).ravel(), minlength=len(counts))
    of_byte = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1).astype(np.float64)
    ones = (counts.reshape(-1, 256).astype(np.float64) @ of_byte).ravel()[:bits]
    return (2 * ones - len(hashes)) / np.sqrt(max(1, len(hashes)))


def soft_keys(sums: np.ndarray, tables: int, segments: int, probes: int) -> np.ndarray:
    """(texts, tables * probes) fuzzy keys of rows of bit sums.

    A key is a table and one codeword index for each of its ``segments``. Every segment is decoded to the codewords whose
    disagreement with it, weighed by how clear the disagreeing bits are, is least; of the combinations the ``probes``
    least in all are taken. Near copies differ in unclear bits first, so they share a key far more often than by the
    number of their differing bits.
    """
    n = len(sums)
    words, places, real = _patterns()
    x = sums.reshape(-1, SEGMENT_BITS)
    hard = (x > 0) @ (1 << np.arange(SEGMENT_BITS - 1, -1, -1))
    clear = np.concatenate([np.abs(x), np.zeros((len(x), 1))], axis=1)
    syndrome = golay_tables()[0][hard >> 11] ^ (hard & 2047)
    cost = np.take_along_axis(clear[:, None, :], places[syndrome].reshape(len(x), 1, -1), axis=2).reshape(len(x), -1, SOFT_WEIGHT).sum(axis=2)
    cost[~real[syndrome]] = np.inf
    best = np.argsort(cost, axis=1, kind="stable")[:, :probes]
    cost = np.take_along_axis(cost, best, axis=1).reshape(n, tables, segments, probes)
    index = ((hard[:, None] ^ np.take_along_axis(words[syndrome], best, axis=1)) >> 11).reshape(n, tables, segments, probes)
    chosen = np.array([c for c in product(range(probes), repeat=segments) if np.prod(np.array(c) + 1) <= probes])  # no other one is among the least
    keys, total = np.zeros((n, tables, len(chosen)), np.int64), np.zeros((n, tables, len(chosen)))
    for s in range(segments):
        keys, total = keys << 12 | index[:, :, s, chosen[:, s]], total + cost[:, :, s, chosen[:, s]]
    least = np.argsort(total, axis=2, kind="stable")[:, :, :probes]
    return (np.take_along_axis(keys, least, axis=2) | (np.arange(tables)[None, :, None] << 12 * segments)).reshape(n, -1)


def links(distinct: DataFrame) -> DataFrame:
    """Edges (a, b) between different fingerprints whose components are those of all links of up to MAX_BITS bits."""
    keys = materialise(fuzzy_keys(distinct), "keys")
    shared = keys.groupBy("key").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    candidates = materialise(keys.join(shared, "key"), "candidates")
    small = candidates.filter(F.col("n") <= BUCKET_LIMIT)
    one, two = small.select("key", F.col("fp").alias("a")), small.select("key", F.col("fp").alias("b"))
    pairs = one.join(two.hint("merge"), "key").filter("a < b").filter(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= MAX_BITS).select("a", "b")
    large = candidates.filter(F.col("n") > BUCKET_LIMIT).select("fp").distinct()
    flips = F.array(F.lit(0).cast("long"), *[F.lit((1 << i) - (1 << 64 if i == 63 else 0)).cast("long") for i in range(64)])
    near = materialise(large.select("fp", F.explode(flips).alias("flip")).select("fp", F.col("fp").bitwiseXOR(F.col("flip")).alias("near")), "near")
    least = near.groupBy("near").agg(F.min("fp").alias("a"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    stars = near.join(least, "near").filter("a <> fp").select("a", F.col("fp").alias("b"))
    return spanning_forest(pairs.unionByName(stars))


def labels(distinct: DataFrame, edges: DataFrame) -> DataFrame:
    """(fp, n, comp, component_id) of the written ``distinct(fp, least, n)``: its component and the smallest id in it."""
    joined = components(edges)
    of = distinct.join(joined.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", "n", F.coalesce("comp", "fp").alias("comp"))
    of = materialise(of, "labels")
    ids = of.groupBy("comp").agg(F.min("least").alias("component_id"), F.count(F.lit(1)).alias("prints"))
    ids = materialise(ids, "ids")
    return materialise(join_lookup(of, ids, "comp", "prints").select("fp", "n", "comp", "component_id"), "by-print")


def near_groups(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """One row per document: doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable by links)."""
    prints = materialise(fingerprints(docs, shingle), "fingerprints")
    distinct = materialise(prints.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("n")), "distinct")
    by_print = labels(distinct, links(distinct)).drop("comp")
    out = join_lookup(prints, by_print, "fp", "n")
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
