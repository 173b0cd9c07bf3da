"""Best-fit packing by a plan over the length histogram (operator 7).

Texts become token ids plus an end id; longer documents are cut into pieces of ``capacity`` tokens. The plan reads only
the histogram of piece lengths (at most ``capacity`` numbers, whatever the size of the data): lengths in falling order
go to the open sequences with the least room that is enough, sequences with equal room and history being one group with
a count. The plan is a list of runs: the pieces of ranks a..b of a length fill such and such sequences at such an
offset. Pieces are ranked within their length in a distributed way and find their place in the runs of their length.

The number of runs does not depend on the data: per length at most three groups are added, and a group gets at most 90
different lengths (different lengths adding up to 4096), so there are at most some 1.1 million runs.

Defined results: a null text is empty and gives one piece, the end id; repeated rows are pieces of their own; nulls in
``doc_id`` stay null; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import heapq
import os
import zlib
from collections import defaultdict
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import public_tokenizers
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textgroups.llm.words import as_text, slices, split_words
from textgroups.plans.skew import running_totals
from textgroups.plans.storage import materialise

CAPACITY = 4096
TOKENIZER = "word_bpe_49k.json"
END_ID = 1
#: Different words whose ids a worker keeps; the store is emptied when it is full.
CACHE_WORDS = 600_000
#: Bytes of text encoded at once, about: a worker's arrays follow it.
ENCODE_BYTES = 2 << 20
BUCKET_ROWS = 20_000


#: A word of letters with ASCII punctuation behind it: the tokenizer splits it there. The one letter whose lower case
#: holds a mark (dotted capital I) is not split from what follows.
_LETTERS_THEN_MARKS = r"^(?P<head>[^\P{L}\x{0130}]+)(?P<tail>[!-/:-@\[-`{-~]+)$"


class WordIds:
    """Token ids of words, remembered between batches.

    Exact for tokenizers that drop white space and whose pre-tokens never span it, as the one used here: the ids of a
    text are those of its words one after the other, and the ids of letters followed by marks are those of the two
    parts. The tokenizer lower-cases, so A-Z are lower-cased first, except where a text may hold a special string.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
        from tokenizers import Tokenizer

        self.encoder = Tokenizer.from_file(path)
        self.encoder.no_truncation()
        self.encoder.no_padding()
        self.clear()

    def clear(self) -> None:
        self.place: dict[str, int] = {"": 0}
        self.ids = np.zeros(1 << 20, np.uint32)
        self.sizes = np.zeros(1 << 16, np.int32)
        self.begins = np.zeros(1 << 16, np.int64)
        self.used = 0

    def _room(self, name: str, n: int) -> None:
        old = getattr(self, name)
        if n > len(old):
            new = np.zeros(max(n, 2 * len(old)), old.dtype)
            new[: len(old)] = old
            setattr(self, name, new)

    def _learn(self, words: list[str]) -> None:
        for i in range(0, len(words), 20_000):
            part = words[i : i + 20_000]
            found = [e.ids for e in self.encoder.encode_batch_fast(part, add_special_tokens=False)]
            sizes = np.fromiter(map(len, found), np.int32, len(found))
            flat = np.fromiter(chain.from_iterable(found), np.uint32, int(sizes.sum()))
            n = len(self.place)
            self._room("sizes", n + len(part))
            self._room("begins", n + len(part))
            self._room("ids", self.used + len(flat))
            self.sizes[n : n + len(part)] = sizes
            self.begins[n : n + len(part)] = self.used + np.cumsum(sizes) - sizes
            self.ids[self.used : self.used + len(flat)] = flat
            self.used += len(flat)
            self.place.update(zip(part, range(n, n + len(part)), strict=True))

    def _places(self, distinct: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Places of the first and second part of each word; the second one is 0 where there is none."""
        cut = pc.extract_regex(distinct, _LETTERS_THEN_MARKS)
        whole = pc.is_null(cut)
        head = pc.if_else(whole, distinct, pc.struct_field(cut, 0))
        tail = pc.if_else(whole, pa.scalar(""), pc.struct_field(cut, 1))
        coded = pa.concat_arrays([head, tail]).dictionary_encode()
        parts = coded.dictionary.to_pylist()
        if len(self.place) + len(parts) > CACHE_WORDS:
            self.clear()
        self._learn([w for w in parts if w not in self.place])
        at = np.fromiter(map(self.place.__getitem__, parts), np.int64, len(parts))[coded.indices.to_numpy(zero_copy_only=False)]
        return at[: len(distinct)], at[len(distinct) :]

    def encode(self, texts: pa.Array, end_id: int = END_ID) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts with their end ids, tokens of each text)."""
        plain = not pc.any(pc.match_substring(texts, "<|")).as_py()
        starts, codes, distinct = split_words(texts, lower=plain)
        head, tail = self._places(distinct)
        number = (1 + (tail > 0))[codes]  # parts of each word
        upto = np.concatenate([[0], np.cumsum(number)])
        at = np.repeat(head[codes], number)
        two = np.flatnonzero(number == 2)
        at[upto[two] + 1] = tail[codes[two]]
        sizes = self.sizes[at].astype(np.int64)
        ends = np.concatenate([[0], np.cumsum(sizes)])
        of_text = ends[upto[starts]]
        tokens = np.diff(of_text) + 1
        within = np.arange(ends[-1]) + np.repeat(self.begins[at] - ends[:-1], sizes)
        out = np.full(int(tokens.sum()), end_id, np.uint32)
        real = np.ones(len(out), bool)
        real[np.cumsum(tokens) - 1] = False
        out[real] = self.ids[within]
        return out, tokens


@lru_cache(maxsize=2)
def _word_ids(path: str) -> WordIds:
    return WordIds(path)


def pieces(docs: DataFrame, tokenizer: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID, keep_ids: bool = False) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32) of every piece, with ``ids array<int>`` if ``keep_ids``."""
    path = tokenizer or public_tokenizers.path(TOKENIZER)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _word_ids(path)
        for batch in batches:
            for part in slices(batch, "text", ENCODE_BYTES):
                ids, tokens = encoder.encode(as_text(part.column("text")), end_id)
                number = -(-tokens // capacity)
                owner = np.repeat(np.arange(len(tokens)), number)
                piece = np.arange(len(owner)) - np.repeat(np.cumsum(number) - number, number)
                begin = piece * capacity
                length = np.minimum(capacity, tokens[owner] - begin)
                first = (np.cumsum(tokens) - tokens)[owner] + begin
                octets = memoryview(ids.astype("<u4").tobytes())
                crc = np.fromiter((zlib.crc32(octets[4 * a : 4 * b]) for a, b in zip(first.tolist(), (first + length).tolist(), strict=True)), np.int64, len(owner))
                columns = [pc.take(part.column("doc_id"), pa.array(owner)), pa.array(piece.astype(np.int32)), pa.array(begin), pa.array(length), pa.array(crc)]
                names = ["doc_id", "piece", "start", "length", "ids_crc32"]
                if keep_ids:
                    columns.append(pa.ListArray.from_arrays(pa.array(np.append(first, len(ids)).astype(np.int32)), pa.array(ids.astype(np.int32))))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(columns, names=names)

    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * keep_ids
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, schema)


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int, int]]:
    """Runs (length, first rank, count, first sequence, per sequence, offset) of a best-fit packing of the histogram.

    Rank r of a run goes to sequence ``first sequence + r // per sequence`` at ``offset + length * (r % per sequence)``,
    r counted from the run's first rank.
    """
    rooms: list[int] = []
    groups: dict[int, list[tuple[int, int]]] = defaultdict(list)  # room -> (first sequence, count)
    sequences, runs = 0, []

    def put(room: int, group: tuple[int, int]) -> None:
        if room and group[1]:
            if not groups[room]:
                heapq.heappush(rooms, room)
            groups[room].append(group)

    for length in sorted(histogram, reverse=True):
        left, rank = histogram[length], 0
        held = []  # rooms too small for this length stay for shorter ones
        while left:
            while rooms and (rooms[0] < length or not groups[rooms[0]]):
                room = heapq.heappop(rooms)
                if groups[room]:
                    held.append(room)
            if rooms:
                room = rooms[0]
                first, count = groups[room].pop()
                if not groups[room]:
                    heapq.heappop(rooms)
            else:
                room, first = capacity, sequences
                count = -(-left // (capacity // length))
                sequences += count
            each = room // length
            full = min(count, left // each)
            if full:
                runs.append((length, rank, full * each, first, each, capacity - room))
                put(room - each * length, (first, full))
                rank, left = rank + full * each, left - full * each
            if left and full < count:
                runs.append((length, rank, left, first + full, each, capacity - room))
                put(room - left * length, (first + full, 1))
                rank, left, full = rank + left, 0, full + 1
            put(room, (first + full, count - full))
        for room in held:
            heapq.heappush(rooms, room)
    return runs


def pack(docs: DataFrame, tokenizer: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID, keep_ids: bool = False) -> DataFrame:
    """One row per piece with its place: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    cut = materialise(pieces(docs, tokenizer, capacity, end_id, keep_ids), "pieces")
    histogram = {r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most `capacity` rows
    runs = np.array(plan(histogram, capacity), np.int64).reshape(-1, 6)
    order = np.lexsort((runs[:, 1], runs[:, 0]))
    runs = runs[order]
    digits = 1
    while 16**digits * BUCKET_ROWS < sum(histogram.values()) and digits < 7:
        digits += 1
    keyed = cut.withColumn("_h", F.xxhash64("doc_id", "piece", "ids_crc32")).withColumn("_b", F.substring(F.lpad(F.hex("_h"), 16, "0"), 1, digits))
    ranked = running_totals(keyed, ["length"], "_b", [F.lpad(F.hex("_h"), 16, "0")], F.lit(0), "_rank", "_zero").drop("_h", "_b", "_zero")
    names = ranked.columns[:-1]
    at_length, at_rank = ranked.columns.index("length"), ranked.columns.index("_rank")
    # Position of a run in one number line: the lengths one after the other, each as long as its pieces.
    lengths = np.array(sorted(histogram), np.int64)
    bases = np.concatenate([[0], np.cumsum([histogram[x] for x in lengths.tolist()])]).astype(np.int64)
    run_at = bases[np.searchsorted(lengths, runs[:, 0])] + runs[:, 1] if len(runs) else np.zeros(0, np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, rank = (batch.column(i).to_numpy(zero_copy_only=False) for i in (at_length, at_rank))
            i = np.searchsorted(run_at, bases[np.searchsorted(lengths, length)] + rank, side="right") - 1
            inside = rank - runs[i, 1]
            sequence, offset = runs[i, 3] + inside // runs[i, 4], runs[i, 5] + length * (inside % runs[i, 4])
            columns = [batch.column(j) for j in range(batch.num_columns) if j != at_rank]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(sequence), pa.array(offset)], names=[*names, "sequence_id", "offset"])

    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in ranked.schema.fields if f.name != "_rank")
    placed = ranked.mapInArrow(run, f"{fields}, sequence_id long, offset long")
    return placed.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset", *(["ids"] if keep_ids else []))
