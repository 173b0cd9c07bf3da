"""Words of Arrow text columns as arrays: no Python object for a word that was seen before in its batch."""

from __future__ import annotations

import ctypes
from contextlib import suppress
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash

#: Java and Python pattern of a word; white space is these six characters only.
WORD = r"[^\x20\x09-\x0D]+"
#: Texts are worked on in slices of about so many bytes, so that memory does not follow the batch size.
SLICE_BYTES = 8 << 20
_LONG = 64


class Words(NamedTuple):
    """``codes[starts[i]:starts[i + 1]]`` are the words of text i as positions in ``distinct``."""

    starts: np.ndarray
    codes: np.ndarray
    distinct: pa.Array


def let_go() -> None:
    """Give the memory of a finished task back to the system: workers live on and take other tasks."""
    pa.default_memory_pool().release_unused()
    with suppress(OSError, AttributeError):  # other C libraries have no such call
        ctypes.CDLL(None).malloc_trim(0)


def as_text(column: pa.Array) -> pa.Array:
    """Null counts as the empty text."""
    return pc.fill_null(column.cast(pa.string()), "")


def slices(batch: pa.RecordBatch, column: str | int, most: int = SLICE_BYTES) -> list[pa.RecordBatch]:
    """The batch in runs of rows of about ``most`` bytes of text each (a longer text is a run of its own)."""
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    runs, first, held = [], 0, 0
    for i, size in enumerate(sizes):
        if held and held + size > most:
            runs.append(batch.slice(first, i - first))
            first, held = i, 0
        held += int(size)
    return [*runs, batch.slice(first)] if batch.num_rows else []


def split_words(texts: pa.Array, lower: bool = False) -> Words:
    if lower:
        texts = pc.ascii_lower(texts)
    lists = pc.ascii_split_whitespace(texts)
    flat = lists.flatten()
    starts = np.concatenate([[0], np.cumsum(pc.list_value_length(lists).to_numpy(zero_copy_only=False))]).astype(np.int64)
    coded = flat.dictionary_encode()
    codes = coded.indices.to_numpy(zero_copy_only=False)
    blank = pc.index(coded.dictionary, pa.scalar("", coded.dictionary.type)).as_py()
    if blank >= 0:
        real = codes != blank
        starts = np.concatenate([[0], np.cumsum(real)])[starts]
        codes = codes[real]
    return Words(starts, codes, coded.dictionary)


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def hash_strings(strings: pa.Array) -> np.ndarray:
    """A 64-bit hash of each string (FNV-1a with a final mix; XXH64 beyond 64 bytes), the same on every machine."""
    n = len(strings)
    if not n:
        return np.zeros(0, np.uint64)
    _, ends, data = strings.buffers()
    offsets = np.frombuffer(ends, np.int32)[strings.offset : strings.offset + n + 1].astype(np.int64)
    octets = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    sizes = np.diff(offsets)
    order = np.argsort(-sizes, kind="stable")
    first, sizes = offsets[:-1][order], sizes[order]
    longer = np.searchsorted(-sizes, -np.arange(_LONG + 1), side="left")  # longer[j]: strings of more than j bytes
    h = np.full(n, 0xCBF29CE484222325, np.uint64)
    for j in range(min(_LONG, int(sizes[0]))):
        k = longer[j]
        h[:k] = (h[:k] ^ octets[first[:k] + j]) * np.uint64(0x100000001B3)
    h = _mix(h ^ sizes.astype(np.uint64))
    for i in range(longer[_LONG]):
        h[i] = xxhash.xxh64_intdigest(octets[first[i] : first[i] + sizes[i]].tobytes(), 7)
    out = np.empty(n, np.uint64)
    out[order] = h
    return out


def combine(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Order-dependent hash of two hashes."""
    return _mix(left * np.uint64(0x9E3779B97F4A7C15) + right)
