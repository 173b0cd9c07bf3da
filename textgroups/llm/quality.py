"""Quality rules as a bitmask ledger (operator 5).

Every rule is evaluated once per document; the ledger, a written table, keeps the measurements, one failure bit per rule
and the number of rules it was made with. Policies are versioned sets of rules: a verdict is a bitwise test of the
ledger, so a new policy or an ablation reads the ledger and never the texts. Defined results: a null or empty text has no words, all measures 0, and fails the word count; repeated
rows and ids are judged row by row; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from textgroups.llm.rows import keep_unmarked, text_key
from textgroups.llm.words import as_text, combine, hash_strings, let_go, slices, split_words
from textgroups.plans.storage import materialise

WINDOW = 8
#: Bytes of text measured at once, about: a worker's arrays follow it.
MEASURE_BYTES = 2 << 20
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_same_next", "n_upper", "n_letters", "n_alpha_words", "n_marks")


class Rule(NamedTuple):
    """``fails`` builds the failing condition from a function that gives the column of a measure."""

    name: str
    fails: Callable[[Callable[[str], Column]], Column]


#: The position of a rule is its bit; rules are appended, never moved, so that stored ledgers stay valid.
RULES = (
    Rule("few_words", lambda m: m("n_words") < 20),
    Rule("repeated_passages", lambda m: 100 * m("n_repeat_words") > 30 * m("n_words")),
    Rule("symbols", lambda m: 10 * m("n_symbols") > m("n_words")),
    Rule("duplicate_lines", lambda m: (m("n_lines") >= 4) & (100 * m("n_dup_lines") > 30 * m("n_lines"))),
    Rule("long_words", lambda m: m("word_chars") > 20 * m("n_words")),
    Rule("stuttering", lambda m: 5 * m("n_same_next") > m("n_words")),
    Rule("capitals", lambda m: 10 * m("n_upper") > 6 * m("n_letters")),
    Rule("few_letters", lambda m: 10 * m("n_alpha_words") < 6 * m("n_words")),
    Rule("exclamations", lambda m: 4 * m("n_marks") > m("n_words")),
)
#: Versioned policies: the rules that count. ``base`` is the published floor, ``v1`` what the pipeline uses.
POLICIES = {"base": ("few_words", "repeated_passages"), "v1": tuple(r.name for r in RULES)}


def mask_of(policy: str | tuple[str, ...]) -> int:
    names = POLICIES[policy] if isinstance(policy, str) else policy
    return sum(1 << i for i, r in enumerate(RULES) if r.name in names)


def _repeated(starts: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    """Per text, the words that lie in windows of WINDOW words which the text has twice or more."""
    n, texts = len(hashes), len(starts) - 1
    if n < WINDOW:
        return np.zeros(texts, np.int64)
    rolled = hashes
    for half in (1, 2, 4):  # windows of 2, 4, 8 words
        rolled = combine(rolled[:-half], rolled[half:])
    owner = np.repeat(np.arange(texts), np.diff(starts))
    at = np.flatnonzero(owner[: n - WINDOW + 1] == owner[WINDOW - 1 :])
    key = combine(rolled[at], owner[at].astype(np.uint64))
    order = np.argsort(key, kind="stable")
    ranked = key[order]
    same = ranked[1:] == ranked[:-1]
    twice = np.zeros(len(at), bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, at[twice], 1)
    np.add.at(edge, at[twice] + WINDOW, -1)
    covered = np.concatenate([[0], np.cumsum(np.cumsum(edge[:-1]) > 0)])
    return covered[starts[1:]] - covered[starts[:-1]]


def _per_text(starts: np.ndarray, values: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(values, dtype=np.int64)])
    return total[starts[1:]] - total[starts[:-1]]


def measure(texts: pa.Array) -> dict[str, np.ndarray]:
    """The measures of each text."""
    words = split_words(texts)
    starts, codes, distinct = words
    chars = pc.utf8_length(distinct).to_numpy(zero_copy_only=False)
    letters = pc.match_substring_regex(distinct, r"\p{L}").to_numpy(zero_copy_only=False)
    same = np.zeros(len(codes), np.int64)
    if len(codes) > 1:
        same[1:] = codes[1:] == codes[:-1]
        inner = starts[(starts > 0) & (starts < len(codes))]
        same[inner] = 0
    lists = pc.split_pattern(texts, "\n")
    flat = lists.flatten()
    line_starts = np.concatenate([[0], np.cumsum(pc.list_value_length(lists).to_numpy(zero_copy_only=False))]).astype(np.int64)
    coded = flat.dictionary_encode()
    ids, owner = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64), np.repeat(np.arange(len(texts)), np.diff(line_starts))
    real = pc.match_substring_regex(coded.dictionary, r"[^\x20\x09-\x0D]").to_numpy(zero_copy_only=False)[ids] if len(ids) else np.zeros(0, bool)
    again = np.zeros(len(ids), np.int64)
    key = owner[real] * (len(coded.dictionary) + 1) + ids[real]
    first = np.unique(key, return_index=True)[1]
    later = np.ones(len(key), np.int64)
    later[first] = 0
    again[np.flatnonzero(real)] = later
    count = lambda pattern: pc.fill_null(pc.count_substring_regex(texts, pattern), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    return {
        "n_words": np.diff(starts),
        "word_chars": _per_text(starts, chars[codes]),
        "n_symbols": count(r"[#*$%&|<>]"),
        "n_dup_lines": _per_text(line_starts, again),
        "n_repeat_words": _repeated(starts, hash_strings(distinct)[codes]),
        "n_lines": _per_text(line_starts, real.astype(np.int64)),
        "n_same_next": _per_text(starts, same),
        "n_upper": count(r"\p{Lu}"),
        "n_letters": count(r"\p{L}"),
        "n_alpha_words": _per_text(starts, letters[codes].astype(np.int64)),
        "n_marks": count("!"),
    }


def _measured(docs: DataFrame) -> DataFrame:
    """(doc_id, tx, measures): taken where the text is, without a shuffle; ``tx`` is a hash of the text."""
    rows = docs.select(F.col("doc_id").cast("long"), text_key(F.col("text")).alias("tx"), "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text", MEASURE_BYTES):
                got = measure(as_text(part.column("text")))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("tx"), *[pa.array(got[m].astype(np.int64)) for m in MEASURES]], names=["doc_id", "tx", *MEASURES])
        let_go()

    return rows.mapInArrow(run, "doc_id long, tx long, " + ", ".join(f"{m} long" for m in MEASURES))


def _failed(mask: int, of: Callable[[str], Column]) -> Column:
    bits = [F.when(r.fails(of), F.lit(1 << i)).otherwise(F.lit(0)).cast("long") for i, r in enumerate(RULES) if mask >> i & 1]
    return reduce(lambda x, y: x.bitwiseOR(y), bits, F.lit(0).cast("long"))


def ledger(docs: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, tx, measures, failed, rules): bit i of ``failed`` is set if rule i fails, of the first ``rules`` rules.

    The texts are read here and nowhere else: the ledger is written to ``path`` (to the shared folder without one) and
    what is returned reads it. A ledger of fewer rules stays valid for the policies that use none of the later ones.
    """
    rows = _measured(docs).withColumn("failed", _failed((1 << len(RULES)) - 1, F.col)).withColumn("rules", F.lit(len(RULES)))
    if path is None:
        return materialise(rows, "ledger")
    rows.write.mode("append").parquet(path)
    return docs.sparkSession.read.schema(rows.schema).parquet(path)


def _active(policy: str | tuple[str, ...]) -> int:
    """The bits that reject a document: the policy's and, always, those of the base."""
    return mask_of(policy) | mask_of("base")


def verdicts(rows: DataFrame, policy: str | tuple[str, ...] = "v1") -> DataFrame:
    """The ledger with ``base_failed`` and ``kept`` under a policy; no text is read."""
    return rows.withColumn("base_failed", F.col("failed").bitwiseAND(F.lit(mask_of("base"))) != 0).withColumn("kept", F.col("failed").bitwiseAND(F.lit(_active(policy))) == 0)


def ablations(rows: DataFrame, policy: str | tuple[str, ...] = "v1") -> DataFrame:
    """Per rule that counts under a policy: documents that fail it, that fail only it, and that would stay without it."""
    mask = _active(policy)
    by_mask = rows.groupBy(F.col("failed").bitwiseAND(F.lit(mask)).alias("mask")).agg(F.count(F.lit(1)).alias("n"))
    rules = F.array(*[F.struct(F.lit(r.name).alias("rule"), F.lit(1 << i).cast("long").alias("bit")) for i, r in enumerate(RULES) if mask >> i & 1])
    each = by_mask.select("mask", "n", F.explode(rules).alias("r")).select("mask", "n", "r.*")
    fails, only = F.col("mask").bitwiseAND(F.col("bit")) != 0, F.col("mask") == F.col("bit")
    count = lambda c: F.sum(F.when(c, F.col("n")).otherwise(0)).cast("long")
    return each.groupBy("rule").agg(count(fails).alias("failing"), count(only).alias("failing_alone"), count(only | (F.col("mask") == 0)).alias("kept_without"))


def keep_good(docs: DataFrame, policy: str | tuple[str, ...] = "v1", path: str | None = None) -> DataFrame:
    """The documents that a policy keeps, with their own columns; the verdict is read from the ledger."""
    rejected = verdicts(ledger(docs, path), policy).filter("not kept").select(F.col("doc_id").alias("id"), "tx").distinct()
    return keep_unmarked(docs, materialise(rejected.withColumn("stays", F.lit(False)), "rejected"))
