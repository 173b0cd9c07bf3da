"""Sharding by a permutation-filled lookup table (operator 4).

Each shard has its own order of preference over the slots of a table of prime size (an offset and a step from its
name). The shards take turns, each claiming the next free slot of its order, so slots are shared evenly and few slots
change hands when a shard joins or leaves. The table has a fixed size, so it is broadcast, and placing a key is one hash
and one lookup. Defined results: a null key is the key ''; repeated rows go to the same shard; an empty table gives no
rows; extra columns stay unless they are named ``slot`` or ``shard``, which are replaced.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SHARDS = 64
SLOTS = 16381  # prime, 256 slots a shard


def _number(text: str) -> int:
    return int(hashlib.md5(text.encode()).hexdigest()[:15], 16)


def fill_table(shards: list[str], slots: int = SLOTS) -> list[int]:
    """The shard (position in ``shards``) of each slot."""
    if not shards or slots < len(shards) or any(slots % p == 0 for p in range(2, int(slots**0.5) + 1)):
        raise ValueError("needs shards, and a prime number of slots not below their number")
    at = [_number(f"offset:{s}") % slots for s in shards]
    step = [_number(f"step:{s}") % (slots - 1) + 1 for s in shards]
    table, free = [-1] * slots, slots
    while free:
        for i in range(len(shards)):
            while table[at[i]] >= 0:
                at[i] = (at[i] + step[i]) % slots
            table[at[i]] = i
            free -= 1
            if not free:
                break
    return table


def shard_names(n: int = SHARDS) -> list[str]:
    return [f"shard-{i:05d}" for i in range(n)]


def lookup_frame(spark: SparkSession, shards: list[str], slots: int = SLOTS) -> DataFrame:
    """(slot, shard): ``slots`` rows."""
    table = fill_table(shards, slots)
    return spark.range(slots, numPartitions=1).select("id", F.element_at(F.lit(table), (F.col("id") + 1).cast("int")).alias("shard")).select(F.col("id").alias("slot"), F.col("shard").cast("int"))


def slot_of(key: Column, slots: int = SLOTS) -> Column:
    """60 bits of the key's MD5, modulo the table size."""
    head = F.substring(F.md5(F.coalesce(key.cast("string"), F.lit(""))), 1, 15)
    return F.pmod(F.conv(head, 16, 10).cast("long"), F.lit(slots))


def place(rows: DataFrame, key: str = "doc_id", shards: list[str] | None = None, slots: int = SLOTS) -> DataFrame:
    """``rows`` with ``slot`` and ``shard``. The broadcast table has ``slots`` rows, whatever the data."""
    table = lookup_frame(rows.sparkSession, shards or shard_names(), slots)
    kept = rows.drop("slot", "shard").withColumn("slot", slot_of(F.col(key), slots))
    return kept.join(F.broadcast(table), "slot")


def moved_share(before: list[str], after: list[str], slots: int = SLOTS) -> float:
    """Share of the slots whose shard differs between two sets of shards."""
    old, new = fill_table(before, slots), fill_table(after, slots)
    return sum(before[a] != after[b] for a, b in zip(old, new, strict=True)) / slots
