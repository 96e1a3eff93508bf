"""Shard placement by a permutation-filled lookup table.

Each shard has its own permutation of the slots of a prime-sized table; shards
take turns claiming the next free slot they prefer, so all get nearly equal
shares, and when a shard leaves few slots of the others move.  A row's key
hashes to a slot; joining the broadcast table (its size is the prime, whatever
the data) places it.  Placement is one projection and one broadcast hash join
over native columns: no shuffle, and a hot source or key spreads by row id.

Defined results: null keys hash like the empty string; repeated keys share a
shard; an empty table gives no rows; columns of the input are kept aside from
``slot`` and ``shard``, which are replaced.
"""

from __future__ import annotations

import hashlib
import json

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SLOTS = 16381
SHARDS = tuple(f"shard-{k:03d}" for k in range(64))


def is_prime(n: int) -> bool:
    return n > 1 and all(n % k for k in range(2, int(n**0.5) + 1))


def _number(name: str, salt: str) -> int:
    return int.from_bytes(hashlib.md5(f"{salt}:{name}".encode()).digest()[:8], "big")


def lookup_table(shards: tuple[str, ...] | list[str] = SHARDS, slots: int = SLOTS) -> list[int]:
    """For each slot the index of the shard that claimed it."""
    if not shards or len(set(shards)) != len(shards):
        raise ValueError("shards need distinct names")
    if not is_prime(slots) or slots < len(shards):
        raise ValueError("the table's size must be a prime, no less than the number of shards")
    # a shard's place in turn is by name, so the order of the list doesn't matter
    turn = sorted(range(len(shards)), key=lambda i: shards[i])
    place = [_number(s, "offset") % slots for s in shards]
    step = [_number(s, "skip") % (slots - 1) + 1 if slots > 1 else 1 for s in shards]
    table, left = [-1] * slots, slots
    while left:
        for i in turn:
            while table[place[i]] >= 0:
                place[i] = (place[i] + step[i]) % slots
            table[place[i]] = i
            left -= 1
            if not left:
                break
    return table


def slot_of(key: Column, slots: int = SLOTS) -> Column:
    """The slot of a key: 60 bits of its md5, modulo the table's size."""
    return F.pmod(F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit("")).cast("binary")), 1, 15), 16, 10).cast("long"), F.lit(slots).cast("long"))


def table_frame(spark: SparkSession, shards: tuple[str, ...] | list[str] = SHARDS, slots: int = SLOTS) -> DataFrame:
    """(slot, shard_index, shard) as a frame made of two literals."""
    listed = F.from_json(F.lit(json.dumps(lookup_table(shards, slots))), "array<int>")
    names = F.from_json(F.lit(json.dumps(list(shards))), "array<string>")
    return spark.range(1).select(F.posexplode(listed).alias("slot", "shard_index")).select(F.col("slot").cast("long").alias("slot"), "shard_index", F.element_at(names, F.col("shard_index") + 1).alias("shard"))


def place(rows: DataFrame, key: str, shards: tuple[str, ...] | list[str] = SHARDS, slots: int = SLOTS) -> DataFrame:
    """``rows`` with ``slot``, ``shard_index`` and ``shard``."""
    kept = rows.drop("slot", "shard_index", "shard") if key not in ("slot", "shard_index", "shard") else rows
    return kept.withColumn("slot", slot_of(F.col(key), slots)).join(F.broadcast(table_frame(rows.sparkSession, shards, slots)), "slot")


def oracle(shards: tuple[str, ...] | list[str] = SHARDS, slots: int = SLOTS) -> str:
    """DuckDB SQL of the placement, from the same table; the table itself is tested by brute force."""
    listed = ",".join(map(str, lookup_table(shards, slots)))
    names = ",".join(f"'{s}'" for s in shards)
    return f"""
WITH hashed AS (
  SELECT doc_id, n_chars, (('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15))::BIGINT % {slots})::BIGINT AS slot FROM documents
), filled AS (SELECT [{listed}] AS claims, [{names}] AS names)
SELECT doc_id, n_chars, slot, claims[slot + 1]::INTEGER AS shard_index, names[claims[slot + 1] + 1] AS shard FROM hashed, filled
"""
