"""Shard placement (operator 7): a permutation-filled lookup table of prime size.

Shards take turns; each claims the next free slot of its own permutation of the slots, until none is free. A key's slot
is its hash modulo the table size, so placement is one lookup in a broadcast table. Removing or adding a shard moves few
keys. The table has ``slots`` rows whatever the data's size, which bounds the broadcast; filling it is the only driver work.

Defined results: a null key goes to the slot of the empty string; equal keys always share a shard; an empty input gives no
rows. All columns pass through; the result adds ``slot`` and ``shard``. An input column of either name (the key may be one)
passes through as ``slot_in`` or ``shard_in``, with further ``_in`` until the name is free.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Prime, and about 100 slots a shard, which keeps shard sizes within about one per cent.
SLOTS = 6553
SHARDS = 64
MAX_SLOTS = 1_000_003


def is_prime(n: int) -> bool:
    return n > 1 and all(n % d for d in range(2, int(n**0.5) + 1))


def _digest(name: str, salt: str) -> int:
    return int.from_bytes(hashlib.md5(f"{salt}:{name}".encode()).digest()[:8], "big")


def fill(shards: list[str], slots: int = SLOTS) -> list[int]:
    """The shard number that owns each slot."""
    if not shards or not is_prime(slots) or len(shards) > slots or slots > MAX_SLOTS:
        raise ValueError("needs a prime number of slots within MAX_SLOTS, and 1 to that many shards")
    start = [_digest(s, "start") % slots for s in shards]
    step = [_digest(s, "step") % (slots - 1) + 1 if slots > 2 else 1 for s in shards]
    owner, turn, left = [-1] * slots, [0] * len(shards), slots
    while left:
        for k in range(len(shards)):
            while owner[spot := (start[k] + turn[k] * step[k]) % slots] >= 0:
                turn[k] += 1
            owner[spot] = k
            left -= 1
            if not left:
                break
    return owner


def shard_names(n: int = SHARDS) -> list[str]:
    return [f"shard-{k:05d}" for k in range(n)]


def slot_of(key: Column, slots: int) -> Column:
    """First 60 bits of the key's MD5, modulo the table size."""
    head = F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit("")).cast("binary")), 1, 15), 16, 10)
    return head.cast("long") % slots


def lookup(spark: SparkSession, shards: list[str], slots: int = SLOTS) -> DataFrame:
    owner = fill(shards, slots)
    return spark.range(1).select(F.posexplode(F.split(F.lit(",".join(map(str, owner))), ",")).alias("slot", "shard")).select(
        F.col("slot").cast("long"), F.col("shard").cast("long")
    )


def place(df: DataFrame, key: str = "doc_id", shards: list[str] | None = None, slots: int = SLOTS) -> DataFrame:
    """``df`` with its slot and shard: one broadcast hash join, no shuffle."""
    shards = shards or shard_names()
    names: list[str] = []
    for c in df.columns:
        own = c
        if c in ("slot", "shard"):
            own += "_in"
            while own in df.columns or own in names:
                own += "_in"
        names.append(own)
    keyed = df.select(*(F.col(f"`{c}`").alias(n) for c, n in zip(df.columns, names)), slot_of(F.col(f"`{key}`"), slots).alias("slot"))
    return keyed.join(F.broadcast(lookup(df.sparkSession, shards, slots)), "slot", "left").select(*(F.col(f"`{n}`") for n in names), "slot", "shard")
