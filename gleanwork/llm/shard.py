"""Sharding by a permutation-filled lookup table.

Every shard has a preference order over the slots of a prime-sized table (an offset and a step, both hashed from its
name). Shards take turns, each claiming the first free slot of its order, until the table is full. The table is small and
its size is fixed by a parameter, so it is broadcast; a row's shard is one lookup. Adding or losing a shard moves few rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from .common import table

SHARDS = 64
SLOTS = 65537


def _prime(n: int) -> bool:
    return n > 1 and all(n % k for k in range(2, int(n**0.5) + 1))


def lookup_table(shards: list[str], slots: int = SLOTS) -> np.ndarray:
    """slots shard numbers; slots must be prime and at least the number of shards, names distinct."""
    if not _prime(slots) or slots < len(shards) or not shards or len(set(shards)) < len(shards):
        raise ValueError("slots must be a prime of at least the number of shards, and shards distinct")
    at, step = [], []
    for name in shards:
        h = hashlib.md5(name.encode()).digest()
        at.append(int.from_bytes(h[:8], "big") % slots)
        step.append(int.from_bytes(h[8:], "big") % (slots - 1) + 1 if slots > 2 else 1)
    filled, left = np.full(slots, -1, np.int32), slots
    while left:
        for k in range(len(shards)):
            while filled[at[k]] >= 0:
                at[k] = (at[k] + step[k]) % slots
            filled[at[k]] = k
            left -= 1
            if not left:
                break
    return filled


def slot_of(key: Column, slots: int = SLOTS) -> Column:
    """Slot of a key: the first 60 bits of its md5 modulo the table's size; a null key hashes as the empty string."""
    return F.pmod(F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit("")).cast("binary")), 1, 15), 16, 10).cast("bigint"), F.lit(slots))


def place(df: DataFrame, key: str = "doc_id", shards: list[str] | int = SHARDS, slots: int = SLOTS, prefix: str = "") -> DataFrame:
    """df with columns <prefix>slot (long) and <prefix>shard (int).

    Equal keys share a shard; null keys share one too; repeated rows stay; an empty table stays empty. A column of df that
    already has one of the two names is replaced (choose a prefix to keep it). The broadcast table has exactly slots rows of
    12 bytes.
    """
    names = [f"shard-{k:05d}" for k in range(shards)] if isinstance(shards, int) else list(shards)
    filled = lookup_table(names, slots)
    lookup = df.sparkSession.createDataFrame(pa.table({f"{prefix}slot": np.arange(slots, dtype=np.int64), f"{prefix}shard": filled}))
    kept = [c for c in df.columns if c.lower() not in (f"{prefix}slot".lower(), f"{prefix}shard".lower()) or c == key]
    packed = df.select(F.struct(*[df[f"`{c}`"] for c in kept]).alias("_row"), slot_of(df[f"`{key}`"], slots).alias("_slot"))
    placed = packed.join(F.broadcast(lookup.toDF("_at", "_shard")), F.col("_slot") == F.col("_at"), "left")
    return placed.select("_row.*", F.col("_slot").alias(f"{prefix}slot"), F.col("_shard").alias(f"{prefix}shard"))


def op10_shard(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return place(docs.select("doc_id")).select("doc_id", "slot", "shard")
