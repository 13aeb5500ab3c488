"""Sharding by a permutation-filled lookup table.

Every shard has its own permutation of the slots of a prime-sized table (an offset and a step
from two hashes of its name).  Shards take turns, each claiming the next free slot of its
permutation, until the table is full: shares differ by at most one slot, and adding or removing a shard moves few
others.  A row's hash picks a slot; the table is broadcast, so placement is one lookup.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def is_prime(n: int) -> bool:
    return n > 1 and all(n % k for k in range(2, int(n**0.5) + 1))


def _hash(name: str, salt: bytes) -> int:
    return int.from_bytes(hashlib.blake2b(name.encode(), digest_size=8, key=salt).digest(), "little")


def fill_table(shards: list[str], size: int = 65_537) -> np.ndarray:
    """For every slot the number of its shard in ``shards``.

    Names decide, not their order: shards take turns by name.  size is a prime of at least the number of shards.
    """
    if not is_prime(size):
        raise ValueError("the table size must be a prime")
    if len(set(shards)) != len(shards) or not 0 < len(shards) <= size:
        raise ValueError("between one shard and one for each slot, all of different names")
    order = sorted(range(len(shards)), key=lambda i: shards[i])
    offset = [_hash(shards[i], b"offset") % size for i in order]
    step = [_hash(shards[i], b"step") % (size - 1) + 1 if size > 2 else 1 for i in order]
    table = np.full(size, -1, np.int64)
    owner, at, left = table.tolist(), [0] * len(order), size
    while left:
        for j, i in enumerate(order):
            slot = (offset[j] + at[j] * step[j]) % size
            while owner[slot] >= 0:
                at[j] += 1
                slot = (offset[j] + at[j] * step[j]) % size
            owner[slot] = i
            at[j] += 1
            left -= 1
            if not left:
                break
    return np.array(owner, np.int64)


def slot_of(keys: list[str], size: int):
    """A slot from a hash of the key columns; rows whose keys are all null are dealt by nothing but the seed and
    should bring a further column."""
    return F.pmod(F.xxhash64(*keys), F.lit(size)).cast("long")


def place(df: DataFrame, shards: list[str], keys: list[str], size: int = 65_537) -> DataFrame:
    """df with slot and shard (name).  The lookup table has ``size`` rows whatever df is, and is broadcast.

    Equal keys share a shard; null keys hash like any value; an empty table gives no rows; columns of these names are replaced.
    """
    owner = fill_table(shards, size)
    spark = df.sparkSession
    table = spark.createDataFrame([(i, shards[j]) for i, j in enumerate(owner.tolist())], "slot long, shard string")
    base = df.drop("slot", "shard").withColumn("slot", slot_of(keys, size))
    return base.join(F.broadcast(table), "slot").select(*[c for c in base.columns if c != "slot"], "slot", "shard")


def write_shards(df: DataFrame, path: str, shards: list[str], keys: list[str], files_each: int = 1, size: int = 65_537) -> None:
    """One folder for each shard; a shard's rows are dealt over ``files_each`` tasks, so none gathers a whole shard."""
    placed = place(df, shards, keys, size).withColumn("__part", F.pmod(F.xxhash64(*keys, F.lit(1)), F.lit(files_each)))
    placed.repartition(len(shards) * files_each, "shard", "__part").drop("__part", "slot").write.partitionBy("shard").parquet(path)
