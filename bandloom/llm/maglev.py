"""Sharding by a permutation-filled lookup table.

Every shard has a permutation of the slots of a prime-sized table, from two hashes of its name. Shards take turns; at
its turn a shard claims the first slot of its permutation that is still free, until the table is full. Each shard gets
size/n slots give or take one, and removing a shard moves few keys of the others. The table (a fixed number of small
rows) is broadcast, so placing a row takes one hash and one lookup, and no shuffle.

Defined results: a null key has the hash seed's value and so one fixed shard; repeated rows go to one shard; a hot key
goes to one shard by the definition of sharding by key (shard by row columns to split it); an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SLOTS = 65_537
SHARDS = tuple(f"shard-{i:02d}" for i in range(16))


def is_prime(n: int) -> bool:
    return n > 1 and all(n % d for d in range(2, int(n**0.5) + 1))


def fill(shards: tuple[str, ...] | list[str], slots: int = SLOTS) -> np.ndarray:
    """The number of the owning shard for every slot."""
    if not is_prime(slots) or len(set(shards)) != len(shards) or not 0 < len(shards) <= slots:
        raise ValueError("a prime number of slots, and at least one and at most so many distinct shards, are needed")
    names = sorted(shards)
    start = [xxhash.xxh64_intdigest(n.encode(), 1) % slots for n in names]
    step = [xxhash.xxh64_intdigest(n.encode(), 2) % (slots - 1) + 1 for n in names]
    owner, at, taken = np.full(slots, -1, np.int32), list(start), 0
    while taken < slots:
        for i in range(len(names)):
            while owner[at[i]] >= 0:
                at[i] = (at[i] + step[i]) % slots
            owner[at[i]] = i
            taken += 1
            if taken == slots:
                break
    return owner


def slot_of(key: Column, slots: int = SLOTS) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(slots)).cast("int")


def place(rows: DataFrame, key: Column, shards: tuple[str, ...] = SHARDS, slots: int = SLOTS) -> DataFrame:
    """rows with columns slot and shard (columns of these names are replaced)."""
    names, owner = sorted(shards), fill(shards, slots)
    spark = rows.sparkSession
    lookup = spark.createDataFrame([(i, names[o]) for i, o in enumerate(owner.tolist())], "slot int, shard string")
    kept = [F.col(f"`{c}`") for c in rows.columns if c not in ("slot", "shard")]
    keyed = rows.select(*kept, slot_of(key, slots).alias("slot"))  # the key may be a column of either name
    return keyed.join(F.broadcast(lookup), "slot", "left")  # at most `slots` short rows


def moved(before: DataFrame, after: DataFrame, id_column: str) -> DataFrame:
    """How many rows changed their shard between two placements."""
    both = before.select(id_column, F.col("shard").alias("old")).join(after.select(id_column, F.col("shard").alias("new")), id_column)
    return both.agg(F.count("*").alias("n_rows"), F.sum((F.col("old") != F.col("new")).cast("long")).alias("n_moved"))
