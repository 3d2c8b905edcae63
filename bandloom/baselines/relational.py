"""Bloom filters as relations, built by bit_or aggregation and probed by equi-joins; mergeable, and JVM only.

A filter of at most BROADCAST_BITS bits is probed against a broadcast bitmap instead, without a shuffle.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bandloom.functions.hashing import key_hash
from bandloom.operators.probe import RELATION_BROADCAST, Names, others

BROADCAST_BITS = 1 << 26
LOW = (1 << 56) - 1


@dataclass(frozen=True)
class BloomRelation:
    """words: (word, bits) rows. size: bits in all; k: probes; h1, h2: how the two hashes follow from a key column."""

    words: DataFrame
    size: int
    k: int


def digest_hashes(df: DataFrame, key: str, seed: int = 0) -> tuple[Column, Column]:
    """Two numbers below 2^32 from the portable digest."""
    h = F.md5(F.concat(F.lit(f"{seed}:"), F.col(f"`{key}`").cast("string")))
    return F.conv(F.substring(h, 1, 8), 16, 10).cast("long"), F.conv(F.substring(h, 9, 8), 16, 10).cast("long")


def fast_hashes(df: DataFrame, key: str, seed: int = 0) -> tuple[Column, Column]:
    """Two numbers below 2^56, so that positions reach every bit of any filter."""
    h = key_hash(df, key)
    return tuple(F.xxhash64(h, F.lit(2 * seed + i).cast("long")).bitwiseAND(F.lit(LOW).cast("long")) for i in (0, 1))


def positions(h1: Column, h2: Column, k: int, size: int) -> Column:
    """k bit positions by double hashing; h1 + i * h2 stays below 2^63 for k up to 64."""
    return F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda i: F.pmod(h1 + i.cast("long") * h2.bitwiseOR(F.lit(1).cast("long")), F.lit(size).cast("long")))


def one_bit(place: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), place.bitwiseAND(F.lit(63).cast("long")).cast("int"))


def build_bloom(df: DataFrame, key: str, size: int, k: int, hashes=fast_hashes) -> BloomRelation:
    h1, h2 = hashes(df, key)
    bits = df.where(F.col(f"`{key}`").isNotNull()).select(F.explode(positions(h1, h2, k, size)).alias("p"))
    words = bits.groupBy(F.shiftright("p", 6).alias("word")).agg(F.bit_or(one_bit(F.col("p"))).alias("bits"))
    return BloomRelation(words, size, k)


def merge(a: BloomRelation, b: BloomRelation) -> BloomRelation:
    if (a.size, a.k) != (b.size, b.k):
        raise ValueError("only filters of one size and probe count merge")
    return BloomRelation(a.words.unionByName(b.words).groupBy("word").agg(F.bit_or("bits").alias("bits")), a.size, a.k)


def probe_bloom(df: DataFrame, flt: BloomRelation, key: str, out: str = "maybe", hashes=fast_hashes, limit: int = BROADCAST_BITS) -> DataFrame:
    """df with a boolean. Beyond the limit distinct keys are probed once: explode, join by word, and all k bits must be set."""
    h1, h2 = hashes(df, key)
    my, known = Names(df), F.col(f"`{key}`").isNotNull()
    if flt.size <= limit:
        rows = flt.words.toArrow()
        bitmap = np.zeros(-(-flt.size // 64), np.uint64)
        bitmap[rows.column("word").to_numpy()] = rows.column("bits").to_numpy().view(np.uint64)
        shared, size, k = df.sparkSession.sparkContext.broadcast(bitmap), flt.size, flt.k

        @F.pandas_udf("boolean")
        def member(first: pd.Series, step: pd.Series) -> pd.Series:
            a, b, got = first.to_numpy(), step.to_numpy() | 1, np.ones(len(first), bool)
            for i in range(k):
                p = (a + i * b) % size
                got &= (shared.value[p >> 6] >> (p & 63).astype(np.uint64)) & np.uint64(1) > 0
            return pd.Series(got)

        none = F.lit(0).cast("long")
        return df.select(*others(df, out), F.when(known, member(F.coalesce(h1, none), F.coalesce(h2, none))).otherwise(F.lit(False)).alias(out))
    asked = df.select(F.col(f"`{key}`").alias("key"), h1.alias("h1"), h2.alias("h2")).where("key is not null").distinct()
    probes = asked.select("key", F.explode(positions(F.col("h1"), F.col("h2"), flt.k, flt.size)).alias("p")).withColumn("word", F.shiftright("p", 6))
    hit = F.coalesce("bits", F.lit(0).cast("long")).bitwiseAND(one_bit(F.col("p"))) != 0
    answer = probes.join(flt.words, "word", "left").groupBy(F.col("key").alias(my("key"))).agg(F.min(hit).alias(my("hit")))
    return df.join(answer, F.col(f"`{key}`") == my.col("key"), "left").select(*others(df, out), F.coalesce(my.col("hit"), F.lit(False)).alias(out))


def block_words(h1: Column, h2: Column, blocks: int) -> tuple[Column, list[Column]]:
    """The block, and one bit in each of its eight 64-bit words."""
    block = F.pmod(h1, F.lit(blocks).cast("long"))
    return block, [one_bit(F.pmod(F.shiftright(h2, 3 * i) + F.lit(i).cast("long") * h1, F.lit(64).cast("long"))) for i in range(8)]


def build_blocked_bloom(df: DataFrame, key: str, blocks: int, hashes=fast_hashes) -> DataFrame:
    """(block, w0..w7): one shuffle with partial bit_or, no Python."""
    block, bits = block_words(*hashes(df, key), blocks)
    return df.where(F.col(f"`{key}`").isNotNull()).select(block.alias("block"), *[b.alias(f"w{i}") for i, b in enumerate(bits)]).groupBy("block").agg(*[F.bit_or(f"w{i}").alias(f"w{i}") for i in range(8)])


def probe_blocked_bloom(df: DataFrame, words: DataFrame, key: str, blocks: int, out: str = "maybe", hashes=fast_hashes) -> DataFrame:
    """One equi-join by block and eight bit tests; the words (72 bytes a block) are broadcast while they are small."""
    block, bits = block_words(*hashes(df, key), blocks)
    my = Names(df)
    own = words.select(*[F.col(c).alias(my(c)) for c in ("block", *(f"w{i}" for i in range(8)))])
    rows = df.withColumn(my("block"), block).join(F.broadcast(own) if blocks * 72 <= RELATION_BROADCAST else own, my("block"), "left")
    test = F.lit(True)
    for i, b in enumerate(bits):
        test = test & (my.col(f"w{i}").bitwiseAND(b) != 0)
    return rows.select(*others(df, out), (F.coalesce(test, F.lit(False)) & F.col(f"`{key}`").isNotNull()).alias(out))


def exact_semi(df: DataFrame, members: DataFrame, key: str, member_key: str) -> DataFrame:
    return df.join(members.select(F.col(member_key).alias(key)), key, "left_semi")
