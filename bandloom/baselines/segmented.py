"""Any baseline family on Spark: one structure per hash segment, built in its segment's task, probed beside its keys."""

from __future__ import annotations

import pickle
import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandloom.baselines import families
from bandloom.functions.hashing import distinct_np, key_hash, key_kinds, segment_np, segment_of
from bandloom.operators.build import SEGMENTS_PER_TASK
from bandloom.operators.probe import Names, in_bulk, others
from bandloom.plans.planning import segments_for
from bandloom.runtime import ship, written

STRUCTURES = "segment int, payload binary, n long, bits double, build_ns long"
BROADCAST_BYTES = 64 << 20


@dataclass(frozen=True)
class SegmentedFilter:
    family: str
    segments: int
    structures: DataFrame
    kinds: tuple[str, ...] | None = None


class Opened:
    """The structures of a filter in one process, unpickled once, and the segment of each key."""

    def __init__(self, segments: int, payloads: dict[int, bytes]):
        self.segments, self.held = segments, {s: pickle.loads(p) for s, p in payloads.items()}

    def contains(self, h: np.ndarray) -> np.ndarray:
        where, got = segment_np(h, self.segments), np.zeros(len(h), bool)
        order = np.argsort(where, kind="stable")
        for rows in np.split(order, np.flatnonzero(np.diff(where[order])) + 1):
            if len(rows) and (made := self.held.get(int(where[rows[0]]))):
                got[rows] = made.contains(h[rows])
        return got


def build(df: DataFrame, keys: list[str] | str, family: str, segment_keys: int = 1 << 16, n_hint: int | None = None, **params) -> SegmentedFilter:
    """A filter of a family named in families.NAMES over the distinct non-null keys; one shuffle of 8-byte hashes."""
    spark = df.sparkSession
    ship(spark)
    thin = df.select(key_hash(df, keys).alias("key_h")).where("key_h is not null")
    segments = segments_for(thin.count() if n_hint is None else n_hint, segment_keys)
    tasks = max(1, min(segments, max(-(-segments // SEGMENTS_PER_TASK), spark.sparkContext.defaultParallelism)))

    def once(it):
        for batch in it:
            _, first = np.unique(batch.column(1).to_numpy(), return_index=True)
            yield batch.take(pa.array(first))

    def make(it):
        batches = list(it)
        if not batches:
            return
        table = pa.Table.from_batches(batches)
        segment, key_h = table.column(0).to_numpy(), table.column(1).to_numpy()
        order = np.argsort(segment, kind="stable")
        for rows in np.split(order, np.flatnonzero(np.diff(segment[order])) + 1) if len(order) else []:
            own = distinct_np(key_h[rows])
            began = time.perf_counter_ns()
            made = families.build(family, own, **params)
            spent = time.perf_counter_ns() - began
            yield pa.RecordBatch.from_arrays(
                [pa.array([int(segment[rows[0]])], pa.int32()), pa.array([pickle.dumps(made)], pa.binary()), pa.array([len(own)]), pa.array([float(made.bits)]), pa.array([spent])],
                ["segment", "payload", "n", "bits", "build_ns"],
            )

    dealt = thin.withColumn("segment", segment_of(F.col("key_h"), segments)).select("segment", "key_h")
    rows, _ = written(dealt.mapInArrow(once, "segment int, key_h long").repartition(tasks, "segment").mapInArrow(make, STRUCTURES), family)
    return SegmentedFilter(family, segments, rows, key_kinds(df, keys))


def probe(df: DataFrame, flt: SegmentedFilter, keys: list[str] | str, out: str = "maybe", limit: int = BROADCAST_BYTES) -> DataFrame:
    """df with a boolean. Small filters are broadcast after a size check; large ones meet their keys by segment."""
    spark = df.sparkSession
    ship(spark)
    size = flt.structures.agg(F.coalesce(F.sum(F.octet_length("payload")), F.lit(0))).first()[0]
    my = Names(df)
    hashed = df.withColumn(my("key"), key_hash(df, keys, flt.kinds))
    if size <= limit:
        shared = spark.sparkContext.broadcast(Opened(flt.segments, {r.segment: bytes(r.payload) for r in flt.structures.select("segment", "payload").collect()}))

        @F.pandas_udf("boolean")
        def member(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
            return in_bulk(shared.value.contains, batches)

        maybe = F.when(my.col("key").isNotNull(), member(F.coalesce(my.col("key"), F.lit(0).cast("long")))).otherwise(F.lit(False))
        return hashed.select(*others(df, out), maybe.alias(out))
    # Distinct key hashes meet their structure, so a hot key is one row; the answer joins back by hash.
    asked = hashed.where(my.col("key").isNotNull()).select(segment_of(my.col("key"), flt.segments).alias("segment"), my.col("key").alias("key_h")).distinct()

    def answer(_, left, right):
        h = left.column("key_h").to_numpy()
        got = pickle.loads(right.column("payload")[0].as_py()).contains(h) if right.num_rows else np.zeros(len(h), bool)
        return pa.table({"key_h": pa.array(h), "hit": pa.array(got)})

    answered = asked.groupBy("segment").cogroup(flt.structures.groupBy("segment")).applyInArrow(answer, "key_h long, hit boolean")
    answered = answered.select(F.col("key_h").alias(my("key")), F.col("hit").alias(my("hit")))
    return hashed.join(answered, my("key"), "left").select(*others(df, out), F.coalesce(my.col("hit"), F.lit(False)).alias(out))
