"""Streams: probing a static filter, windowed counts, runs closed per window, late rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bandloom.operators.build import BandFilter, build_filter
from bandloom.operators.probe import probe
from bandloom.spec import FilterSpec


def read_events(spark: SparkSession, folder: str, schema) -> DataFrame:
    """A parquet folder as a stream, with event time as a timestamp that watermarks accept."""
    return spark.readStream.schema(schema).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def probe_stream(stream: DataFrame, flt: BandFilter, keys: list[str], out: str = "maybe") -> DataFrame:
    """Each micro-batch meets the static filter in the way its measured size allows; nothing is kept as state."""
    return probe(stream, flt, keys, out)


def window_counts(rows: DataFrame, size: str, flag: str = "maybe", late: str = "1 day", slide: str | None = None) -> DataFrame:
    """Rows and probable members per tumbling (or, with a slide, sliding) window, batch or stream."""
    timed = rows.withWatermark("ts", late) if rows.isStreaming else rows
    windows = F.window("ts", size, slide) if slide else F.window("ts", size)
    return timed.groupBy(windows.alias("w")).agg(F.count("*").alias("n"), F.sum(F.col(flag).cast("long")).alias("n_maybe")).select(F.col("w.start").alias("window_start"), "n", "n_maybe")


def sessions(rows: DataFrame, key: str, gap: str, late: str = "1 day") -> DataFrame:
    timed = rows.withWatermark("ts", late) if rows.isStreaming else rows
    return timed.groupBy(key, F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select(key, F.col("w.start").alias("session_start"), F.col("w.end").alias("session_end"), "n")


def first_in_watermark(stream: DataFrame, keys: list[str], late: str) -> DataFrame:
    """Repeats within the watermark dropped."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys) if stream.isStreaming else stream.dropDuplicates(keys)


def close_runs(stream: DataFrame, keys: list[str], path: str, spec: FilterSpec = FilterSpec(), on_run: Callable[[int, BandFilter], None] | None = None):
    """A foreachBatch writer: each micro-batch becomes an immutable run of rows with a filter of its own.

    Filters do not merge; growth means more runs, and compaction rebuilds from the runs' keys. A batch that is retried
    overwrites its own run, so the sink is idempotent.
    """
    from bandloom.sources.catalog import save

    def write(batch: DataFrame, number: int) -> None:
        rows = batch.persist()
        try:
            rows.write.mode("overwrite").parquet(f"{path}/data/run={number}")
            flt = build_filter(rows, keys, spec)
            save(flt, f"{path}/filters/run={number}")
            if on_run:
                on_run(number, flt)
        finally:
            rows.unpersist()

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", f"{path}/checkpoint")


def compact(spark: SparkSession, path: str, keys: list[str], spec: FilterSpec = FilterSpec()) -> BandFilter:
    """One filter over all closed runs."""
    return build_filter(spark.read.parquet(f"{path}/data"), keys, spec)


def split_late(rows: DataFrame, closed_until) -> tuple[DataFrame, DataFrame]:
    """Rows of open windows, and rows that come after their run was closed (for an exact overflow set)."""
    return rows.where(F.col("ts") >= F.lit(closed_until)), rows.where(F.col("ts") < F.lit(closed_until))


PREFIX_STATE = "keys array<long>, run int"
PREFIX_OUT = "shard int, run int, n_keys long, m long, closed boolean, version long, keys array<long>, words binary"


def prefix_runs(stream: DataFrame, keys: list[str], shards: int, spec: FilterSpec = FilterSpec(variant="standard", edge=16), rows: int | None = None):
    """Grow a run per shard until it no longer fits its rows, then emit it and start the next with the keys left.

    The prefix that fits is found by elimination itself, not by a count. A closed run is emitted once, with its solution (`words`,
    64-bit words by block and column), which is all that a probe needs; the open run is emitted after every batch with its
    keys, as the newest `version` of it: together they hold every key seen. State per shard is at most the keys of one
    open run (fewer than its rows), so it is bounded, and so is an output row.
    """
    import numpy as np
    import pandas as pd

    from bandloom.functions.hashing import START, clamp_start_np, coefficients_np, fingerprint_np, key_hash, salted_np, segment_of
    from bandloom.kernel import ranges
    from bandloom.kernel.banding import back_substitute, band_until_failure
    from bandloom.runtime import ship

    ship(stream.sparkSession)
    m, w = rows or ranges.shard_rows(spec), spec.w

    def fit(own: np.ndarray) -> tuple[int, bytes]:
        start = clamp_start_np(salted_np(own, START), m - w + 1, spec.edge)
        bank, n = band_until_failure(m, start, coefficients_np(own, 0, w), fingerprint_np(own, 0, spec.r_hi), int(0.9 * m))
        return n, back_substitute(bank, spec.r_hi, m, spec.free).astype("<u8").tobytes() if n < len(own) else b""

    def grow(shard, frames, state):
        held, run = (list(state.get[0]), state.get[1]) if state.exists else ([], 0)
        out = []
        for pdf in frames:
            seen = set(held)
            held += [k for k in pdf["key_h"].tolist() if not (k in seen or seen.add(k))]
            while len(held) >= m * 0.9:
                n, words = fit(np.array(held[: m + w], np.int64))
                if n == len(held):
                    break
                out.append((shard[0], run, n, m, True, 0, None, words))
                held, run = held[n:], run + 1
        state.update((held, run))
        out.append((shard[0], run, len(held), m, False, len(held), held, None))
        yield pd.DataFrame(out, columns=[f.split()[0] for f in PREFIX_OUT.split(", ")])

    hashed = stream.select(key_hash(stream, keys).alias("key_h")).where("key_h is not null")
    return hashed.withColumn("shard", segment_of(F.col("key_h"), shards)).groupBy("shard").applyInPandasWithState(grow, PREFIX_OUT, PREFIX_STATE, "append", "NoTimeout")


def probe_prefix_runs(df: DataFrame, keys: list[str], runs: DataFrame, shards: int, spec: FilterSpec = FilterSpec(variant="standard", edge=16), out: str = "maybe") -> DataFrame:
    """df with a boolean from the emitted runs: a key asks every closed run of its shard, and the open one's keys.

    Each asked key meets its shard's runs in one task; keys are asked once each, in pieces of a shard, so no task holds more
    than a piece of the keys and one shard's runs. All runs of a size are asked together, 64 in a word.
    """
    import numpy as np
    import pyarrow as pa

    from bandloom.functions.hashing import START, clamp_start_np, coefficients_np, fingerprint_np, key_hash, salted_np, segment_of
    from bandloom.kernel.banding import any_matches
    from bandloom.operators.probe import Names, others
    from bandloom.runtime import ship

    ship(df.sparkSession)
    my, w, r = Names(df), spec.w, spec.r_hi
    hashed = df.withColumn(my("key"), key_hash(df, keys))
    asked = hashed.select(my.col("key").alias("key_h")).where("key_h is not null").distinct()
    pieces = asked.select(segment_of(F.col("key_h"), shards).alias("shard"), F.pmod(F.xxhash64("key_h", F.lit(5)), F.lit(16)).cast("int").alias("piece"), "key_h")
    every = runs.withColumn("piece", F.explode(F.sequence(F.lit(0), F.lit(15))))

    def answer(_, left, right):
        h = left.column("key_h").to_numpy()
        got, newest, closed = np.zeros(len(h), bool), (-1, -1, None), {}
        for run in right.to_pylist():
            if not run["closed"]:
                newest = max(newest, (run["run"], run["version"], run["keys"]), key=lambda x: x[:2])
                continue
            closed.setdefault(run["m"], []).append(np.frombuffer(run["words"], "<u8").reshape(-1, r))
        for m, words in closed.items():
            start = clamp_start_np(salted_np(h, START), m - w + 1, spec.edge)
            got |= any_matches(np.stack(words), start, coefficients_np(h, 0, w), fingerprint_np(h, 0, r))
        if newest[2]:
            got |= np.isin(h, np.array(newest[2], np.int64))
        return pa.table({"key_h": pa.array(h), "hit": pa.array(got)})

    answered = pieces.groupBy("shard", "piece").cogroup(every.groupBy("shard", "piece")).applyInArrow(answer, "key_h long, hit boolean")
    answered = answered.select(F.col("key_h").alias(my("key")), F.col("hit").alias(my("hit")))
    return hashed.join(answered, my("key"), "left").select(*others(df, out), F.coalesce(my.col("hit"), F.lit(False)).alias(out))
