"""Saved filters, and a store of immutable runs whose filters say which runs a lookup may skip."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from bandloom.functions.hashing import SEGMENT, coefficients, fingerprint, key_hash, reduce32, reduce32_np, salted, salted_np
from bandloom.kernel.bands import Segment, contains
from bandloom.operators.build import BandFilter, build_filter, small
from bandloom.operators.probe import COMPACT_BROADCAST, Names, probe_text, relation_bytes, segments_of, start_column
from bandloom.runtime import delete, exists, ship, written
from bandloom.spec import FilterSpec


def save(flt: BandFilter, path: str) -> None:
    """meta, blocks and the spec under a path, in any store Spark can write."""
    spark = flt.meta.sparkSession
    flt.meta.write.mode("overwrite").parquet(f"{path}/meta")
    flt.blocks.write.mode("overwrite").parquet(f"{path}/blocks")
    head = {"spec": asdict(flt.spec), "segments": flt.segments, "fixed_m": flt.fixed_m, "static": flt.static, "first_column": flt.first_column, "cut": flt.cut, "by_run": flt.by_run, "parts": flt.parts, "kinds": flt.kinds}
    if flt.run_parts is not None:
        flt.run_parts.write.mode("overwrite").parquet(f"{path}/run_parts")
        head["run_parts"] = True
    spark.createDataFrame([(json.dumps(head),)], "spec string").coalesce(1).write.mode("overwrite").parquet(f"{path}/spec")


def load(spark: SparkSession, path: str) -> BandFilter:
    head = json.loads(spark.read.parquet(f"{path}/spec").first()[0])
    head["kinds"] = tuple(head["kinds"]) if head.get("kinds") else None
    head["run_parts"] = spark.read.parquet(f"{path}/run_parts") if head.pop("run_parts", False) else None
    return BandFilter(FilterSpec(**head.pop("spec")), meta=spark.read.parquet(f"{path}/meta"), blocks=spark.read.parquet(f"{path}/blocks"), **head)


def filter_dump(flt: BandFilter) -> DataFrame:
    """segment, row, column, bit of the solution, for inspection."""
    words = flt.blocks.select("segment", "block", F.posexplode("words").alias("column", "word"))
    bits = words.select("segment", "block", "column", "word", F.explode(F.sequence(F.lit(0), F.lit(63))).alias("i"))
    return bits.select("segment", (F.col("block") * 64 + F.col("i")).alias("row"), "column", F.call_function("shiftrightunsigned", "word", "i").bitwiseAND(F.lit(1).cast("long")).cast("int").alias("bit"))


def register_views(flt: BandFilter, prefix: str = "filter") -> None:
    flt.meta.createOrReplaceTempView(f"{prefix}_meta")
    flt.blocks.createOrReplaceTempView(f"{prefix}_blocks")


RUNS_PER_ROW = 256
SKIP = FilterSpec(variant="homogeneous", step=1.1)


@dataclass(frozen=True)
class RunStore:
    """Immutable runs: data partitioned by run, one filter for all of them keyed by (run, segment), and zone maps.

    path: where all of it lies, and where `shelved` keeps the runs' blocks, those of up to RUNS_PER_ROW runs of one size side
    by side, so that a key asks that many runs with one row.
    """

    data: DataFrame
    run: str
    keys: list[str]
    flt: BandFilter
    zones: DataFrame
    path: str


SIZE = ["m", "seed", "parts", "shelf"]


def write_runs(df: DataFrame, run: str, keys: list[str], path: str, spec: FilterSpec = SKIP, parts: int | None = None) -> RunStore:
    """Write df partitioned by its int run column, and each run's filter beside it."""
    spark = df.sparkSession
    delete(spark, f"{path}/shelves")  # of an earlier store at this path
    df.hint("rebalance", run).write.mode("overwrite").partitionBy(run).parquet(f"{path}/data")  # few files a run; large runs are split
    data = spark.read.parquet(f"{path}/data")
    save(build_filter(data, keys, spec, run=run, parts=parts), f"{path}/filters")
    zones = data.groupBy(run).agg(F.count("*").alias("n_rows"), F.min(keys[0]).alias("least"), F.max(keys[0]).alias("most"))
    zones.write.mode("overwrite").parquet(f"{path}/zones")
    flt, zones = load(spark, f"{path}/filters"), spark.read.parquet(f"{path}/zones")
    store = RunStore(data, run, keys, flt, zones, path)
    if relation_bytes(flt)[0] > COMPACT_BROADCAST:
        shelved(store)
    return store


def shelved(store: RunStore) -> tuple[DataFrame, DataFrame]:
    """The shelves of runs' blocks, and the sizes (m, seed, parts) and shelf numbers there are; written once beside the filters."""
    spark, flt, run, path = store.data.sparkSession, store.flt, store.run, f"{store.path}/shelves"
    if not exists(spark, f"{path}/_SUCCESS"):
        own = F.shiftright("segment", 24).cast("int")
        counted = flt.run_parts if flt.run_parts is not None else flt.meta.select(own.alias("run")).distinct().withColumn("parts", F.lit(flt.parts))
        shelf = F.pmod(F.xxhash64("run"), F.lit(max(1, -(-store.zones.count() // RUNS_PER_ROW)))).cast("int").alias("shelf")
        named = flt.meta.select("segment", "m", "seed", own.alias("run")).join(counted, "run").select("*", shelf, F.col("segment").bitwiseAND(F.lit((1 << 24) - 1).cast("long")).alias("part"))
        named = named.join(store.zones.select(F.col(run).alias("run"), "least", "most"), "run")
        piece = F.struct("run", "least", "most", "words", "next_words", "third_words").alias("piece")
        blocks = flt.blocks.select("segment", "block", "words", "next_words", "third_words").join(named, "segment")
        blocks.groupBy(*SIZE, "part", "block").agg(F.collect_list(piece).alias("pieces")).write.mode("overwrite").parquet(path)
    shelves = spark.read.parquet(path)
    return shelves, shelves.select(*SIZE).distinct()


class Piece(Names):
    """The same names, but for the words, which are those of a lambda's x."""

    def __call__(self, name: str) -> str:
        return f"x.{name}" if name.endswith("words") else super().__call__(name)


def candidate_runs(store: RunStore, wanted: DataFrame, limit: int = COMPACT_BROADCAST) -> DataFrame:
    """(keys, run) pairs that zone map and filter leave of every wanted key with every run.

    Filters of at most `limit` bytes in all (measured) are broadcast, and each batch of keys asks run after run. Beyond, a key
    meets one relation row for each size of run and shelf of RUNS_PER_ROW runs, not one for each run; the runs inside
    a row are asked there, and only those left become rows.
    """
    flt, spec, first = store.flt, store.flt.spec, store.keys[0]
    asked = wanted.select(*store.keys).distinct()
    if relation_bytes(flt)[0] <= limit:
        return ask_each_run(store, asked)
    my = Piece(asked)
    one = flt.but(by_run=False, segments=1, fixed_m=None, meta=None)
    key = my.col("key")
    shelves, classes = shelved(store)
    classes = classes.select(*[F.col(c).alias(my(c)) for c in SIZE])
    rows = asked.withColumn(my("key"), key_hash(asked, store.keys, flt.kinds)).where(key.isNotNull()).crossJoin(small(classes, 10_000))  # sizes and shelves, not runs
    low, high = coefficients(key, my.col("seed"), spec.w)
    rows = rows.withColumn(my("part"), reduce32(salted(key, SEGMENT), my.col("parts"))).withColumn(my("start"), start_column(one, my, my.col("m"), my.col("seed")))
    rows = rows.withColumn(my("block"), F.shiftright(my("start"), 6).cast("int")).withColumn(my("o"), my.col("start").bitwiseAND(F.lit(63).cast("long")).cast("int"))
    rows = rows.withColumn(my("low"), low).withColumn(my("high"), high if high is not None else F.lit(None).cast("long"))
    rows = rows.withColumn(my("fp"), F.lit(0).cast("long") if spec.variant == "homogeneous" else fingerprint(key, my.col("seed"), spec.r_hi))
    on = [*SIZE, "part", "block"]
    shelves = shelves.select(*[F.col(c).alias(my(c)) for c in on], F.col("pieces").alias(my("pieces")))
    rows = rows.join(shelves, [my(c) for c in on])
    match = f"`{first}` BETWEEN x.least AND x.most AND {probe_text(flt, my)}"
    found = F.expr(f"transform(filter({my('pieces')}, x -> {match}), x -> x.run)")
    return rows.select(*store.keys, F.explode(found).alias(store.run))


def ask_each_run(store: RunStore, asked: DataFrame) -> DataFrame:
    """candidate_runs by a broadcast of the compact filters and, for long keys, the zones."""
    spark, spec, names, n = asked.sparkSession, store.flt.spec, list(asked.columns), len(asked.columns)
    ship(spark)
    segments = segments_of(store.flt)
    runs: dict[int, dict[int, Segment]] = {}
    for s, seg in segments.items():
        runs.setdefault(s >> 24, {})[s & ((1 << 24) - 1)] = seg
    parts = {r[0]: r[1] for r in store.flt.run_parts.collect()} if store.flt.run_parts is not None else {}
    zoned = dict(asked.dtypes)[names[0]] in ("bigint", "int")
    zones = {r[0]: (r[1], r[2]) for r in store.zones.select(store.run, "least", "most").collect()} if zoned else {}
    shared = spark.sparkContext.broadcast((runs, parts, zones))
    every, run_name = store.flt.parts, store.run  # the store itself must stay out of the closure

    def ask(it):
        runs, parts, zones = shared.value
        for batch in it:
            h = batch.column(n).to_numpy()
            first = batch.column(0).to_numpy() if zoned else None
            for run, own in runs.items():
                rows = np.flatnonzero((first >= zones[run][0]) & (first <= zones[run][1])) if zoned and run in zones else np.arange(len(h))
                where = reduce32_np(salted_np(h[rows], SEGMENT), parts.get(run, every))
                hit = np.zeros(len(rows), bool)
                for part in np.unique(where).tolist():
                    if part in own:
                        mine = where == part
                        hit[mine] = contains(own[part], spec, h[rows[mine]])
                if hit.any():
                    left = batch.take(pa.array(rows[hit]))
                    yield pa.RecordBatch.from_arrays([*left.columns[:n], pa.array(np.full(int(hit.sum()), run), pa.int32())], [*names, run_name])

    hashed = asked.select(*names, key_hash(asked, store.keys, store.flt.kinds).alias("_h")).where("_h is not null")
    schema = T.StructType([*asked.schema.fields, T.StructField(store.run, T.IntegerType())])
    return hashed.mapInArrow(ask, schema)


def multi_get(store: RunStore, wanted: DataFrame) -> DataFrame:
    """The stored rows of the wanted keys, read from candidate runs only and verified exactly."""
    pairs, _ = written(candidate_runs(store, wanted), "pairs")
    return needed(store, pairs).join(pairs, [*store.keys, store.run])


def needed(store: RunStore, pairs: DataFrame, most: int = 10_000) -> DataFrame:
    """The data of the runs that some pair names: their partitions alone are listed and read, if there are at most so many."""
    runs = [r[0] for r in pairs.select(store.run).distinct().limit(most + 1).collect()]
    return store.data.where(F.col(store.run).isin(runs)) if len(runs) <= most else store.data


def skip_counts(store: RunStore, wanted: DataFrame) -> DataFrame:
    """Pairs of keys and runs in all, those left by the zones and filters, and those that really hold the key."""
    n_keys, n_runs = wanted.select(*store.keys).distinct().count(), store.zones.count()
    pairs, _ = written(candidate_runs(store, wanted), "pairs")
    real = pairs.join(store.data.select(*store.keys, store.run).distinct(), [*store.keys, store.run], "left_semi")
    left = pairs.agg(F.count("*").alias("n_candidates")).crossJoin(real.agg(F.count("*").alias("n_real")))
    return left.withColumn("n_pairs", F.lit(n_keys * n_runs).cast("long"))
