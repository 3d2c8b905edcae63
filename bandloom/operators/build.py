"""From a DataFrame of keys to a band filter or static function: one shuffle of 8-byte hashes, no sort.

The result is two relations, metadata (a row per segment) and blocks (a row per 64 solution rows, with the following
blocks' words beside its own, so that a query needs one row). They are written to the shared folder, so that a lost
executor costs a read, not a rebuild.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, replace
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from bandloom.functions.hashing import SEGMENT, distinct_np, key_hash, key_kinds, reduce32, salted, segment_of
from bandloom.kernel import balanced, ranges, softshards
from bandloom.kernel.banding import back_substitute
from bandloom.kernel.bands import NoSolution, Segment, build_segments, rhs_of, split_block
from bandloom.plans.planning import natural_shard, recommended_eps, rows_for, segments_for
from bandloom.runtime import ship, written
from bandloom.spec import FilterSpec

SEGMENTS_PER_TASK = 8
HEAD = 1024
META = (
    "segment long, m long, seed int, n_rows long, n_redundant long, attempts int, additions long, displacement long, "
    "split_block int, bits long, build_ns long, shards array<int>, alpha double, cuts array<long>, defer array<int>, deferred array<long>, r double, from_h long, next_first array<long>, next_size array<long>"
)
BLOCKS = "segment long, block int, n_blocks int, words array<long>, next_words array<long>, third_words array<long>"


@dataclass(frozen=True)
class BandFilter:
    """A finished filter or static function: its spec and its two relations.

    fixed_m: rows of every segment if all are alike (then no metadata is needed to probe), else None.
    first_column: result bit that the first stored column stands for (after a split by columns).
    parts: how many segments each run has, where the filter is kept by run; run_parts: (run, parts) where runs differ.
    cut: the blocks are some of the filter's only, so the compact form, which needs them all, is not made of it.
    kinds: what the key columns were compared as, so that a probe with other types is coerced like a join, or refused.
    """

    spec: FilterSpec
    segments: int
    fixed_m: int | None
    meta: DataFrame
    blocks: DataFrame
    static: bool = False
    first_column: int = 0
    by_run: bool = False
    parts: int = 1
    run_parts: DataFrame | None = None
    kinds: tuple[str, ...] | None = None
    cut: bool = False
    laid: DataFrame | None = None  # the blocks in the spec's layout, where that is not the interleaved one

    def but(self, **changes) -> BandFilter:
        return replace(self, **({"laid": None} if "blocks" in changes else {}) | changes)

    @cached_property
    def head(self) -> list | None:
        """segment, m, seed and bits of every segment, if there are at most HEAD of them; read once."""
        rows = self.meta.select("segment", "m", "seed", "bits").limit(HEAD + 1).collect()
        return rows if len(rows) <= HEAD else None


def words_array(rows: np.ndarray, widths: np.ndarray) -> pa.Array:
    """A list array of the leading `widths` words of each row."""
    keep = np.arange(rows.shape[1])[None, :] < widths[:, None]
    offsets = np.concatenate([[0], np.cumsum(widths)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(rows[keep].view(np.int64)))


def block_batch(seg: Segment, spec: FilterSpec) -> pa.RecordBatch:
    n = len(seg.words)
    pad = np.concatenate([seg.words, np.zeros((2, seg.words.shape[1]), np.uint64)])
    own = seg.own_spec(spec)
    widths = np.where(np.arange(n) < seg.split, own.r_lo, own.r_hi)
    third = words_array(pad[2 : n + 2], widths) if spec.w == 128 else pa.nulls(n, pa.list_(pa.int64()))
    columns = [pa.array(np.full(n, seg.segment), pa.int64()), pa.array(np.arange(n), pa.int32()), pa.array(np.full(n, n), pa.int32())]
    columns += [words_array(pad[:n], widths), words_array(pad[1 : n + 1], widths), third]
    return pa.RecordBatch.from_arrays(columns, ["segment", "block", "n_blocks", "words", "next_words", "third_words"])


def meta_batch(segs: list[Segment], spec: FilterSpec) -> pa.RecordBatch:
    def routing(s: Segment) -> dict[str, list]:
        if spec.variant != "balanced":
            return {"cuts": [], "next_first": [], "next_size": []}
        way = balanced.Routing(s.shards, s.alpha)
        first, size = way.following()
        return {"cuts": way.cuts.tolist(), "next_first": first.tolist(), "next_size": size.tolist()}

    rows = [
        {
            "segment": s.segment, "m": s.m, "seed": s.seed, "n_rows": s.n, "n_redundant": s.redundant, "attempts": s.attempts,
            "additions": s.additions, "displacement": s.displacement, "split_block": s.split, "bits": s.bits(spec), "build_ns": s.build_ns,
            "shards": s.shards, "alpha": s.alpha,
            "defer": s.flags.tolist(), "deferred": s.stats.get("deferred", []), "r": s.r, "from_h": s.from_h,
        }
        | routing(s)
        for s in segs
    ]
    kinds = {"int": pa.int32(), "long": pa.int64(), "double": pa.float64(), "array<int>": pa.list_(pa.int32()), "array<long>": pa.list_(pa.int64())}
    schema = pa.schema([(f.split()[0], kinds[f.split()[1]]) for f in META.split(", ")])
    return pa.RecordBatch.from_pylist(rows, schema)


def tagged(batch: pa.RecordBatch, schema: pa.Schema) -> pa.RecordBatch:
    """Both kinds of row in one schema: absent columns are null."""
    have = dict(zip(batch.schema.names, batch.columns, strict=True))
    return pa.RecordBatch.from_arrays([have.get(f.name, pa.nulls(batch.num_rows, f.type)).cast(f.type) for f in schema], schema=schema)


def both_schema() -> tuple[str, pa.Schema]:
    block_part = ", ".join(f for f in BLOCKS.split(", ") if not f.startswith("segment "))
    text = f"{META}, {block_part}"
    kinds = {"int": pa.int32(), "long": pa.int64(), "double": pa.float64(), "array<int>": pa.list_(pa.int32()), "array<long>": pa.list_(pa.int64())}
    return text, pa.schema([(f.split()[0], kinds[f.split()[1]]) for f in text.split(", ")])


def distinct_keys(keys: np.ndarray, values: np.ndarray | None) -> tuple[np.ndarray, np.ndarray | None]:
    if values is None:
        return distinct_np(keys), None
    unique, first, at = np.unique(keys, return_index=True, return_inverse=True)
    if (values[first][at] != values).any():
        raise ValueError("a key has two values: no static function can hold both")
    return unique, values[first]


def soft_segments(groups: dict[int, np.ndarray], spec: FilterSpec, values: dict[int, np.ndarray] | None) -> list[Segment]:
    """One system for each group, whose shards choose their own seeds; more rows where no choice of seeds is found."""
    out = []
    for s, keys in groups.items():
        began, shards = time.perf_counter_ns(), max(1, len(keys) // (spec.shard_rows or max(natural_shard(spec.w), 2 * spec.w)))
        for attempt in range(spec.seeds):
            m = rows_for(len(keys), (0.07 if spec.eps is None else spec.eps) * 1.3**attempt, spec.w)
            ok, bank, chosen, tried = softshards.build(keys, lambda rows, seed, keys=keys, s=s: rhs_of(keys[rows], seed, spec, values[s][rows] if values else None), m, spec.w, shards)
            if ok:
                break
        else:
            raise NoSolution(f"segment {s} had no solution in {spec.seeds} sizes")
        words = back_substitute(bank, spec.r_hi, m, spec.free)[0]
        seg = Segment(s, m, 0, len(keys), words, split_block(spec, m // 64), np.array(chosen, np.int64), [shards], attempts=tried, flag_bits=3)
        seg.words[: seg.split, spec.r_lo :] = 0
        seg.redundant, seg.build_ns = len(keys) - int(bank.used.sum()), time.perf_counter_ns() - began
        out.append(seg)
    return out


def build_filter(
    df: DataFrame, keys: list[str] | str, spec: FilterSpec = FilterSpec(), n_hint: int | None = None,
    values: Column | None = None, run: str | None = None, parts: int | None = None,
) -> BandFilter:
    """A filter of the distinct non-null keys of df (values: a static function instead).

    n_hint: number of keys, if known; else one pass counts them. run: an int column; each of its values gets a system (or
    `parts` systems; None: so many that none holds more than segment_keys rows) of its own, so that a run's filter can be
    kept, probed and dropped with the run.
    """
    spark: SparkSession = df.sparkSession
    from bandloom.operators import layouts

    ship(spark)
    if spec.sharding == "until_failure":  # short systems gain most from inflated ends
        spec = spec.but(edge=max(spec.edge, spec.w // 4))
    kinds, r_hi = key_kinds(df, keys), spec.r_hi
    key = key_hash(df, keys)
    thin = df.select(key.alias("key_h"), *([values.cast("long").alias("value")] if values is not None else []), *([F.col(run).cast("int").alias("run")] if run else [])).where("key_h is not null")
    if values is not None:
        thin = thin.where("value is not null")
    parallelism, run_parts, fixed_m, budget = spark.sparkContext.defaultParallelism, None, None, None
    if run and spec.sharding != "hash":
        raise ValueError("filters kept by run are sharded by hash")
    if run:
        thin = thin.where("run is not null")
        segments = 1
        counts, _ = written(thin.groupBy("run").agg(F.count("*").alias("n")).withColumn("parts", F.lit(parts) if parts else F.greatest(F.lit(1), F.ceil(F.col("n") / spec.segment_keys).cast("int"))), "runs")
        most, systems = counts.agg(F.max("parts"), F.sum("parts")).first()
        if parts is None and (most or 1) > 1:
            run_parts = counts.select(F.col("run").cast("int").alias("run"), "parts")
            thin = thin.join(small(run_parts), "run").withColumn("segment", run_segment(F.col("run"), F.col("key_h"), F.col("parts")))
        parts = parts or 1
        if run_parts is None:
            thin = thin.withColumn("segment", run_segment(F.col("run"), F.col("key_h"), F.lit(parts)))
        tasks = max(parallelism, -(-(systems or 1) // SEGMENTS_PER_TASK))
    else:
        parts = 1
        if n_hint is None:
            # One sketch object a task (1.6 % error); approx_count_distinct would plan over a thousand buffer columns.
            total, about = thin.agg(F.count("*"), F.hll_sketch_estimate(F.hll_sketch_agg("key_h", 12))).first()
            n_hint = min(total, int((about or 0) * 1.03) + 1)
        segments = segments_for(n_hint, spec.segment_keys)
        per = -(-n_hint // segments)
        if spec.sharding == "fixed_bytes":
            eps = recommended_eps(spec, per)
            spec, budget = spec.but(r=min(62, spec.r_hi + 3), eps=eps), 64 * max(1, round(rows_for(per, eps, spec.w) * spec.r / 64))
        elif spec.variant == "homogeneous" and values is None:
            fixed_m = rows_for(per, recommended_eps(spec, per), spec.w)
        if spec.sharding == "until_failure":
            order = salted(F.col("key_h"), ranges.RANGE)
            thin = thin.withColumn("segment", reduce32(order, segments))
        else:
            thin = thin.withColumn("segment", segment_of(F.col("key_h"), segments).cast("long"))
        tasks = min(segments, max(-(-segments // SEGMENTS_PER_TASK), parallelism))
    text, schema = both_schema()
    static, value_bits = values is not None, r_hi  # the column itself must stay out of the closures
    columns = ["segment", "key_h", *(["value"] if values is not None else [])]

    def once(it):
        """Drop repeats inside each batch before the shuffle: a hot key leaves one row per batch."""
        for batch in it:
            columns = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            order = np.lexsort(columns[::-1])
            new = np.ones(len(order), bool)
            new[1:] = False
            for c in columns:
                new[1:] |= c[order][1:] != c[order][:-1]
            yield batch.take(pa.array(order[new]))

    def build(it):
        table = pa.Table.from_batches(it, schema=None) if (it := list(it)) else None
        if table is None or not table.num_rows:
            return
        segment, key_h = table.column("segment").to_numpy(), table.column("key_h").to_numpy()
        value = table.column("value").to_numpy() if static else None
        if static and (value.view(np.uint64) >> np.uint64(value_bits)).any():
            raise ValueError(f"a value does not fit the {value_bits} bits of the static function")
        order = np.argsort(segment, kind="stable")
        cuts = np.flatnonzero(np.diff(segment[order])) + 1
        groups, own = {}, {}
        for rows in np.split(order, cuts):
            s = int(segment[rows[0]])
            groups[s], own[s] = distinct_keys(key_h[rows], value[rows] if value is not None else None)
        for at in range(0, len(names := sorted(groups)), SEGMENTS_PER_TASK):
            some = {s: groups[s] for s in names[at : at + SEGMENTS_PER_TASK]}
            held = {s: own[s] for s in some} if value is not None else None
            if spec.sharding == "until_failure":
                built = [g for s, k in some.items() for g in ranges.build(s, (-(-(s << 32) // segments) << 32) - (1 << 63), k, spec, held and held[s])]
            elif spec.sharding == "soft":
                built = soft_segments(some, spec, held)
            else:
                built = build_segments(some, spec, held, fixed_m, budget)
            yield tagged(meta_batch(built, spec), schema)
            for seg in built:
                yield tagged(block_batch(seg, spec), schema)

    schema_in = "segment long, key_h long" + (", value long" if values is not None else "")
    rows, _ = written(thin.select(*columns).mapInArrow(once, schema_in).repartition(max(1, tasks), "segment").mapInArrow(build, text), "filter")
    meta = rows.where("block is null").select(*[f.split()[0] for f in META.split(", ")])
    blocks = rows.where("block is not null").select(*[f.split()[0] for f in BLOCKS.split(", ")])
    laid = written(layouts.relation(blocks, spec.layout), spec.layout)[0] if spec.layout != "icm" and not static else None
    return BandFilter(spec, segments, fixed_m, meta, blocks, static, by_run=run is not None, parts=parts, run_parts=run_parts, kinds=kinds, laid=laid)


def small(rows: DataFrame, most: int = 100_000) -> DataFrame:
    """rows, marked for a broadcast if there are at most so many (of a few numbers each)."""
    return F.broadcast(rows) if rows.limit(most + 1).count() <= most else rows


def run_segment(run: Column, key_h: Column, parts: Column) -> Column:
    """A run's systems are numbered from run * 2^24 on."""
    return run.cast("long") * (1 << 24) + reduce32(salted(key_h, SEGMENT), parts)


def build_static(df: DataFrame, keys: list[str] | str, value: Column | str, bits: int | None = None, spec: FilterSpec | None = None, n_hint: int | None = None) -> BandFilter:
    """A static function from key to a value of `bits` bits; arbitrary (not a membership test) for other keys.

    bits: None takes as many as the largest value needs, at the cost of a pass. A value that does not fit is refused.
    """
    value = F.col(value) if isinstance(value, str) else value
    if bits is None:
        least, most = df.agg(F.min(value.cast("long")), F.max(value.cast("long"))).first()
        if (least or 0) < 0:
            raise ValueError("a static function's values are not negative")
        bits = max(1, (most or 0).bit_length())
    spec = (spec or FilterSpec(variant="standard")).but(r=bits)
    if spec.variant == "homogeneous":
        raise ValueError("a static function needs right-hand sides: use the standard or balanced variant")
    return build_filter(df, keys, spec, n_hint, values=value)
