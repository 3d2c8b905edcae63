"""Experiments on the keys of a table: a grid of configurations, each built and measured on every segment of the keys.

Key hashes are dealt to segments of bounded size, a task builds every configuration on a few segments in lock-step, and sums
over the segments give a configuration's rate, space, times and counters. Any number of keys takes part; what is held at once
is a task's few segments. The paper's keys are random, so its own sizes are reached with `synthetic`.
"""

from __future__ import annotations

import math
import time

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from bandloom.baselines import families
from bandloom.functions.hashing import START, clamp_start_np, coefficients_np, distinct_np, fingerprint_np, key_hash, salted_np, segment_np
from bandloom.kernel import ranges
from bandloom.kernel.banding import Bank
from bandloom.kernel.bands import NoSolution, build_segments, contains, contains_ranges
from bandloom.plans.planning import recommended_eps, rows_for, segments_for
from bandloom.runtime import ship, written
from bandloom.spec import FilterSpec

SUMS = ("n", "bits", "build_ns", "asked", "positive_ns", "negative_ns", "mixed_asked", "mixed_ns", "probes", "hits", "misses", "failed", "attempts", "redundant", "additions", "displacement", "metadata_bits",
        "deferred_1", "tier_1", "rounds", "sorted_steps", "sorted_additions", "same_rows", "shards", "rows", "trials", "rate_sum", "rate_squares")
GRID = (("filter", "string"), ("w", "int"), ("r", "double"), ("eps", "double"), ("edge", "int"), ("retry", "string"), ("sharding", "string"), ("params", "string"))


def random_keys(n: int, seed: int) -> np.ndarray:
    return distinct_np(np.random.default_rng(seed).integers(-(2**63), 2**63 - 1, n, dtype=np.int64))


def spec_of(cfg: dict) -> FilterSpec:
    keep = {k: cfg[k] for k in ("variant", "w", "r", "eps", "edge", "retry", "free_rule", "seeds", "alpha", "sharding", "shard_rows") if cfg.get(k) is not None}
    return FilterSpec(**keep)


def timed(action, keys: np.ndarray) -> tuple[int, np.ndarray]:
    began = time.perf_counter_ns()
    out = action(keys)
    return time.perf_counter_ns() - began, out


class Others:
    """Keys outside a segment and mixes of both, drawn once for all configurations that ask for as many."""

    def __init__(self, keys: np.ndarray, segment: int):
        self.keys, self.segment, self.held = keys, segment, {}

    def __call__(self, cfg: dict) -> tuple[np.ndarray, np.ndarray]:
        n, rep = cfg.get("probes") or max(20_000, len(self.keys)), cfg.get("rep", 0)
        if (n, rep) not in self.held:
            self.held = {k: v for k, v in self.held.items() if k[1] == rep}
            fresh = random_keys(n, 10_000_019 + 7919 * self.segment + rep)
            half = min(len(self.keys), len(fresh))
            self.held[n, rep] = fresh, np.random.default_rng(3).permutation(np.concatenate([self.keys[:half], fresh[:half]]))
        return self.held[n, rep]


ASKED = 1 << 15  # keys that a filter is asked at once, so that what it computes for them stays in the processor's cache


def in_pieces(ask, keys: np.ndarray) -> np.ndarray:
    out = np.empty(len(keys), bool)
    for at in range(0, len(keys), ASKED):
        out[at : at + ASKED] = ask(keys[at : at + ASKED])
    return out


def asked(cfg: dict, ask, others: Others) -> dict:
    """Query times on members, on others and on a mix, misses and hits."""
    fresh, mixed = others(cfg)
    ask_all = lambda keys: in_pieces(ask, keys)
    pos, hit = timed(ask_all, others.keys)
    neg, got = timed(ask_all, fresh)
    mix, _ = timed(ask_all, mixed)
    return {"asked": len(others.keys), "positive_ns": pos, "negative_ns": neg, "mixed_asked": len(mixed), "mixed_ns": mix, "probes": len(fresh), "hits": int(got.sum()), "misses": int((~hit).sum())}


def band_systems(spec: FilterSpec, held: dict[int, np.ndarray], per: int) -> tuple[dict[int, list], FilterSpec]:
    """The systems of each segment, all segments in lock-step; a segment has several where a shard ends at the first failure."""
    if spec.sharding == "until_failure":
        return ranges.build_many({s: (-(1 << 63), keys) for s, keys in held.items()}, spec), spec
    if spec.sharding == "soft":
        from bandloom.operators.build import soft_segments

        return {g.segment: [g] for g in soft_segments(held, spec, None)}, spec
    if spec.sharding == "fixed_bytes":
        eps = recommended_eps(spec, per)
        wide = spec.but(r=min(62, spec.r_hi + 3), eps=eps)
        return {g.segment: [g] for g in build_segments(held, wide, budget=64 * round(rows_for(per, eps, spec.w) * spec.r / 64))}, wide
    return {g.segment: [g] for g in build_segments(held, spec)}, spec


def band_structures(cfg: dict, held: dict[int, np.ndarray], per: int = 0) -> dict[int, tuple]:
    """Scores of the build and the query function of each segment; (scores, None) where there is no solution."""
    began = time.perf_counter_ns()
    try:
        made, spec = band_systems(spec_of(cfg), held, per)
    except NoSolution:
        if len(held) == 1:
            return {s: ({"n": len(keys), "failed": 1}, None) for s, keys in held.items()}
        return {s: one for k, keys in held.items() for s, one in band_structures(cfg, {k: keys}, per).items()}
    spent = (time.perf_counter_ns() - began) / max(1, sum(len(k) for k in held.values()))

    def score(built: list, n: int) -> dict:
        first = built[0].stats
        return {
            "n": n, "bits": sum(s.bits(spec) for s in built), "build_ns": spent * n, "attempts": sum(s.attempts for s in built), "redundant": sum(s.redundant for s in built), "additions": sum(s.additions for s in built),
            "displacement": sum(s.displacement for s in built), "metadata_bits": sum(s.flag_bits * len(s.flags) for s in built), "shards": sum(max(1, len(s.flags)) for s in built), "rows": sum(s.m for s in built),
            "deferred_1": first["deferred"][0] if first.get("deferred") else 0, "tier_1": first["tier_keys"][0] if first.get("deferred") else 0,
        }

    def asker(built: list):
        if len(built) == 1:
            return lambda k: contains(built[0], spec, k)
        return lambda k: contains_ranges(built, spec, k)

    return {s: (score(made[s], len(keys)), asker(made[s])) for s, keys in held.items()}


def family_structures(cfg: dict, held: dict[int, np.ndarray], per: int = 0) -> dict[int, tuple]:
    params = {k: cfg[k] for k in ("bits_per_key", "k", "cell_bits", "load", "expansion", "cells_per_word") if cfg.get(k) is not None}
    if cfg["filter"] in ("quotient", "xor", "xor_plus", "xor_coupled", "sparse_gauss", "band_sorted"):
        params["r"] = int(cfg["r"])
    if cfg["filter"] == "blocked_bloom":
        params["variant"] = cfg.get("style") or "fixed8"
    out = {}
    for segment, keys in held.items():
        began = time.perf_counter_ns()
        try:
            made = families.build(cfg["filter"], keys, **params)
        except NoSolution:
            out[segment] = {"n": len(keys), "failed": 1}, None
            continue
        out[segment] = {"n": len(keys), "bits": made.bits, "build_ns": time.perf_counter_ns() - began}, made.contains
    return out


def counters_trial(cfg: dict, keys: np.ndarray, segment: int = 0, per: int = 0) -> dict:
    """The same equations by the batch rounds and by the earlier sorted solver."""
    spec = spec_of(cfg)
    m = rows_for(len(keys), spec.eps or 0.15, spec.w)
    start, coeff = clamp_start_np(salted_np(keys, START), m - spec.w + 1, spec.edge), coefficients_np(keys, 0, spec.w)
    rhs = fingerprint_np(keys, 0, 60)
    bank = Bank(m, len(coeff))
    got, old = bank.insert(start, coeff, rhs), families.SortedBand.solve(start, coeff, rhs)
    filled = np.flatnonzero(bank.used)
    same = old.ok == got.ok() and (not old.ok or sorted(old.pivots) == filled.tolist())
    return {
        "n": len(keys), "displacement": int(filled.sum() - start.sum()) if got.ok() else 0, "additions": got.additions, "rounds": got.rounds, "sorted_steps": old.steps, "sorted_additions": old.additions,
        "same_rows": int(same), "failed": int(not got.ok()), "redundant": got.redundant, "rows": m, "shards": 1,
    }


def seeds_trial(cfg: dict, keys: np.ndarray, segment: int = 0, per: int = 0) -> dict:
    """The same keys under `reps` hash functions: sums of the trials' rates and of their squares too."""
    out: dict = {}
    for rep in range(cfg["reps"]):
        own = distinct_np(salted_np(keys, 1000, rep).view(np.int64))
        here = cfg | {"rep": rep}
        (got, ask), = band_structures(here, {segment: own}).values()
        got |= asked(here, ask, Others(own, segment)) if ask else {}
        rate = got.get("hits", 0) / max(1, got.get("probes", 1))
        for k, v in (got | {"trials": 1, "rate_sum": rate, "rate_squares": rate * rate}).items():
            out[k] = out.get(k, 0) + v
    return out


ALONE = {"seeds": seeds_trial, "counters": counters_trial}
STRUCTURES = {"band": band_structures, "family": family_structures}
TOGETHER = 1 << 19  # keys of the segments that a task takes in lock-step


def kind_of(cfg: dict) -> str:
    return cfg.get("kind") or ("band" if "variant" in cfg else "family")


def trials(grid: dict[int, dict], held: dict[int, np.ndarray], per: int) -> dict[int, dict]:
    """Sums of the scores of each configuration over the segments. All structures of a few segments are built before the
    first is asked, so the keys that are asked are drawn once for each segment."""
    sums = {i: dict.fromkeys(SUMS, 0.0) for i in grid}

    def add(i: int, got: dict) -> None:
        for k, v in got.items():
            sums[i][k] += v

    made = {i: STRUCTURES[kind_of(c)](c, held, per) for i, c in grid.items() if kind_of(c) in STRUCTURES}
    for segment, keys in held.items():
        others = Others(keys, segment)
        for i, cfg in sorted(grid.items(), key=lambda x: x[1].get("probes") or 0):
            if i in made:
                scores, ask = made[i].pop(segment)
                add(i, scores | (asked(cfg, ask, others) if ask else {}))
            else:
                add(i, ALONE[kind_of(cfg)](cfg, keys, segment, per))
    return sums


def synthetic(spark: SparkSession, n: int) -> tuple[DataFrame, list[str]]:
    return spark.range(n).select(F.xxhash64("id", F.lit(2024)).alias("k")), ["k"]


def hashes_of(keys: tuple[DataFrame, list[str]]) -> DataFrame:
    df, names = keys
    return df.select(key_hash(df, names).alias("h")).where("h is not null")


def hashed(keys: tuple[DataFrame, list[str]]) -> DataFrame:
    """The distinct hashes of the keys, written once for all grids that take them."""
    return written(hashes_of(keys).distinct(), "keys")[0]


def at_most(hashes: DataFrame) -> int:
    """Bounds the distinct hashes, without a shuffle: their rows or, where many repeat, the estimate and three deviations more."""
    rows, about = hashes.agg(F.count("h"), F.approx_count_distinct("h", 0.01)).first()
    return min(rows, math.ceil(1.03 * about))


DEALT = 1 << 20  # keys that a task sorts at once before it deals them out


def pack(keys: np.ndarray) -> bytes:
    """Sorted keys, all first bytes, all second bytes and so on; the high bytes change seldom, so the shuffle's codec shortens them."""
    return keys.view(np.uint8).reshape(-1, 8).T.tobytes()


def unpack(data) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(data, np.uint8).reshape(8, -1).T).view(np.int64).ravel()


def dealt(hashes: DataFrame, segments: int, groups: int, parts: int) -> DataFrame:
    """Each group of segments in a partition of its own for each part, as rows of many packed keys."""

    def flush(held: list[np.ndarray]):
        h = distinct_np(np.concatenate(held))
        group = segment_np(h, segments) % groups
        order = np.argsort(group, kind="stable")
        group, h = group[order], h[order]
        cuts = np.flatnonzero(np.diff(group)) + 1
        names, packed = group[np.concatenate([[0], cuts])].astype(np.int32), [pack(k) for k in np.split(h, cuts)]
        for part in range(parts):
            yield pa.RecordBatch.from_pydict({"at": pa.array(names + np.int32(part * groups)), "keys": pa.array(packed, pa.binary())})

    def deal(it):
        held, n = [], 0
        for batch in it:
            if batch.num_rows:
                held.append(batch.column(0).to_numpy())
                n += batch.num_rows
            if n >= DEALT:
                yield from flush(held)
                held, n = [], 0
        if n:
            yield from flush(held)

    return hashes.select("h").mapInArrow(deal, "at int, keys binary").repartitionById(groups * parts, F.col("at"))


def run(spark: SparkSession, experiment: str, keys: tuple[DataFrame, list[str]] | DataFrame, grid: list[dict], segment_keys: int = 1 << 16) -> DataFrame:
    """A row of scores for each configuration. A configuration is a dict: kind (band, family, counters) and parameters.
    keys: a table and its key columns, or what `hashed` made of them."""
    ship(spark)
    if not isinstance(keys, DataFrame) and any(c.get("sharding") == "fixed_bytes" for c in grid):
        keys = hashed(keys)  # whose budget needs the exact number of keys
    hashes, total = (keys, keys.count()) if isinstance(keys, DataFrame) else (own := hashes_of(keys), at_most(own))
    cores = spark.sparkContext.defaultParallelism
    segments = segments_for(total, segment_keys)
    per, texts = -(-total // segments), [repr(c) for c in grid]
    together = max(1, TOGETHER // segment_keys)
    groups = min(segments, max(cores, -(-segments // together)))
    # A key is shuffled once, not once for each configuration; only where there are fewer groups of segments than keep the
    # cores busy are the configurations split too, each part with the keys.
    parts = max(1, min(len(grid), -(-4 * cores // groups)))

    def work(it):
        import ast

        pieces: dict[int, list[np.ndarray]] = {}
        for batch in it:
            for at, keys in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                pieces.setdefault(at // groups, []).append(unpack(keys.as_buffer()))
        for p, packed in pieces.items():
            h = distinct_np(np.concatenate(packed))
            segment = segment_np(h, segments)
            order = np.argsort(segment, kind="stable")
            segment, h = segment[order], h[order]
            cuts = np.flatnonzero(np.diff(segment)) + 1
            held = dict(zip(segment[np.concatenate([[0], cuts])].tolist(), np.split(h, cuts), strict=True))
            mine, names = {i: ast.literal_eval(texts[i]) for i in range(p, len(texts), parts)}, sorted(held)
            for at in range(0, len(names), together):
                some = {s: held[s] for s in names[at : at + together]}
                for i, got in trials(mine, some, per).items():
                    yield pa.RecordBatch.from_pydict({"i": pa.array([i], pa.int32()), "segments": pa.array([len(some)], pa.int64()), **{c: pa.array([float(got[c])], pa.float64()) for c in SUMS}})

    schema = "i int, segments long, " + ", ".join(f"{c} double" for c in SUMS)
    sums = dealt(hashes, segments, groups, parts).mapInArrow(work, schema).groupBy("i").agg(*[F.sum(c).alias(c) for c in SUMS], F.sum("segments").alias("segments"))
    rows = []
    for i, c in enumerate(grid):
        used = ("kind", "variant", "filter", "w", "r", "eps", "edge", "retry", "sharding", "probes", "seeds")
        more = ", ".join(f"{k}={v}" for k, v in c.items() if k not in used)
        named = c.get("filter") or c.get("variant")
        rows.append((i, named, c.get("w"), float(c["r"]) if c.get("r") is not None else None, c.get("eps"), c.get("edge"), c.get("retry"), c.get("sharding"), more))
    configs = spark.createDataFrame(rows, "i int, " + ", ".join(f"{n} {t}" for n, t in GRID))
    f = F.col("hits") / F.col("probes")
    bpk = F.col("bits") / F.col("n")
    scored = F.broadcast(configs).join(sums, "i").withColumn("fp_rate", F.when(F.col("probes") > 0, f)).withColumn("bits_per_key", F.when(F.col("bits") > 0, bpk))
    scored = scored.withColumn("overhead", F.when((F.col("hits") > 0) & (F.col("hits") < F.col("probes")), F.col("bits_per_key") / -F.log2("fp_rate") - 1))
    ns = [(F.col("build_ns") / F.col("n")).alias("build_ns")] + [F.try_divide(F.col(a), F.col(b)).alias(a) for a, b in (("positive_ns", "asked"), ("negative_ns", "probes"), ("mixed_ns", "mixed_asked"))]
    whole = [F.col(c).cast("long").alias(c) for c in ("n", "misses", "failed", "hits", "probes")]
    rest = [F.col(c) for c in SUMS[12:]]
    return scored.select(F.lit(experiment).alias("experiment"), *[n for n, _ in GRID], "segments", *whole, "bits_per_key", "fp_rate", "overhead", *ns, *rest)


def five_sigma_rate(expected: Column) -> Column:
    """Five standard deviations of a rate over the probes that were made."""
    return 5 * F.sqrt(expected / F.col("probes"))


def five_sigma_overhead() -> Column:
    """What five standard deviations of the sampled rate are in overhead."""
    return 5 / F.sqrt("hits") / math.log(2) * F.col("bits_per_key") / F.pow(F.log2("fp_rate"), 2)
