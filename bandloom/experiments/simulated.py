"""Experiments on random equations, which no table stands for: a grid of configurations, each a row, spread over tasks.

Every run_* takes (spark, **grid) and returns a frame with a row per configuration; `extra` holds what only one
experiment reports. Experiments on keys are in workloads.
"""

from __future__ import annotations

import itertools

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from bandloom.baselines import families
from bandloom.functions.hashing import START, U64, clamp_start_np
from bandloom.kernel.banding import Bank, XorBasis, back_substitute, lookup, many_until_failure
from bandloom.plans.planning import access_model, fp_model, info_bound, rows_for
from bandloom.runtime import ship


SCORE = "experiment string, w int, r double, eps double, edge int, n long, rep int, fp_rate double, overhead double, extra map<string,double>"


def equations(rng: np.random.Generator, n: int, m: int, w: int, edge: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    h = rng.integers(0, 2**64, n, dtype=np.uint64)
    low = rng.integers(0, 2**64, n, dtype=np.uint64) | U64(1)
    if w < 64:
        low &= U64((1 << w) - 1)
    coeff = np.stack([low, rng.integers(0, 2**64, n, dtype=np.uint64)]) if w == 128 else low[None]
    return clamp_start_np(h, m - w + 1, edge), coeff, rng.integers(0, 2**64, n, dtype=np.uint64)


def until_failure_trial(cfg: dict) -> list[dict]:
    """Insert random equations until the first contradiction; the overhead there, and the empty rows left; for `reps` trials."""
    m, w, reps = cfg["m"], cfg["w"], range(cfg["rep"], cfg["rep"] + cfg.get("reps", 1))
    parts = [equations(np.random.default_rng(1000 + k), m + 64, m, w, cfg["edge"]) for k in reps]
    start, coeff, rhs = np.stack([p[0] for p in parts]), np.stack([p[1] for p in parts], 1), np.stack([p[2] for p in parts])
    bank, done = many_until_failure(m, start, coeff, rhs, int({16: 0.45, 32: 0.75, 64: 0.85, 128: 0.93}[w] * m))
    empty = 1 - bank.used.reshape(len(reps), m).mean(1)
    return [{"rep": k, "eps": (m - n) / n, "n": n, "extra": {"empty_share": e}} for k, n, e in zip(reps, done.tolist(), empty.tolist(), strict=True)]


def square_trial(cfg: dict) -> dict:
    """Whether a square band system with edge w/2, and a dense random one, are regular."""
    n, w = cfg["n"], cfg["w"]
    start, coeff, _ = equations(np.random.default_rng(5000 + cfg["rep"]), n, n, w, w // 2)
    bank = Bank(n, len(coeff))
    bank.insert(start, coeff, np.zeros(n, U64))
    return {"extra": {"band_regular": float(bank.used.all()), "dense_regular": float(families.dense_rank_full(n, cfg["rep"]))}}


def two_location_trial(cfg: dict) -> dict:
    """The flagless alternative to tiers: a key's equation spans a window in each of two locations.

    No metadata says which location answers, but the system is no band any more: reduced rows reach from one location to
    the other. Reports the overhead at the first contradiction and how far the solved rows reach, beside one location's.
    """
    m, w, out = cfg["m"], cfg["w"], {}
    first, coeff, rhs = equations(np.random.default_rng(7000 + cfg["rep"]), m + 64, m, w, 1)
    second, other, _ = equations(np.random.default_rng(8000 + cfg["rep"]), m + 64, m, w, 1)

    def whole(start, words, i):
        return sum(int(x[i]) << 64 * lane for lane, x in enumerate(words)) << int(start[i])

    for name in ("one", "two"):
        basis = XorBasis(m)
        for i in range(m + 64):
            row = whole(first, coeff, i)
            if name == "two":
                row ^= whole(second, other, i)
            if basis.offer(0, row, int(rhs[i])) == "inconsistent":
                break
        reach = [((v & ((1 << m) - 1)) // low).bit_length() for low, v in basis.vectors.items()]
        out[f"{name}_eps"], out[f"{name}_reach"] = (m - i) / i, float(np.mean(reach))
    return {"n": m, "eps": out["two_eps"], "extra": out}


def span_trial(cfg: dict) -> dict:
    """Share p of fresh rows in the span, the rate measured and the rate that p predicts."""
    n, w, r = cfg["n"], cfg["w"], int(cfg["r"])
    rng = np.random.default_rng(9000 + cfg["rep"])
    m = rows_for(n, cfg["eps"], w)
    start, coeff, _ = equations(rng, n, m, w, 1)
    bank = Bank(m, len(coeff))
    got = bank.insert(start, coeff, np.zeros(n, U64))
    s2, c2, _ = equations(rng, 100_000, m, w, 1)
    p = float(bank.in_span(s2, c2).mean())
    words = back_substitute(bank, r, m, "xxhash")
    f = float((lookup(words, np.zeros(len(s2), np.int64), s2, c2) == 0).mean())
    return {"fp_rate": f, "overhead": m * r / n / info_bound(f) - 1, "extra": {"span_share": p, "fp_predicted": fp_model(r, p), "redundant": float(got.redundant)}}


TRIALS = {"until_failure": until_failure_trial, "square": square_trial, "span": span_trial, "two_location": two_location_trial}


def run_grid(spark: SparkSession, experiment: str, kind: str, grid: list[dict]) -> DataFrame:
    """A row (or several) per configuration, however long the grid; neighbours go to different tasks."""
    ship(spark)
    rows = [(i, repr(c)) for i, c in enumerate(grid)]
    configs = spark.createDataFrame(rows, "i int, cfg string").repartition(max(1, min(len(rows), 4 * spark.sparkContext.defaultParallelism)), "i")
    names = [f.split()[0] for f in SCORE.split(", ")]

    def run(it):
        import ast

        for pdf in it:
            out = []
            for text in pdf["cfg"]:
                cfg = {"rep": 0} | ast.literal_eval(text)
                got = TRIALS[kind](cfg)
                for one in got if isinstance(got, list) else [got]:
                    row = {"experiment": experiment} | {k: cfg.get(k) for k in ("w", "r", "eps", "edge", "n", "rep")} | one
                    row["extra"] = ({"m": float(cfg["m"])} if "m" in cfg else {}) | row.get("extra", {})
                    out.append([row.get(c) for c in names])
            frame = pd.DataFrame(out, columns=names)
            for c in ("w", "edge", "n", "rep"):
                frame[c] = frame[c].astype("Int64")
            yield frame

    return configs.mapInPandas(run, SCORE)


def product(**axes) -> list[dict]:
    return [dict(zip(axes, v, strict=True)) for v in itertools.product(*axes.values())]


def run_success_table(spark, sizes=((1 << 10, 2000), (1 << 14, 160), (1 << 17, 16)), ws=(16, 32, 64, 128)) -> DataFrame:
    """Overhead at the first failure: its mean, median, 95 % and 99.9 % quantiles are what constructions need to fail with
    probability .5, .05, .001. Edge inflation w/2 and w/4 at the smallest m. sizes: m and trials; a quantile is given where
    at least two trials lie beyond it, else it is null."""
    few, many = sizes[0]
    cases = [(w, m, 1, trials) for w in ws for m, trials in sizes[::-1]] + [(w, few, e, many) for w in ws for e in (w // 4, w // 2)]
    grid = []
    for w, m, edge, trials in cases:
        at_once = max(1, min(trials, (1 << 17) // m))  # systems that advance together
        grid += [{"w": w, "m": m, "edge": edge, "rep": k, "reps": min(at_once, trials - k)} for k in range(0, trials, at_once)]
    got = run_grid(spark, "success_table", "until_failure", grid)
    by = got.groupBy("w", "edge", F.col("extra")["m"].cast("long").alias("m"))
    n = F.count("*")
    quantiles = [F.when(n * (1 - q) >= 2, F.percentile("eps", F.lit(q))).alias(c) for c, q in (("eps_fail_50", 0.5), ("eps_fail_5", 0.95), ("eps_fail_01", 0.999))]
    return by.agg(n.alias("trials"), F.avg("eps").alias("mean_eps"), (F.stddev("eps") / F.sqrt(n)).alias("mean_error"), *quantiles, F.avg(F.col("extra")["empty_share"]).alias("empty_share"))


def run_access_model(spark) -> DataFrame:
    rows = [(layout, w, r, float(a["bits"]), float(a["lines"])) for layout in ("icm", "row", "column") for w in (16, 32, 64, 128) for r in (1, 2, 3, 6, 7, 11) for a in [access_model(layout, w, r)]]
    return spark.createDataFrame(rows, "layout string, w int, r int, bits_read double, cache_lines double")


def run_square(spark, ns=(64, 256, 1024), trials: int = 400) -> DataFrame:
    """Share of square systems that are regular; both columns tend to about 0.289."""
    got = run_grid(spark, "square", "square", [{"n": n, "w": w, "rep": k} for n in ns for w in (64, 128) if w <= n for k in range(trials)])
    return got.groupBy("n", "w").agg(F.count("*").alias("trials"), F.avg(F.col("extra")["band_regular"]).alias("band_regular"), F.avg(F.col("extra")["dense_regular"]).alias("dense_regular"))


def run_two_location(spark, ms=(512, 1024), ws=(32, 64), trials: int = 8) -> DataFrame:
    """Overhead at the first contradiction and mean reach of a solved row, with windows in one and in two locations."""
    got = run_grid(spark, "two_location", "two_location", [{"m": m, "w": w, "rep": k} for m in ms for w in ws for k in range(trials)])
    extra = [F.avg(F.col("extra")[k]).alias(k) for k in ("one_eps", "two_eps", "one_reach", "two_reach")]
    return got.groupBy(F.col("n").alias("m"), "w").agg(F.count("*").alias("trials"), *extra)


def run_span_probability(spark, ns=(10_000, 50_000)) -> DataFrame:
    return run_grid(spark, "span_probability", "span", product(w=[16, 32, 64], r=[7], eps=[0.05, 0.1, 0.2, 0.3], n=list(ns)))


def run_load_diagonal(spark, n: int = 1024, w: int = 64) -> DataFrame:
    """Most that the number of starts up to i falls behind i, over a square system, by edge inflation."""
    from bandloom.functions.hashing import clamp_start, salted

    keys = spark.range(n * 50).select((F.col("id") % 50).alias("trial"), F.col("id").alias("key"))
    out = None
    for edge in (1, w // 4, w // 2):
        starts = keys.withColumn("start", clamp_start(salted(F.col("key"), START), n - w + 1, edge))
        counts = starts.groupBy("trial", "start").agg(F.count("*").alias("k"))
        running = F.sum("k").over(Window.partitionBy("trial").orderBy("start"))
        lag = counts.withColumn("behind", F.col("start") + 1 - running).groupBy("trial").agg(F.max("behind").alias("worst_behind"), F.min("behind").alias("worst_ahead"))
        one = lag.agg(F.avg("worst_behind").alias("mean_behind"), F.avg("worst_ahead").alias("mean_ahead")).withColumn("edge", F.lit(edge))
        out = one if out is None else out.unionByName(one)
    return out
