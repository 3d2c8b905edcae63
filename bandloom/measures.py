"""Measures of filters: rates, space, time, counters."""

from __future__ import annotations

import math
import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandloom.baselines import segmented
from bandloom.operators import probe as bands
from bandloom.operators.build import BandFilter
from bandloom.plans.planning import info_bound


def ask(df: DataFrame, flt, keys, out: str = "maybe", mode: str = "auto") -> DataFrame:
    return bands.probe(df, flt, keys, out, mode) if isinstance(flt, BandFilter) else segmented.probe(df, flt, keys, out)


def wilson(hits: int, n: int, z: float = 5.0) -> tuple[float, float]:
    p, d = hits / n, 1 + z * z / n
    mid, half = (p + z * z / (2 * n)) / d, z * math.sqrt(p * (1 - p) / n + z * z / (4 * n * n)) / d
    return mid - half, mid + half


def measure_fp(flt, negatives: DataFrame, keys, mode: str = "auto") -> DataFrame:
    """n, n_positive, fp_rate and a five-sigma interval."""
    got = ask(negatives, flt, keys, "_maybe", mode).agg(F.count("*").alias("n"), F.coalesce(F.sum(F.col("_maybe").cast("long")), F.lit(0)).alias("n_positive"))
    rate = F.col("n_positive") / F.col("n")
    z = 5.0
    d = 1 + z * z / F.col("n")
    mid = (rate + z * z / (2 * F.col("n"))) / d
    half = z * F.sqrt(rate * (1 - rate) / F.col("n") + z * z / (4 * F.col("n") * F.col("n"))) / d
    return got.select("n", "n_positive", rate.alias("fp_rate"), (mid - half).alias("fp_low"), (mid + half).alias("fp_high"))


def count_false_negatives(flt, members: DataFrame, keys, mode: str = "auto") -> DataFrame:
    """n distinct member keys and how many of them the filter denies (0, or the filter is wrong)."""
    asked = members.select(*([keys] if isinstance(keys, str) else keys)).distinct().na.drop()
    return ask(asked, flt, keys, "_maybe", mode).agg(F.count("*").alias("n"), F.coalesce(F.sum((~F.col("_maybe")).cast("long")), F.lit(0)).alias("misses"))


def space(flt) -> DataFrame:
    """n, bits, bits_per_key of the compact form."""
    rows = flt.meta.select(F.col("n_rows").alias("n"), F.col("bits").cast("double").alias("bits")) if isinstance(flt, BandFilter) else flt.structures.select("n", "bits")
    return rows.agg(F.sum("n").alias("n"), F.sum("bits").alias("bits")).withColumn("bits_per_key", F.col("bits") / F.col("n"))


def measure_space(flt, fp_rate: float) -> DataFrame:
    return space(flt).withColumn("fp_rate", F.lit(fp_rate)).withColumn("overhead", F.col("bits_per_key") / F.lit(info_bound(fp_rate)) - 1)


def build_counters(flt: BandFilter) -> DataFrame:
    """Displacement, additions, redundant keys, attempts, metadata bits, over all segments."""
    return flt.meta.agg(
        F.sum("n_rows").alias("n"), F.sum("displacement").alias("displacement"), F.sum("additions").alias("additions"), F.sum("n_redundant").alias("n_redundant"),
        F.max("attempts").alias("most_attempts"), (8 * F.sum(F.greatest(F.size("defer"), F.lit(0)))).alias("metadata_bits"), F.sum("build_ns").alias("kernel_ns"),
    )


def timed(action) -> tuple[float, object]:
    began = time.perf_counter()
    out = action()
    return time.perf_counter() - began, out


def time_probe(df: DataFrame, flt, keys, mode: str = "auto") -> float:
    """Seconds to probe all of df and count."""
    return timed(lambda: ask(df, flt, keys, "_maybe", mode).agg(F.sum(F.col("_maybe").cast("long"))).first())[0]


def ran(df: DataFrame) -> tuple[int, list]:
    """Rows of df, and the plan's nodes (from the JVM) after it ran, adaptive stages opened."""
    counted = df.agg(F.count("*").alias("n"))
    n, nodes, todo = counted.collect()[0].n, [], [counted._jdf.queryExecution().executedPlan()]
    while todo:
        node = todo.pop()
        name = node.getClass().getSimpleName()
        if name == "AdaptiveSparkPlanExec":
            todo.append(node.executedPlan())
        elif name.endswith("QueryStageExec"):
            todo.append(node.plan())
        else:
            nodes.append((name, node))
            todo += [node.children().apply(i) for i in range(node.children().size())]
    return n, nodes


def shuffled(df: DataFrame) -> tuple[int, int, int]:
    """Rows of df, and the rows and bytes that its exchanges wrote, from the metrics of the plan that ran."""
    n, nodes = ran(df)
    metrics = [node.metrics() for name, node in nodes if name == "ShuffleExchangeExec"]
    # The count's own exchange, of a row a task, is the first one from the root.
    return n, sum(m.apply("shuffleRecordsWritten").value() for m in metrics[1:]), sum(m.apply("shuffleBytesWritten").value() for m in metrics[1:])


def files_read(df: DataFrame) -> int:
    """Files that the scans of df list and read."""
    return sum(node.metrics().apply("numFiles").value() for name, node in ran(df)[1] if name == "FileSourceScanExec")


def shuffle_plan(df: DataFrame) -> dict[str, int]:
    """Counts of plan nodes that matter: exchanges, broadcasts, sorts, Python nodes."""
    text = df._jdf.queryExecution().executedPlan().toString()
    lines = text.splitlines()
    count = lambda *names: sum(any(n in line for n in names) for line in lines)
    return {
        "exchanges": sum("Exchange" in line and "BroadcastExchange" not in line for line in lines), "broadcasts": count("BroadcastExchange"),
        "sorts": sum(" Sort [" in line or line.strip().startswith("Sort [") for line in lines), "python": count("MapInArrow", "MapInPandas", "ArrowEvalPython", "BatchEvalPython", "FlatMapGroups", "FlatMapCoGroups"),
    }
