"""Experiments on the given tables, through the Spark operators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bandloom import measures
from bandloom.baselines import segmented
from bandloom.operators import elastic, surface
from bandloom.operators.build import build_filter, build_static
from bandloom.operators.prefilter import prefilter, verified_semi
from bandloom.operators.probe import lookup_static, probe
from bandloom.runtime import scratch, spread, table
from bandloom.sources.catalog import skip_counts, write_runs
from bandloom.spec import FilterSpec

LINE_KEY = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]
MIX = "case string, n long, n_maybe long, seconds double"


def worded(docs: DataFrame, id_column: str, size: int) -> tuple[DataFrame, F.Column]:
    """Rows of at least `size` words (lower case, split at white space) and their shingles' starts."""
    words = F.split(F.trim(F.regexp_replace(F.lower("text"), r"\s+", " ")), " ")
    rows = docs.where("text is not null").select(id_column, words.alias("w")).where(F.size("w") >= size)
    return rows, F.sequence(F.lit(0), F.greatest(F.size("w") - size, F.lit(-1)))


def shingles(docs: DataFrame, id_column: str, size: int = 8) -> DataFrame:
    """Distinct word shingles of each text."""
    rows, starts = worded(docs, id_column, size)
    return rows.select(id_column, F.explode(F.transform(starts, lambda i: F.array_join(F.slice("w", i + 1, size), " "))).alias("shingle")).distinct()


def shingle_hashes(docs: DataFrame, id_column: str, size: int = 8) -> DataFrame:
    """A 64-bit hash of every shingle, repeats included, made of its words' hashes: no strings are built."""
    rows, starts = worded(docs, id_column, size)
    hashed = rows.select(id_column, F.transform("w", lambda x: F.xxhash64(x)).alias("w"))
    return hashed.select(id_column, F.explode(F.transform(starts, lambda i: F.xxhash64(*[F.get("w", i + k) for k in range(size)]))).alias("h"))


def specs() -> dict[str, FilterSpec]:
    return {
        "homogeneous": FilterSpec(), "standard": FilterSpec(variant="standard", edge=16), "balanced": FilterSpec(variant="balanced"),
        "fractional": FilterSpec(r=7.5),
    }


def query_batches(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    keys = table(spark, sf_dir, "orders").select("o_orderkey")
    others = keys.select((F.col("o_orderkey") + 10**9).alias("o_orderkey"))
    return {"positive": keys, "negative": others, "mixed": keys.unionByName(others)}


def run_probe_mix(spark: SparkSession, sf_dir: str, mode: str = "auto") -> DataFrame:
    """Members, non-members and a mix, for three band variants and two baselines."""
    orders, rows = table(spark, sf_dir, "orders"), []
    filters = {n: build_filter(orders, "o_orderkey", s) for n, s in specs().items() if n != "fractional"}
    filters |= {f: segmented.build(orders, "o_orderkey", f) for f in ("blocked_bloom", "xor")}
    for name, flt in filters.items():
        for case, batch in query_batches(spark, sf_dir).items():
            s, got = measures.timed(lambda flt=flt, batch=batch: measures.ask(batch, flt, "o_orderkey", "_m", mode).agg(F.count("*"), F.sum(F.col("_m").cast("long"))).first())
            rows.append((f"{name} {case}", got[0], got[1], s))
    return spark.createDataFrame(rows, MIX)


def run_engine_timing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Build and probe wall clock per key over the composite line key, kernel time beside it."""
    lines, rows = table(spark, sf_dir, "lineitem").select(*LINE_KEY), []
    n = lines.distinct().count()
    others = lines.withColumn("l_linenumber", F.col("l_linenumber") + 100)
    for name in ("homogeneous", "standard", "balanced", "blocked_bloom", "xor"):
        s, flt = measures.timed(lambda name=name: build_filter(lines, LINE_KEY, specs()[name], n) if name in specs() else segmented.build(lines, LINE_KEY, name, n_hint=n))
        kernel = (flt.meta if name in specs() else flt.structures).agg(F.sum("build_ns")).first()[0]
        got = measures.measure_fp(flt, others, LINE_KEY).first()
        asked = measures.time_probe(lines, flt, LINE_KEY)
        size = measures.space(flt).first()
        rows.append((name, n, 1e9 * s / n, kernel / n, 1e9 * asked / lines.count(), size.bits_per_key, got.fp_rate))
    return spark.createDataFrame(rows, "filter string, n long, build_wall_ns double, build_kernel_ns double, probe_wall_ns double, bits_per_key double, fp_rate double")


def run_run_skipping(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders as monthly immutable runs: pairs of keys and runs that filters leave."""
    orders = table(spark, sf_dir, "orders").withColumn("run_id", F.date_format("o_orderdate", "yyyyMM").cast("int"))
    store = write_runs(orders, "run_id", ["o_orderkey"], scratch(spark, "runs"))
    return skip_counts(store, orders.select("o_orderkey"))


def run_elasticity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rate after trimming to r columns, of the parts of a split and their product, and of a cut filter."""
    orders = table(spark, sf_dir, "orders")
    flt = build_filter(orders, "o_orderkey", FilterSpec(variant="standard", r=8))
    neg = query_batches(spark, sf_dir)["negative"]
    rate = lambda f: measures.measure_fp(f, neg, "o_orderkey").first().fp_rate
    rows = [(f"trim {r}", rate(elastic.trim(flt, r)) if r < 8 else rate(flt)) for r in (8, 7, 6.5, 6, 5, 4, 3)]
    parts = elastic.split_columns(flt, [4, 4])
    each = [rate(p) for p in parts]
    rows += [("part 1", each[0]), ("part 2", each[1]), ("product", each[0] * each[1])]
    rows.append(("cut bits", float(elastic.cut_bits(flt, [10]))))
    return spark.createDataFrame(rows, "case string, value double")


def run_latency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One key against a batch: seconds each."""
    orders = table(spark, sf_dir, "orders")
    flt = build_filter(orders, "o_orderkey")
    rows = []
    for case, batch in (("single", orders.limit(1)), ("batch", orders)):
        s, got = measures.timed(lambda batch=batch: probe(batch, flt, "o_orderkey", "_m").agg(F.count("*"), F.sum(F.col("_m").cast("long"))).first())
        rows.append((case, got[0], got[1], s))
    return spark.createDataFrame(rows, MIX)


def run_join_prefilter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows and shuffled bytes of the large side of two joins: no filter, band filter, blocked Bloom, the engine's own
    runtime filter, exact. Every way ends in the same join, shuffled on both sides."""
    cases = {
        "lines of finished orders": (table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("k"), "l_linenumber"), table(spark, sf_dir, "orders").where("o_orderstatus = 'F'").select(F.col("o_orderkey").alias("k"))),
        "orders of a segment": (table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("k"), "o_orderkey"), table(spark, sf_dir, "customer").where("c_mktsegment = 'BUILDING'").select(F.col("c_custkey").alias("k"))),
    }
    off = {"spark.sql.autoBroadcastJoinThreshold": "-1", "spark.sql.adaptive.autoBroadcastJoinThreshold": "-1", "spark.sql.optimizer.runtime.bloomFilter.enabled": "false"}
    rows = []
    for case, (fact, dim) in cases.items():
        flt, bloom = build_filter(dim, "k"), segmented.build(dim, "k", "blocked_bloom")
        engine_join, wanted = surface.runtime_filtered(spark, fact, dim, ["k"])
        ways = {
            "none": fact, "band": prefilter(fact, ["k"], flt), "blocked_bloom": segmented.probe(fact, bloom, "k", "_hit").where("_hit").drop("_hit"),
            "exact": fact.join(F.broadcast(dim), "k", "left_semi"),
        }
        for name, side in ways.items():
            with surface.settings(spark, off):
                rows.append((case, name, *measures.shuffled(side.join(dim.hint("merge"), "k"))))
        with surface.settings(spark, off | wanted):
            rows.append((case, "engine", *measures.shuffled(engine_join)))
    return spark.createDataFrame(rows, "case string, filter string, n_joined long, n_shuffled long, shuffle_bytes long")


def run_string_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """URLs, whole texts and shingles as keys: misses (0) and rate on altered strings."""
    sets = {
        "url": table(spark, sf_dir, "pages").select(F.col("url").alias("k")), "text": table(spark, sf_dir, "documents").select(F.col("text").alias("k")),
        "shingle": shingles(table(spark, sf_dir, "benchmark"), "item_id").select(F.col("shingle").alias("k")), "turn": table(spark, sf_dir, "conversations").select(F.col("text").alias("k")),
    }
    out = None
    for name, keys in sets.items():
        flt = build_filter(keys, "k", FilterSpec(variant="standard", edge=16))
        miss = measures.count_false_negatives(flt, keys, "k").withColumn("case", F.lit(name))
        fp = measures.measure_fp(flt, keys.distinct().select(F.concat("k", F.lit("#none")).alias("k")), "k").select("fp_rate")
        one = miss.crossJoin(fp)
        out = one if out is None else out.unionByName(one)
    return out


def priority_code(column) -> F.Column:
    return F.substring(column, 1, 1).cast("long")


def static_inputs(spark: SparkSession, sf_dir: str) -> dict[str, tuple[DataFrame, str, F.Column, int | None]]:
    """Name -> (rows, key, value, bits; None: as many as the values need, where they grow with the table)."""
    t = lambda n: table(spark, sf_dir, n)
    return {
        "priority": (t("orders"), "o_orderkey", F.substring("o_orderpriority", 1, 1).cast("long"), 3), "nation": (t("customer"), "c_custkey", F.col("c_nationkey"), 5),
        "size": (t("part"), "p_partkey", F.col("p_size"), 6), "supplier": (t("supplier"), "s_suppkey", F.col("s_nationkey"), 5),
        "label": (t("embeddings"), "vec_id", F.col("label"), 4), "event_type": (t("events"), "event_id", F.length("event_type"), 4),
        "doc_label": (t("labels"), "doc_id", F.col("quality") * 2 + F.col("toxic"), 2), "custkey": (t("orders"), "o_orderkey", F.col("o_custkey"), None),
        "wide": (t("orders"), "o_orderkey", F.xxhash64("o_custkey", "o_orderkey").bitwiseAND(F.lit((1 << 32) - 1)), 32),
    }


def run_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Wrong answers (0) and bits per key of static functions of 2 to 32 bits."""
    rows = []
    for name, (df, key, value, bits) in static_inputs(spark, sf_dir).items():
        fn = build_static(df, key, value, bits)
        wrong = lookup_static(df.withColumn("want", value.cast("long")), fn, key, "got").where("want <> got or got is null").count()
        rows.append((name, fn.spec.r_hi, wrong, measures.space(fn).first().bits_per_key))
    return spark.createDataFrame(rows, "function string, bits int, n_wrong long, bits_per_key double")


def contamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that share 8-word shingles with the benchmark.

    The filter sits right above the explode, on 64-bit hashes; what it lets through is matched by hash, and only the texts of
    documents that are left have their shingles written out and compared as strings.
    """
    docs, bench = table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark")
    hashes = shingle_hashes(bench, "item_id").select("h").distinct()
    hit = verified_semi(shingle_hashes(spread(docs), "doc_id"), hashes, ["h"], ["h"], FilterSpec(variant="standard", edge=16)).select("doc_id").distinct()
    marks = shingles(bench, "item_id").select("shingle").distinct()
    found = shingles(docs.join(hit, "doc_id", "left_semi"), "doc_id").join(marks, "shingle", "left_semi")
    return found.groupBy("doc_id").agg(F.count("*").alias("n_shingles"))
