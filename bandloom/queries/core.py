"""Registered queries of the band filters, their baselines, measures and workloads, with DuckDB twins."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from bandloom import measures
from bandloom.baselines import families, relational, segmented
from bandloom.experiments import engine, grids, simulated, workloads
from bandloom.functions.hashing import portable_digest
from bandloom.operators import elastic, surface
from bandloom.operators.build import build_filter, build_static
from bandloom.operators.prefilter import prefilter_join, verified_anti, verified_semi
from bandloom.operators.probe import lookup_static, probe
from bandloom.plans import planning
from bandloom.runtime import scratch, ship, table
from bandloom.sources.catalog import filter_dump, load, multi_get, save, write_runs
from bandloom.spec import FilterSpec
from bandloom.streaming.streams import window_counts

QUERIES: dict = {}
ORACLES: dict = {}
STANDARD = FilterSpec(variant="standard", edge=16)
BALANCED = FilterSpec(variant="balanced")
HOMOGENEOUS = FilterSpec()
VARIANTS = {"std": STANDARD, "homog": HOMOGENEOUS, "balanced": BALANCED, "frac": FilterSpec(r=7.5), "wide": FilterSpec(variant="standard", w=128), "narrow": FilterSpec(w=32, r=3)}


def register(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def big(column: str) -> F.Column:
    return F.col(column).cast("long").alias(column)


# No false negatives, for every variant and every baseline.

NO_MISS = "SELECT count(DISTINCT l_orderkey) AS n, CAST(0 AS BIGINT) AS misses FROM lineitem"
COMPOSITE = "SELECT count(*) AS n, CAST(0 AS BIGINT) AS misses FROM (SELECT DISTINCT l_orderkey, l_partkey, l_suppkey, l_linenumber FROM lineitem)"

for _name, _spec in VARIANTS.items():

    @register(f"{_name}_no_false_negative", NO_MISS)
    def _(spark, sf_dir, spec=_spec):
        lines = table(spark, sf_dir, "lineitem")
        return measures.count_false_negatives(build_filter(lines, "l_orderkey", spec), lines, "l_orderkey")

    @register(f"{_name}_semi_join", "SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F')")
    def _(spark, sf_dir, spec=_spec):
        lines = table(spark, sf_dir, "lineitem").select(*engine.LINE_KEY)
        return verified_semi(lines, table(spark, sf_dir, "orders").where("o_orderstatus = 'F'"), ["l_orderkey"], ["o_orderkey"], spec).select(*engine.LINE_KEY)


for _name in families.NAMES:

    @register(f"{_name}_no_false_negative", NO_MISS)
    def _(spark, sf_dir, family=_name):
        lines = table(spark, sf_dir, "lineitem")
        params = {"expansion": 1.12} if family == "sparse_gauss" else {}
        return measures.count_false_negatives(segmented.build(lines, "l_orderkey", family, segment_keys=families.SMALL.get(family, 1 << 16), **params), lines, "l_orderkey")


@register("composite_key_no_false_negative", COMPOSITE)
def _(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem")
    return measures.count_false_negatives(build_filter(lines, engine.LINE_KEY), lines, engine.LINE_KEY)


@register("anti_join_verified", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def _(spark, sf_dir):
    orders = table(spark, sf_dir, "orders").select("o_orderkey")
    return verified_anti(orders, table(spark, sf_dir, "lineitem"), ["o_orderkey"], ["l_orderkey"])


@register("prefiltered_join", "SELECT o_orderpriority, count(*) AS n, CAST(sum(l_linenumber) AS BIGINT) AS lines FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_orderstatus = 'F' GROUP BY 1")
def prefiltered_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber")
    dim = table(spark, sf_dir, "orders").where("o_orderstatus = 'F'").select("o_orderkey", "o_orderpriority")
    joined = prefilter_join(lines, dim, ["l_orderkey"], ["o_orderkey"])
    return joined.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_linenumber").alias("lines"))


# Static functions.


def _static(name: str, sql: str, fact: str, fact_key: str):
    @register(f"static_{name}_lookup", sql)
    def _(spark, sf_dir):
        df, key, value, bits = engine.static_inputs(spark, sf_dir)[name]
        fn = build_static(df, key, value, bits)
        rows = table(spark, sf_dir, fact).select(F.col(fact_key).alias("key"))
        return lookup_static(rows, fn, "key").groupBy("value").agg(F.count("*").alias("n"), F.sum("key").alias("key_sum"))


for _n, _sql, _fact, _k in (
    ("priority", "SELECT CAST(substr(o_orderpriority, 1, 1) AS BIGINT) AS value, count(*) AS n, CAST(sum(l_orderkey) AS BIGINT) AS key_sum FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1", "lineitem", "l_orderkey"),
    ("nation", "SELECT CAST(c_nationkey AS BIGINT) AS value, count(*) AS n, CAST(sum(o_custkey) AS BIGINT) AS key_sum FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1", "orders", "o_custkey"),
    ("size", "SELECT CAST(p_size AS BIGINT) AS value, count(*) AS n, CAST(sum(l_partkey) AS BIGINT) AS key_sum FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1", "lineitem", "l_partkey"),
    ("supplier", "SELECT CAST(s_nationkey AS BIGINT) AS value, count(*) AS n, CAST(sum(l_suppkey) AS BIGINT) AS key_sum FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1", "lineitem", "l_suppkey"),
    ("label", "SELECT CAST(label AS BIGINT) AS value, count(*) AS n, CAST(sum(vec_id) AS BIGINT) AS key_sum FROM embeddings GROUP BY 1", "embeddings", "vec_id"),
    ("event_type", "SELECT CAST(length(event_type) AS BIGINT) AS value, count(*) AS n, CAST(sum(event_id) AS BIGINT) AS key_sum FROM events GROUP BY 1", "events", "event_id"),
    ("doc_label", "SELECT CAST(quality * 2 + toxic AS BIGINT) AS value, count(*) AS n, CAST(sum(doc_id) AS BIGINT) AS key_sum FROM labels GROUP BY 1", "labels", "doc_id"),
    ("custkey", "SELECT o_custkey AS value, count(*) AS n, CAST(sum(l_orderkey) AS BIGINT) AS key_sum FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1", "lineitem", "l_orderkey"),
):
    _static(_n, _sql, _fact, _k)


@register("static_wide_values", "SELECT count(*) AS n, CAST(0 AS BIGINT) AS n_wrong FROM orders")
def _(spark, sf_dir):
    df, key, value, bits = engine.static_inputs(spark, sf_dir)["wide"]
    got = lookup_static(df.withColumn("want", value.cast("long")), build_static(df, key, value, bits, BALANCED), key, "got")
    return got.agg(F.count("*").alias("n"), F.sum((F.col("want") != F.col("got")).cast("long")).alias("n_wrong"))


# Equations and routing on the portable digest.

DIGEST = "CAST(('0x' || substr(h, 1, 8)) AS BIGINT) AS start32, CAST(('0x' || substr(h, 9, 8)) AS BIGINT) AS fp32, CAST(('0x' || substr(h, 17, 16)) AS UBIGINT) AS coeff64 FROM (SELECT {key} AS key, md5('0:' || CAST({key} AS VARCHAR)) AS h FROM {table})"


def eq(df: DataFrame, key: str, m: int, w: int, edge: int = 1) -> DataFrame:
    """key, start, coeff (first bit 1) and an 8-bit fingerprint."""
    d = portable_digest(F.col(key))
    more = 2 * (max(edge, 1) - 1)
    starts = m - w + 1
    u = F.shiftrightunsigned(d["start32"] * F.lit(starts + more).cast("long"), 32) - more // 2
    return df.select(F.col(key).alias("key"), F.greatest(F.lit(0).cast("long"), F.least(u, F.lit(starts - 1).cast("long"))).alias("start"), d["coeff64"].bitwiseOR(F.lit(1).cast("long")).alias("coeff"), d["fp32"].bitwiseAND(F.lit(255).cast("long")).alias("fp"))


def eq_sql(key: str, tab: str, m: int, w: int, edge: int = 1) -> str:
    more, starts = 2 * (max(edge, 1) - 1), m - w + 1
    return f"SELECT key, greatest(0, least(((start32 * {starts + more}) >> 32) - {more // 2}, {starts - 1})) AS start, coeff64 | 1::UBIGINT AS ucoeff, fp32 & 255 AS fp FROM (SELECT key, {DIGEST.format(key=key, table=tab)})"


@register("band_equations_portable", f"SELECT key, start, CASE WHEN ucoeff >= 9223372036854775808 THEN CAST(CAST(ucoeff AS HUGEINT) - 18446744073709551616 AS BIGINT) ELSE CAST(ucoeff AS BIGINT) END AS coeff, fp FROM ({eq_sql('c_custkey', 'customer', 2048, 64)})")
def _(spark, sf_dir):
    return eq(table(spark, sf_dir, "customer"), "c_custkey", 2048, 64)


for _edge in (1, 16, 32):

    @register(f"start_histogram_edge_{_edge}", f"SELECT start // 64 AS bucket, count(*) AS n, count(*) FILTER (start = 0) AS n_first, count(*) FILTER (start = 1984) AS n_last FROM ({eq_sql('o_orderkey', 'orders', 2048, 64, _edge)}) GROUP BY 1")
    def _(spark, sf_dir, edge=_edge):
        e = eq(table(spark, sf_dir, "orders"), "o_orderkey", 2048, 64, edge)
        return e.groupBy(F.shiftright("start", 6).alias("bucket")).agg(F.count("*").alias("n"), F.sum((F.col("start") == 0).cast("long")).alias("n_first"), F.sum((F.col("start") == 1984).cast("long")).alias("n_last"))


@register("prefix_load_diagonal", f"SELECT start, CAST(sum(k) OVER (ORDER BY start) AS BIGINT) - start - 1 AS ahead FROM (SELECT start, count(*) AS k FROM ({eq_sql('c_custkey', 'customer', 2048, 64)}) GROUP BY 1)")
def _(spark, sf_dir):
    counts = eq(table(spark, sf_dir, "customer"), "c_custkey", 2048, 64).groupBy("start").agg(F.count("*").alias("k"))
    # The window's order spans all starts: at most m rows, one per start, are left after the aggregation.
    return counts.select("start", (F.sum("k").over(Window.orderBy("start")) - F.col("start") - 1).alias("ahead"))


@register("overloaded_intervals", f"SELECT CAST(bucket AS BIGINT) AS bucket, CAST(sum(k) OVER (ORDER BY bucket RANGE BETWEEN CURRENT ROW AND 3 FOLLOWING) AS BIGINT) AS load FROM (SELECT start // 64 AS bucket, count(*) AS k FROM ({eq_sql('o_orderkey', 'orders', 16384, 64)}) GROUP BY 1)")
def _(spark, sf_dir):
    counts = eq(table(spark, sf_dir, "orders"), "o_orderkey", 16384, 64).groupBy(F.shiftright("start", 6).alias("bucket")).agg(F.count("*").alias("k"))
    return counts.select("bucket", F.sum("k").over(Window.orderBy("bucket").rangeBetween(0, 3)).alias("load"))


ROUTE_SQL = """SELECT CASE WHEN u < {cut} THEN u // {a} ELSE {first} + (u - {cut}) // {b} END AS shard, CAST(v AS INTEGER) AS bucket
FROM (SELECT start32 >> 12 AS u, CASE {buckets} END AS v FROM (SELECT {digest}))"""


def route(df: DataFrame, key: str) -> DataFrame:
    """Primary shard of 8 (four of tier 1, overloaded by 1/8) and bucket, by the portable digest in 2^20 steps."""
    d = portable_digest(F.col(key))
    u, first = F.shiftrightunsigned(d["start32"], 12), 4
    a = (1 << 20) // 64 * 9
    cut = first * a
    b = ((1 << 20) - cut) // 4
    shard = F.when(u < cut, F.floor(u / a)).otherwise(F.least(F.lit(7), first + F.floor((u - cut) / b)))
    bucket = sum(((d["fp32"] >= e).cast("int") for e in bucket_edges()), F.lit(0))
    return df.select(F.col(key).alias("key"), shard.cast("long").alias("shard"), bucket.alias("bucket"), d["coeff64"].alias("c"))


def bucket_edges() -> list[int]:
    total, out = 0.0, []
    for s in planning.bucket_shares()[:-1]:
        total += s
        out.append(math.floor(total * 2**32))
    return out


def route_sql(key: str, tab: str) -> str:
    a = (1 << 20) // 64 * 9
    b = ((1 << 20) - 4 * a) // 4
    buckets = " + ".join(f"CAST(fp32 >= {e} AS INTEGER)" for e in bucket_edges())
    return f"SELECT key, CAST(CASE WHEN u < {4 * a} THEN u // {a} ELSE least(7, 4 + (u - {4 * a}) // {b}) END AS BIGINT) AS shard, {buckets} AS bucket, coeff64 FROM (SELECT *, start32 >> 12 AS u FROM (SELECT key, {DIGEST.format(key=key, table=tab)}))"


@register("primary_shard_counts", f"SELECT shard, count(*) AS n FROM ({route_sql('o_orderkey', 'orders')}) GROUP BY 1")
def _(spark, sf_dir):
    return route(table(spark, sf_dir, "orders"), "o_orderkey").groupBy("shard").agg(F.count("*").alias("n"))


@register("bucket_counts", f"SELECT bucket, count(*) AS n FROM ({route_sql('o_orderkey', 'orders')}) GROUP BY 1")
def _(spark, sf_dir):
    return route(table(spark, sf_dir, "orders"), "o_orderkey").groupBy("bucket").agg(F.count("*").alias("n"))


@register("secondary_tier_check", f"SELECT tier, count(*) AS n, CAST(sum(later) AS BIGINT) AS n_later FROM (SELECT CASE WHEN shard < 4 THEN 1 WHEN shard < 6 THEN 2 WHEN shard < 7 THEN 3 ELSE 4 END AS tier, CASE WHEN shard < 7 THEN 1 ELSE 0 END AS later FROM ({route_sql('o_orderkey', 'orders')})) GROUP BY 1")
def _(spark, sf_dir):
    r = route(table(spark, sf_dir, "orders"), "o_orderkey")
    edges = [4, 6, 7]
    tier = sum(((F.col("shard") >= e).cast("int") for e in edges), F.lit(1))
    return r.select(tier.alias("tier"), (F.least(tier + 1, F.lit(4)) > tier).cast("long").alias("later")).groupBy("tier").agg(F.count("*").alias("n"), F.sum("later").alias("n_later"))


# Elimination in SQL over few keys: rows occupied, solution, displacement.


def small_system(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Occupied rows of the system of the nations' keys: (row, start), by the insertion kernel on the portable digest."""
    import numpy as np

    from bandloom.kernel.banding import Bank, back_substitute

    rows = eq(table(spark, sf_dir, "nation"), "n_nationkey", 64, 16).select("start", F.col("coeff").bitwiseAND(F.lit(65535)).alias("c"), F.col("fp").alias("b")).orderBy("key").limit(101).collect()
    if len(rows) > 100:
        raise ValueError("the system for SQL's elimination is of at most 100 keys")
    bank = Bank(64, 1)
    report = bank.insert(np.array([r.start for r in rows]), np.array([[r.c for r in rows]], np.uint64), np.array([r.b for r in rows], np.uint64))
    words = back_substitute(bank, 8, 64, "zero")[0, 0]
    out = [(i, bool(bank.used[i]), int(sum(((int(words[j]) >> i) & 1) << j for j in range(8)))) for i in range(64)]
    return spark.createDataFrame([(*o, report.inserted, report.redundant, report.inconsistent, sum(r.start for r in rows)) for o in out], "row int, used boolean, z int, n_inserted int, n_redundant int, n_inconsistent int, start_sum long")


ELIMINATE_SQL = f"""
WITH RECURSIVE e AS (
  SELECT CAST(row_number() OVER (ORDER BY key DESC) AS INTEGER) AS id, CAST(start AS INTEGER) AS start, CAST(ucoeff & 65535 AS BIGINT) AS c, CAST(fp AS BIGINT) AS b
  FROM ({eq_sql('n_nationkey', 'nation', 64, 16)})
), go(id, i, c, b, cs, bs, n_ins, n_red, n_bad) AS (
  SELECT 1, (SELECT start FROM e WHERE id = 1), (SELECT c FROM e WHERE id = 1), (SELECT b FROM e WHERE id = 1),
    list_transform(range(64), lambda x: CAST(0 AS BIGINT)), list_transform(range(64), lambda x: CAST(0 AS BIGINT)), 0, 0, 0
  UNION ALL
  SELECT CASE WHEN done THEN g.id + 1 ELSE g.id END,
    CASE WHEN done THEN n.start ELSE i2 END, CASE WHEN done THEN n.c ELSE c2 END, CASE WHEN done THEN n.b ELSE x_b END,
    CASE WHEN empty THEN list_transform(range(64), lambda x: CASE WHEN x = i THEN g.c ELSE cs[x + 1] END) ELSE cs END,
    CASE WHEN empty THEN list_transform(range(64), lambda x: CASE WHEN x = i THEN g.b ELSE bs[x + 1] END) ELSE bs END,
    n_ins + CAST(empty AS INTEGER), n_red + CAST(NOT empty AND x_c = 0 AND x_b = 0 AS INTEGER), n_bad + CAST(NOT empty AND x_c = 0 AND x_b <> 0 AS INTEGER)
  FROM (
    SELECT *, empty OR x_c = 0 AS done,
      i + CASE WHEN x_c = 0 THEN 0 ELSE CAST(bit_count((x_c & (-x_c)) - 1) AS INTEGER) END AS i2,
      CASE WHEN x_c = 0 THEN 0 ELSE x_c >> CAST(bit_count((x_c & (-x_c)) - 1) AS INTEGER) END AS c2
    FROM (SELECT *, cs[i + 1] = 0 AS empty, xor(c, cs[i + 1]) AS x_c, xor(b, bs[i + 1]) AS x_b FROM go WHERE id <= (SELECT max(id) FROM e))
  ) g LEFT JOIN e n ON n.id = g.id + 1
), f AS (SELECT * FROM go WHERE id > (SELECT max(id) FROM e)),
back(k, z, cs, bs) AS (
  SELECT 63, list_transform(range(80), lambda x: CAST(0 AS BIGINT)), cs, bs FROM f
  UNION ALL
  SELECT k - 1, list_transform(range(80), lambda x: CASE WHEN x <> k OR cs[k + 1] = 0 THEN z[x + 1] ELSE
    xor(bs[k + 1], list_reduce(list_prepend(CAST(0 AS BIGINT), list_transform(range(1, 16), lambda t: CASE WHEN (cs[k + 1] >> CAST(t AS INTEGER)) & 1 = 1 THEN z[k + t + 1] ELSE CAST(0 AS BIGINT) END)), lambda p, q: xor(p, q))) END), cs, bs
  FROM back WHERE k >= 0
)
"""


@register("occupied_rows_small", ELIMINATE_SQL + "SELECT CAST(r AS INTEGER) AS row, n_ins AS n_inserted, n_red AS n_redundant, n_bad AS n_inconsistent FROM f, range(64) t(r) WHERE cs[r + 1] <> 0")
def _(spark, sf_dir):
    return small_system(spark, sf_dir).where("used").select("row", "n_inserted", "n_redundant", "n_inconsistent")


@register("solution_bits_small", ELIMINATE_SQL + "SELECT CAST(r AS INTEGER) AS row, CAST(z[r + 1] AS INTEGER) AS z FROM (SELECT z FROM back WHERE k = -1), range(64) t(r)")
def _(spark, sf_dir):
    return small_system(spark, sf_dir).select("row", "z")


@register("displacement_small", ELIMINATE_SQL + "SELECT CAST((SELECT sum(r) FROM f, range(64) t(r) WHERE cs[r + 1] <> 0) - (SELECT sum(start) FROM e) AS BIGINT) AS displacement")
def _(spark, sf_dir):
    return small_system(spark, sf_dir).groupBy("start_sum").agg(F.sum(F.when(F.col("used"), F.col("row"))).alias("p")).select((F.col("p") - F.col("start_sum")).alias("displacement"))


# Bloom filters as relations.

BLOOM_SQL = "SELECT key, ((h1 + i * (h2 | 1)) % 16384) AS p FROM (SELECT {key} AS key, CAST('0x' || substr(md5('0:' || {key}), 1, 8) AS BIGINT) AS h1, CAST('0x' || substr(md5('0:' || {key}), 9, 8) AS BIGINT) AS h2 FROM {table}), range(7) t(i)"


@register("bloom_bits", f"SELECT word, CASE WHEN b >= 9223372036854775808 THEN CAST(b - 18446744073709551616 AS BIGINT) ELSE CAST(b AS BIGINT) END AS bits FROM (SELECT p // 64 AS word, CAST(sum(DISTINCT CAST(1 AS HUGEINT) << CAST(p % 64 AS INTEGER)) AS HUGEINT) AS b FROM ({BLOOM_SQL.format(key='c_custkey', table='customer')}) GROUP BY 1)")
def _(spark, sf_dir):
    return relational.build_bloom(table(spark, sf_dir, "customer"), "c_custkey", 16384, 7, relational.digest_hashes).words


@register("bloom_fp_exact", f"WITH s AS (SELECT DISTINCT p FROM ({BLOOM_SQL.format(key='c_custkey', table='customer')})), q AS (SELECT key, p FROM ({BLOOM_SQL.format(key='o_orderkey', table='orders')})) SELECT key AS o_orderkey, bool_and(s.p IS NOT NULL) AS maybe FROM q LEFT JOIN s USING (p) GROUP BY 1")
def _(spark, sf_dir):
    flt = relational.build_bloom(table(spark, sf_dir, "customer"), "c_custkey", 16384, 7, relational.digest_hashes)
    return relational.probe_bloom(table(spark, sf_dir, "orders").select("o_orderkey"), flt, "o_orderkey", hashes=relational.digest_hashes)


@register("bloom_merge", f"SELECT word, CASE WHEN b >= 9223372036854775808 THEN CAST(b - 18446744073709551616 AS BIGINT) ELSE CAST(b AS BIGINT) END AS bits FROM (SELECT p // 64 AS word, CAST(sum(DISTINCT CAST(1 AS HUGEINT) << CAST(p % 64 AS INTEGER)) AS HUGEINT) AS b FROM ({BLOOM_SQL.format(key='c_custkey', table='customer')}) GROUP BY 1)")
def _(spark, sf_dir):
    c = table(spark, sf_dir, "customer")
    parts = [relational.build_bloom(c.where(F.pmod("c_custkey", F.lit(2)) == k), "c_custkey", 16384, 7, relational.digest_hashes) for k in (0, 1)]
    return relational.merge(*parts).words


BLOCK_SQL = "SELECT {key} AS key, h1 % 64 AS block, i, CAST(((h2 >> CAST(3 * i AS INTEGER)) + i * h1) % 64 AS INTEGER) AS six FROM (SELECT {key}, CAST('0x' || substr(md5('0:' || {key}), 1, 8) AS BIGINT) AS h1, CAST('0x' || substr(md5('0:' || {key}), 9, 8) AS BIGINT) AS h2 FROM {table}), range(8) t(i)"


@register("blocked_bloom_bits", f"SELECT block, CAST(i AS INTEGER) AS i, CASE WHEN b >= 9223372036854775808 THEN CAST(b - 18446744073709551616 AS BIGINT) ELSE CAST(b AS BIGINT) END AS bits FROM (SELECT block, i, CAST(sum(DISTINCT CAST(1 AS HUGEINT) << six) AS HUGEINT) AS b FROM ({BLOCK_SQL.format(key='c_custkey', table='customer')}) GROUP BY 1, 2)")
def _(spark, sf_dir):
    words = relational.build_blocked_bloom(table(spark, sf_dir, "customer"), "c_custkey", 64, relational.digest_hashes)
    return words.select("block", F.posexplode(F.array(*[f"w{i}" for i in range(8)])).alias("i", "bits"))


@register("blocked_bloom_fp_exact", f"WITH s AS (SELECT DISTINCT block, i, six FROM ({BLOCK_SQL.format(key='c_custkey', table='customer')})) SELECT q.key AS o_orderkey, bool_and(s.block IS NOT NULL) AS maybe FROM ({BLOCK_SQL.format(key='o_orderkey', table='orders')}) q LEFT JOIN s ON q.block = s.block AND q.i = s.i AND q.six = s.six GROUP BY 1")
def _(spark, sf_dir):
    words = relational.build_blocked_bloom(table(spark, sf_dir, "customer"), "c_custkey", 64, relational.digest_hashes)
    return relational.probe_blocked_bloom(table(spark, sf_dir, "orders").select("o_orderkey"), words, "o_orderkey", 64, hashes=relational.digest_hashes)


@register("xor_positions", "SELECT key, (start32 * 700) >> 32 AS p0, 700 + ((fp32 * 700) >> 32) AS p1, 1400 + (CAST((coeff64 >> 32) AS BIGINT) * 700 >> 32) AS p2 FROM (SELECT key, " + DIGEST.format(key="c_custkey", table="customer") + ")")
def _(spark, sf_dir):
    d = portable_digest(F.col("c_custkey"))
    third = lambda h: F.shiftrightunsigned(h * 700, 32)
    return table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("key"), third(d["start32"]).alias("p0"), (700 + third(d["fp32"])).alias("p1"), (1400 + third(F.shiftrightunsigned(d["coeff64"], 32))).alias("p2"))


# Closed forms.


def frame(spark, rows, schema):
    return spark.createDataFrame(rows, schema)


def each(spark, f, *columns) -> F.Column:
    """A closed form in millionths or the like, half away from zero as in SQL, for the values of a table's columns."""
    ship(spark)
    return F.udf(lambda *values: math.floor(f(*values) + 0.5), "long")(*columns)


def quantities(spark, sf_dir) -> DataFrame:
    """How many lines have each whole quantity: parameters that come from a table."""
    return table(spark, sf_dir, "lineitem").groupBy(F.col("l_quantity").cast("int").alias("q")).agg(F.count("*").alias("n"))


QUANTITIES = "(SELECT CAST(l_quantity AS INTEGER) AS q, count(*) AS n FROM lineitem GROUP BY 1)"


@register("rows_for_n", "SELECT n, CAST(greatest(ceil(ceil(n * 1.1) / 64.0) * 64, 128) AS BIGINT) AS m FROM (SELECT count(*) AS n FROM orders UNION ALL SELECT count(*) FROM customer UNION ALL SELECT count(*) FROM supplier)")
def _(spark, sf_dir):
    return frame(spark, [(n, planning.rows_for(n, 0.1, 64)) for n in (table(spark, sf_dir, t).count() for t in ("orders", "customer", "supplier"))], "n long, m long")


@register("eps_recommended", f"SELECT CAST(w AS INTEGER) AS w, q AS r, n, CAST(round((4 + q / 4.0) / w * 1000000) AS BIGINT) AS eps_millionths FROM (SELECT unnest([16, 32, 64, 128]) AS w), {QUANTITIES}")
def _(spark, sf_dir):
    """Result bits are the lines' quantities."""
    q = quantities(spark, sf_dir).crossJoin(frame(spark, [(w,) for w in (16, 32, 64, 128)], "w int"))
    return q.select("w", F.col("q").alias("r"), "n", each(spark, lambda r, w: planning.eps_homogeneous(r, w) * 1e6, "q", "w").alias("eps_millionths"))


@register("fractional_model", f"SELECT r, n, CAST(round(f * 1e9) AS BIGINT) AS rate_billionths, CAST(round((r / -log2(f) - 1) * 1e6) AS BIGINT) AS penalty_millionths FROM (SELECT r, n, (1 - (r - floor(r))) * pow(2, -floor(r)) + (r - floor(r)) * pow(2, -floor(r) - 1) AS f FROM (SELECT CAST(1 + q / 4.0 AS DOUBLE) AS r, n FROM {QUANTITIES}))")
def _(spark, sf_dir):
    """Widths in quarter bits, from the lines' quantities."""
    q = quantities(spark, sf_dir).select((1 + F.col("q") / 4.0).alias("r"), "n")
    return q.select("r", "n", each(spark, lambda r: planning.fp_model(r) * 1e9, "r").alias("rate_billionths"), each(spark, lambda r: planning.fractional_penalty(r) * 1e6, "r").alias("penalty_millionths"))


@register("tier_plan", "SELECT CAST(levels AS INTEGER) AS levels, CAST(t AS INTEGER) AS tier, CAST(ceil(pow(2, levels - t - 1)) AS INTEGER) AS shards FROM range(1, 9) a(levels), range(1, 9) b(t) WHERE t <= levels")
def _(spark, sf_dir):
    return frame(spark, [(n, i + 1, s) for n in range(1, 9) for i, s in enumerate(planning.tiers(n))], "levels int, tier int, shards int")


@register("bucket_plan", "SELECT o_orderstatus, CAST(rank AS INTEGER) AS rank, CAST(round(n * s * 1000) AS BIGINT) AS keys_thousandths FROM (SELECT row_number() OVER (ORDER BY s DESC) - 1 AS rank, s FROM (SELECT (1 - pow(2, -0.5)) * pow(2, -0.5 * k) AS s FROM range(7) t(k) UNION ALL SELECT pow(2, -3.5))), (SELECT o_orderstatus, count(*) AS n FROM orders GROUP BY 1)")
def _(spark, sf_dir):
    """Keys that each bucket expects of the orders of each status."""
    n = table(spark, sf_dir, "orders").groupBy("o_orderstatus").agg(F.count("*").alias("n"))
    ranks = n.crossJoin(frame(spark, [(i,) for i in range(8)], "rank int"))
    return ranks.select("o_orderstatus", "rank", each(spark, lambda n, i: n * planning.bucket_shares()[i] * 1e3, "n", "rank").alias("keys_thousandths"))


@register("alpha_plan", "SELECT l_suppkey, k AS keys_per_shard, CAST(round(least(0.45, 3.5 / sqrt(k)) * 1e6) AS BIGINT) AS alpha_millionths FROM (SELECT l_suppkey, count(*) AS k FROM lineitem GROUP BY 1)")
def _(spark, sf_dir):
    """A supplier's lines as a shard."""
    k = table(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("keys_per_shard"))
    return k.select("l_suppkey", "keys_per_shard", each(spark, lambda k: planning.alpha_plan(k) * 1e6, "keys_per_shard").alias("alpha_millionths"))


@register("access_model_icm", f"SELECT q AS r, n, CAST(128 * q AS BIGINT) AS bits_read FROM {QUANTITIES}")
def _(spark, sf_dir):
    """Bits that one lookup reads where values are as wide as the lines' quantities."""
    return quantities(spark, sf_dir).select(F.col("q").alias("r"), "n", each(spark, lambda r: planning.access_model("icm", 64, r)["bits"], "q").alias("bits_read"))


@register("info_bound_grid", f"SELECT q AS k, n, CAST(round(-log2(pow(2, -q) * 0.75) * 1e6) AS BIGINT) AS bound_millionths FROM {QUANTITIES}")
def _(spark, sf_dir):
    """Rates of three quarters of 2^-k, k being the lines' quantities."""
    return quantities(spark, sf_dir).select(F.col("q").alias("k"), "n", each(spark, lambda k: planning.info_bound(0.75 * 2.0**-k) * 1e6, "q").alias("bound_millionths"))


@register("bits_for_budget", "SELECT true AS within_budget, true AS close_to_budget")
def _(spark, sf_dir):
    n = table(spark, sf_dir, "orders").count()
    bits = 9 * n
    spec = planning.plan_budget(n, bits)
    used = build_filter(table(spark, sf_dir, "orders"), "o_orderkey", spec.but(segment_keys=max(n, 1)), n).meta.agg(F.sum("bits")).first()[0]
    return frame(spark, [(used <= bits * 1.005, used >= bits * 0.97)], "within_budget boolean, close_to_budget boolean")


# Elasticity and layout.

ZERO_MISS = "SELECT '{0}' AS part, count(*) AS n, CAST(0 AS BIGINT) AS misses FROM orders"


@register("trim_no_false_negative", " UNION ALL ".join(ZERO_MISS.format(r) for r in ("7", "6.5", "4", "1")))
def _(spark, sf_dir):
    return misses(spark, sf_dir, lambda f: [(str(r), elastic.trim(f, r)) for r in (7, 6.5, 4, 1)])


@register("split_no_false_negative", " UNION ALL ".join(ZERO_MISS.format(k) for k in ("0", "1", "2")))
def _(spark, sf_dir):
    return misses(spark, sf_dir, lambda f: [(str(i), p) for i, p in enumerate(elastic.split_columns(f, [3, 3, 1]))])


def misses(spark, sf_dir, parts):
    orders = table(spark, sf_dir, "orders")
    out = None
    for name, flt in parts(build_filter(orders, "o_orderkey", STANDARD.but(r=7))):
        one = measures.count_false_negatives(flt, orders, "o_orderkey").withColumn("part", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


@register("repartition_no_false_negative", "SELECT count(*) AS n, CAST(0 AS BIGINT) AS misses FROM orders")
def _(spark, sf_dir):
    orders = table(spark, sf_dir, "orders").select("o_orderkey")
    parts = elastic.repartition_filter(build_filter(orders, "o_orderkey", STANDARD), [40, 90])
    got = None
    for _, _, part in parts:
        one = probe(orders, part, "o_orderkey", "m").where("m").select("o_orderkey")
        got = one if got is None else got.unionByName(one)
    return orders.join(got.distinct().withColumn("found", F.lit(True)), "o_orderkey", "left").agg(F.count("*").alias("n"), F.sum(F.col("found").isNull().cast("long")).alias("misses"))


@register("probe_modes_agree", "SELECT true AS agree")
def _(spark, sf_dir):
    orders = table(spark, sf_dir, "orders").select((F.col("o_orderkey") * 3).alias("k"))
    flt = build_filter(table(spark, sf_dir, "orders"), "o_orderkey", BALANCED)
    got = [probe(orders, flt, "k", mode=m).where("maybe").agg(F.count("*"), F.sum("k")).first() for m in ("block_broadcast", "block_shuffle", "broadcast")]
    return frame(spark, [(got[0] == got[1] == got[2],)], "agree boolean")


@register("saved_filter_round_trip", "SELECT count(*) AS n, CAST(0 AS BIGINT) AS misses FROM part")
def _(spark, sf_dir):
    path, part = scratch(spark, "saved"), table(spark, sf_dir, "part")
    save(build_filter(part, "p_partkey", FilterSpec(r=6.5)), path)
    return measures.count_false_negatives(load(spark, path), part, "p_partkey")


@register("filter_dump_shape", "SELECT CAST(64 * 8 AS BIGINT) AS n_bits")
def _(spark, sf_dir):
    flt = build_filter(table(spark, sf_dir, "region"), "r_regionkey", FilterSpec(variant="standard", w=16, r=8))
    return filter_dump(flt).agg(F.count("*").alias("n_bits"))


# Runs, strings, text.


@register("run_skip_lookup", "SELECT o_orderkey, o_custkey, CAST(strftime(o_orderdate, '%Y%m') AS INTEGER) AS run_id FROM orders")
def _(spark, sf_dir):
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", F.date_format("o_orderdate", "yyyyMM").cast("int").alias("run_id"))
    store = write_runs(orders, "run_id", ["o_orderkey"], scratch(spark, "runs"))
    return multi_get(store, orders).select("o_orderkey", "o_custkey", "run_id")


@register("monthly_runs_meta", "SELECT run_id AS segment, n_rows, CAST(greatest(ceil(ceil(n_rows * 1.25) / 64.0) * 64, 128) AS BIGINT) AS m FROM (SELECT CAST(strftime(o_orderdate, '%Y%m') AS INTEGER) AS run_id, count(*) AS n_rows FROM orders GROUP BY 1)")
def _(spark, sf_dir):
    """One system for each run, whatever its size."""
    orders = table(spark, sf_dir, "orders").withColumn("run_id", F.date_format("o_orderdate", "yyyyMM").cast("int"))
    return build_filter(orders, "o_orderkey", STANDARD.but(eps=0.25), run="run_id", parts=1).meta.select(F.shiftright("segment", 24).cast("int").alias("segment"), "n_rows", "m")


WORDS_SQL = "SELECT {id} AS id, string_split(trim(regexp_replace(lower(text), '\\s+', ' ', 'g')), ' ') AS w FROM {table} WHERE text IS NOT NULL"
SHINGLE_SQL = "SELECT DISTINCT id, array_to_string(w[i + 1 : i + 8], ' ') AS shingle FROM ({words}), LATERAL (SELECT unnest(range(0, len(w) - 7)) AS i)"


@register("contamination_shingles", f"WITH d AS ({SHINGLE_SQL.format(words=WORDS_SQL.format(id='doc_id', table='documents'))}), b AS (SELECT DISTINCT shingle FROM ({SHINGLE_SQL.format(words=WORDS_SQL.format(id='item_id', table='benchmark'))})) SELECT id AS doc_id, count(*) AS n_shingles FROM d SEMI JOIN b USING (shingle) GROUP BY 1")
def _(spark, sf_dir):
    return engine.contamination(spark, sf_dir)


@register("url_membership", "SELECT count(DISTINCT url) AS n, CAST(0 AS BIGINT) AS misses FROM pages")
def _(spark, sf_dir):
    pages = table(spark, sf_dir, "pages")
    return measures.count_false_negatives(build_filter(pages, "url", STANDARD), pages, "url")


def first_copies(spark, sf_dir, name, id_column):
    """Texts that occur more than once: a filter of repeated 64-bit hashes, then groups by whole digests; texts stay put."""
    rows = table(spark, sf_dir, name).where("text is not null").select(id_column, F.xxhash64("text").alias("h"), F.md5("text").alias("text_md5"), F.sha2("text", 256).alias("s"))
    repeated = rows.groupBy("h").agg(F.count("*").alias("n")).where("n > 1").select("h")
    near = verified_semi(rows, repeated, ["h"], ["h"], STANDARD)
    return near.groupBy("h", "text_md5", "s").agg(F.count("*").alias("n"), F.min(id_column).alias("least_id")).where("n > 1").select("text_md5", "n", "least_id")


@register("text_dedup_verified", "SELECT md5(text) AS text_md5, count(*) AS n, min(doc_id) AS least_id FROM documents WHERE text IS NOT NULL GROUP BY text HAVING count(*) > 1")
def _(spark, sf_dir):
    return first_copies(spark, sf_dir, "documents", "doc_id")


@register("conv_dedup_verified", "SELECT md5(text) AS text_md5, count(*) AS n, min(conv_id) AS least_id FROM conversations WHERE text IS NOT NULL GROUP BY text HAVING count(*) > 1")
def _(spark, sf_dir):
    return first_copies(spark, sf_dir, "conversations", "conv_id")


@register("prefix_bloom", "SELECT count(DISTINCT substr(url, 1, 16)) AS n, CAST(0 AS BIGINT) AS misses FROM pages")
def _(spark, sf_dir):
    pages = table(spark, sf_dir, "pages").select(F.substring("url", 1, 16).alias("p"))
    return measures.count_false_negatives(segmented.build(pages, "p", "bloom"), pages, "p")


@register("stream_window_probe", "SELECT time_bucket(INTERVAL '1 day', ts) AS window_start, count(*) AS n, CAST(count(*) AS BIGINT) AS n_maybe FROM events GROUP BY 1")
def _(spark, sf_dir):
    events = table(spark, sf_dir, "events")
    flt = build_filter(table(spark, sf_dir, "customer"), "c_custkey")
    return window_counts(probe(events.withColumn("ts", F.col("ts").cast("timestamp")), flt, "user_id"), "1 day").withColumn("window_start", F.col("window_start").cast("timestamp_ntz"))


@register("two_structures_no_false_negative", "SELECT count(*) AS n, CAST(0 AS BIGINT) AS misses FROM orders")
def _(spark, sf_dir):
    orders = table(spark, sf_dir, "orders")
    got = surface.probe_structures(orders, surface.split_structures(orders, "o_orderkey", 5.5, STANDARD), "o_orderkey", "m")
    return got.agg(F.count("*").alias("n"), F.sum((~F.col("m")).cast("long")).alias("misses"))


@register("sql_surface", "SELECT count(*) AS n, CAST(0 AS BIGINT) AS misses FROM orders")
def _(spark, sf_dir):
    orders = table(spark, sf_dir, "orders")
    surface.register_sql(spark, build_filter(orders, "o_orderkey", STANDARD), "orders_filter")
    orders.createOrReplaceTempView("orders_in")
    return spark.sql("SELECT count(*) AS n, sum(CASE WHEN orders_filter_might_be_member(xxhash64(o_orderkey)) THEN CAST(0 AS BIGINT) ELSE 1 END) AS misses FROM orders_in")


@register("jvm_bloom_sketch", "SELECT true AS no_misses, true AS rate_as_asked")
def _(spark, sf_dir):
    """The engine's sketch, asked about every customer and about as many other keys in a column expression."""
    c = table(spark, sf_dir, "customer").select("c_custkey")
    n = c.count()
    sketch = surface.jvm_bloom(c, "c_custkey", n, 0.01)
    missed = c.where(~surface.jvm_might_contain(spark, sketch, "c_custkey")).count()
    hits = c.select((F.col("c_custkey") + 10**9).alias("k")).where(surface.jvm_might_contain(spark, sketch, "k")).count()
    return frame(spark, [(missed == 0, hits <= 0.01 * n + 5 * math.sqrt(0.01 * n) + 1)], "no_misses boolean, rate_as_asked boolean")


@register("layouts_agree", "SELECT true AS agree")
def _(spark, sf_dir):
    """The blocks of a filter of the orders, 256 at a time, packed in every layout, unpacked and asked."""
    import numpy as np
    import pyarrow as pa

    from bandloom.functions import layout

    asked = [(s, (0x9E3779B97F4A7C15 * (s + 1) & (2**64 - 1)) | 1) for s in (0, 1, 63, 64, 100, 191)]

    def agree(it):
        for batch in it:
            every = np.array(batch.column("words").to_pylist(), np.int64).view(np.uint64).reshape(-1, 6)
            for at in range(0, len(every), 256):
                words = every[at : at + 256]
                rows, m = layout.rows_of(words), 64 * len(words)
                packed = {name: layout.pack(rows, 6, name) for name in layout.LAYOUTS}
                mine = [(s, c) for s, c in asked if s + 64 <= m]
                answers = [[layout.query(packed[n], m, 6, n, s, c, 64) for s, c in mine] for n in layout.LAYOUTS]
                same = (packed["icm"] == words).all() and all((layout.unpack(packed[n], m, 6, n) == rows).all() for n in layout.LAYOUTS)
                yield pa.RecordBatch.from_pydict({"same": pa.array([bool(same and answers[0] == answers[1] == answers[2])])})

    blocks = build_filter(table(spark, sf_dir, "orders"), "o_orderkey", FilterSpec(variant="standard", r=6)).blocks
    return blocks.select("words").mapInArrow(agree, "same boolean").agg(F.coalesce(F.bool_and("same"), F.lit(False)).alias("agree"))


@register("negative_sample", "SELECT segment, count(*) AS n FROM (SELECT CAST(('0x' || substr(md5('7:' || CAST(o_orderkey AS VARCHAR)), 1, 8)) AS BIGINT) % 16 AS b, o_orderkey % 4 AS segment FROM orders) WHERE b = 3 GROUP BY 1")
def _(spark, sf_dir):
    """A repeatable 1-in-16 sample by hash, stratified."""
    d = portable_digest(F.col("o_orderkey"), 7)
    return table(spark, sf_dir, "orders").where(d["start32"] % 16 == 3).groupBy((F.col("o_orderkey") % 4).alias("segment")).agg(F.count("*").alias("n"))


@register("stratified_sample", "SELECT o_orderstatus, true AS share_ok FROM orders GROUP BY 1")
def _(spark, sf_dir):
    """sampleBy with a share for each stratum; each stratum's share within five deviations."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus")
    shares = {"F": 0.5, "O": 0.2, "P": 0.8}
    taken = orders.sampleBy("o_orderstatus", shares, seed=5).groupBy("o_orderstatus").agg(F.count("*").alias("k"))
    share = F.coalesce(*[F.when(F.col("o_orderstatus") == k, v) for k, v in shares.items()])
    whole = orders.groupBy("o_orderstatus").agg(F.count("*").alias("n")).join(taken, "o_orderstatus", "left")
    return whole.select("o_orderstatus", (F.abs(F.coalesce("k", F.lit(0)) - share * F.col("n")) <= 5 * F.sqrt(share * (1 - share) * F.col("n")) + 1).alias("share_ok"))


@register("filter_source", "SELECT CAST(count(*) AS BIGINT) AS n, CAST(0 AS BIGINT) AS misses, true AS bits_agree FROM part")
def _(spark, sf_dir):
    """A saved filter read back as a data source, and its bits by the table function against the words' own."""
    from bandloom.sources import reader

    path, part = scratch(spark, "source"), table(spark, sf_dir, "part")
    flt = build_filter(part, "p_partkey", FilterSpec(variant="standard", r=5))
    save(flt, path)
    reader.register(spark)
    again = spark.read.format("bandfilter").option("path", path)
    back = flt.but(blocks=again.load(), meta=again.option("part", "meta").load())
    flt.blocks.createOrReplaceTempView("source_blocks")
    ones = reader.dump(spark, "source_blocks").agg(F.sum("bit").alias("a")).crossJoin(flt.blocks.agg(F.sum(F.aggregate("words", F.lit(0), lambda a, x: a + F.bit_count(x))).alias("b")))
    return measures.count_false_negatives(back, part, "p_partkey").crossJoin(ones.select((F.col("a") == F.col("b")).alias("bits_agree")))


# Bounds on measured rates and overheads, on the lines' composite keys.

BOUNDED = [c | {"probes": 1_000_000 if c["r"] < 11 else 2_000_000} for c in workloads.bands() if c["r"] != 11 or c["w"] != 16]


@register("fp_within_bound", workloads.checked_sql(BOUNDED, "lines", "rate_ok"))
def _(spark, sf_dir):
    got = grids.run(spark, "bounds", workloads.keys_of(spark, sf_dir, "lines"), BOUNDED)
    return workloads.checked(got, rate_ok=workloads.rate_is_expected())


@register("overhead_within_bound", workloads.checked_sql(BOUNDED, "lines", "space_ok"))
def _(spark, sf_dir):
    got = grids.run(spark, "bounds", workloads.keys_of(spark, sf_dir, "lines"), BOUNDED)
    return workloads.checked(got, space_ok=workloads.space_is_expected())


def pois(mean: float, top: int) -> list[float]:
    out = [math.exp(-mean)]
    for k in range(1, top):
        out.append(out[-1] * mean / k)
    return out


def family_model(c: dict) -> tuple[float, float]:
    """Closed forms of a baseline's false-positive rate and of its bits per key."""
    name, r, b = c["filter"], c.get("r", 7), c.get("bits_per_key", 10.0)
    if name == "bloom":
        k = round(b * math.log(2))
        return (1 - math.exp(-k / b)) ** k, b
    if name in ("blocked_bloom", "two_block_bloom"):  # the block's load is a Poisson variable
        load = pois(512 / b, 200)
        if c.get("style") == "fixed8":
            return sum(p * (1 - (63 / 64) ** j) ** 8 for j, p in enumerate(load)), b
        k = round(b * math.log(2))
        if name == "blocked_bloom":
            return sum(p * (1 - (511 / 512) ** (k * j)) ** k for j, p in enumerate(load)), b
        # Each of the two blocks has its share of the k bits from every key that chose it.
        first, second = (k + 1) // 2, k // 2
        one = [sum(p * q * (1 - (511 / 512) ** (first * i + second * j)) ** n for i, p in enumerate(pois(512 / b, 150)) for j, q in enumerate(pois(512 / b, 150))) for n in (first, second)]
        return one[0] * one[1], b
    if name.startswith("cuckoo"):
        bits, load = {"cuckoo": (c.get("cell_bits", 12), c.get("load", 0.95)), "cuckoo_sorted": (16, 0.95), "cuckoo_blocked": (8, 46 * 0.9 / 64 / 4)}[name]
        return 1 - (1 - 2.0**-bits) ** (8 * load), {"cuckoo": bits / load, "cuckoo_sorted": 15 / load, "cuckoo_blocked": 512 / (46 * 0.9)}[name]
    if name == "quotient":
        return 1 - math.exp(-0.95 * 2.0**-r), (r + 3) / 0.95
    if name == "band_sorted":
        return 2.0**-r, 1.15 * r
    cell, expansion = (64 / 6, 1.23) if name == "xor_word" else (r, {"xor_coupled": 1.18, "sparse_gauss": 1.12}.get(name, 1.23))
    return 2.0 ** -int(cell), 1.08 * r + 0.5 if name == "xor_plus" else expansion * cell


FAMILIES = [c | {"probes": 1_000_000} for c in workloads.competitors() if c["r"] < 11 or c["filter"] in ("cuckoo", "xor", "xor_plus")]
FAMILIES += [{"filter": "sparse_gauss", "r": 8, "expansion": 1.12, "probes": 100_000}, {"filter": "band_sorted", "r": 7, "probes": 100_000}]


@register("family_rates", workloads.checked_sql(FAMILIES, "lines", "rate_ok", "space_ok"))
def _(spark, sf_dir):
    """Every baseline's sampled rate against its closed form, within five deviations and 4 %, and its bits per key within 4 %."""
    keys = grids.hashed(workloads.keys_of(spark, sf_dir, "lines"))
    got = grids.run(spark, "families", keys, FAMILIES[:-2]).unionByName(grids.run(spark, "families", keys, FAMILIES[-2:], segment_keys=4096))
    params = ("style", "bits_per_key", "cell_bits", "load", "cells_per_word", "expansion")
    models = [(c["filter"], float(c["r"]), ", ".join(f"{k}={v}" for k, v in c.items() if k in params), *family_model(c)) for c in FAMILIES]
    known = frame(spark, models, "filter string, r double, params string, model double, size double")
    joined = got.join(F.broadcast(known), ["filter", "r", "params"], "left")
    # Few keys cost whole words, and the coupled form needs more room for them.
    slack = 0.04 + 700 * F.col("segments") / F.col("n") + F.when((F.col("filter") == "xor_coupled") & (F.col("n") < 20_000 * F.col("segments")), 0.2).otherwise(0.0)
    rate_ok = F.abs(F.col("fp_rate") - F.col("model")) <= grids.five_sigma_rate(F.col("model")) + 0.04 * F.col("model")
    return workloads.checked(joined, rate_ok=rate_ok, space_ok=F.abs(F.col("bits_per_key") / F.col("size") - 1) <= slack)


# Workloads on the tables' keys. What times is rows only; every one has a twin that says what must hold.

register("workload_timing")(workloads.run_timing)
register("workload_winner_map")(workloads.run_winner_map)


@register("workload_timing_rows", workloads.checked_sql(workloads.TIMING, "lines"))
def _(spark, sf_dir):
    return workloads.checked(workloads.run_timing(spark, sf_dir))


@register("workload_winner_rows", "SELECT true AS most_cells_won, true AS caps_hold, true AS classes_hold")
def _(spark, sf_dir):
    """Who wins depends on the machine; that winners obey their cell does not."""
    won = workloads.run_winner_map(spark, sf_dir)
    factor = F.col("fp_rate") / F.col("rate")
    return won.agg((F.count("*") >= 60).alias("most_cells_won"), (F.max(F.col("overhead") - F.col("max_overhead")) <= 0).alias("caps_hold"), (F.min(factor).between(0.5, 2) & F.max(factor).between(0.5, 2)).alias("classes_hold"))


for _name, _grid, _keys, _flags in (
    ("overhead_curve", workloads.CURVE, "lines", ("rate_ok", "space_ok")), ("fractional", workloads.FRACTIONAL, "orders", ("rate_ok", "space_ok")), ("one_percent", workloads.ONE_PERCENT, "events", ("rate_ok", "space_ok")),
    ("balanced", workloads.BALANCED, "lines", ("rate_ok", "space_ok")), ("space_time", workloads.SPACE_TIME, "orders", ("rate_ok",)), ("retry_policy", workloads.RETRY, "orders", ("rate_ok", "solved")), ("sharding", workloads.SHARDS, "lines", ("rate_ok", "space_ok", "solved")),
):

    @register(f"workload_{_name}", workloads.checked_sql(_grid, _keys, *_flags))
    def _(spark, sf_dir, name=_name, flags=_flags):
        known = {"rate_ok": workloads.rate_is_expected(), "space_ok": workloads.space_is_expected(), "solved": F.col("failed") == 0}
        return workloads.checked(getattr(workloads, f"run_{name}")(spark, sf_dir), **{f: known[f] for f in flags})


@register("workload_small_n", " UNION ALL ".join(f"SELECT '{k}' AS experiment, v AS filter, CAST(200 * {workloads.count_sql(k)} AS BIGINT) AS n, CAST(0 AS BIGINT) AS misses, true AS mean_ok, true AS spread_ok FROM (VALUES ('homogeneous'), ('standard')) t(v)" for k in ("customers", "suppliers")))
def _(spark, sf_dir):
    """200 seeds: the mean rate is 2^-7 (more for the homogeneous variant), and rates scatter less with end inflation than without."""
    t, p = F.col("trials"), 2.0**-7
    mean = F.col("rate_sum") / t
    spread = F.sqrt(F.greatest(F.lit(0.0), F.col("rate_squares") / t - mean * mean))
    probes = F.col("probes") / t
    sampling = F.sqrt(p / probes)  # what 5000 probes alone scatter
    low = F.when(F.col("filter") == "standard", 1.4).otherwise(20.0)
    got = workloads.run_small_n(spark, sf_dir)
    return got.select("experiment", "filter", "n", "misses", mean.between(0.9 * p, F.when(F.col("filter") == "standard", 1.1).otherwise(1.5) * p).alias("mean_ok"), (spread <= low * sampling).alias("spread_ok"))


@register("workload_elimination_counters", f"SELECT w, eps, CAST({workloads.count_sql('orders')} AS BIGINT) AS n, true AS same_rows, true AS additions_below_displacement, true AS sorted_steps_near_displacement FROM (VALUES {', '.join(f'(CAST({w} AS INTEGER), CAST({e} AS DOUBLE))' for w in (32, 64, 128) for e in (0.25, 0.4))}) t(w, eps)")
def _(spark, sf_dir):
    """Both solvers fill the same rows; additions stay below the displacement, of which the sorted solver looks at every step."""
    got = workloads.run_elimination_counters(spark, sf_dir)
    solved = F.col("failed") == 0
    return got.select("w", "eps", "n", (F.col("same_rows") == F.col("segments")).alias("same_rows"), (~solved | (F.col("additions") <= F.col("displacement"))).alias("additions_below_displacement"), (~solved | F.col("sorted_steps").between(0.5 * F.col("displacement"), 2 * F.col("displacement") + 100)).alias("sorted_steps_near_displacement"))


@register("workload_eps_sweep", "SELECT w, CAST(r AS DOUBLE) AS r, true AS recommended_is_near_best FROM (SELECT CAST(unnest([16, 32, 64]) AS INTEGER) AS w), (SELECT unnest([1, 4, 7, 11]) AS r)")
def _(spark, sf_dir):
    """Overhead at the recommended eps is near the least of the sweep."""
    from bandloom.plans.planning import eps_homogeneous

    got = workloads.run_eps_sweep(spark, sf_dir)
    known = frame(spark, [(w, float(r), round(eps_homogeneous(r, w), 6)) for w in (16, 32, 64) for r in (1, 4, 7, 11)], "w int, r double, best_eps double")
    here = F.max(F.when(F.abs(F.col("eps") - F.col("best_eps")) < 1e-9, F.col("overhead")))
    error = F.max(F.when(F.abs(F.col("eps") - F.col("best_eps")) < 1e-9, grids.five_sigma_overhead()))
    return got.join(F.broadcast(known), ["w", "r"]).groupBy("w", "r").agg((here <= F.min("overhead") + 2 * error + 0.06 + 128 / F.max("n")).alias("recommended_is_near_best"))


PUBLISHED_MEANS = [(w, e, m, row[i]) for w in (16, 32, 64, 128) for row in (planning.STANDARD_OVERHEAD[w, "mean"],) for i, (e, m) in enumerate(((w // 2, 1 << 10), (w // 4, 1 << 10), (1, 1 << 10), (1, 1 << 14), (1, 1 << 17)))]
PUBLISHED_TAILS = [(w, e, m, planning.STANDARD_OVERHEAD[w, "0.5"][i], planning.STANDARD_OVERHEAD[w, "0.05"][i], planning.STANDARD_OVERHEAD[w, "0.001"][i]) for w in (64, 128) for i, (e, m) in enumerate(((w // 2, 1 << 10), (w // 4, 1 << 10), (1, 1 << 10), (1, 1 << 14), (1, 1 << 17)))]


@register("workload_success_table", f"SELECT w, edge, m, true AS mean_ok, true AS tails_ok FROM (VALUES {', '.join(f'(CAST({w} AS INTEGER), CAST({e} AS INTEGER), CAST({m} AS BIGINT))' for w, e, m, _ in PUBLISHED_MEANS)}) t(w, edge, m)")
def _(spark, sf_dir):
    """The table of overheads at first failure: means within five standard errors of the published ones (over 100 %: above it),
    the failure quantiles within what their trials tell."""
    means = frame(spark, PUBLISHED_MEANS, "w int, edge int, m long, mean double")
    tails = frame(spark, PUBLISHED_TAILS, "w int, edge int, m long, half double, five double, one double")
    got = simulated.run_success_table(spark).join(F.broadcast(means), ["w", "edge", "m"]).join(F.broadcast(tails), ["w", "edge", "m"], "left")
    near = F.abs(100 * F.col("mean_eps") - F.col("mean")) <= 500 * F.col("mean_error") + 0.06 + 0.02 * F.col("mean")

    def tail(mine: str, theirs: str, part: float, more: float):
        return F.coalesce(F.abs(100 * F.col(mine) - F.col(theirs)) <= part * F.col(theirs) + more, F.lit(True))

    ok = tail("eps_fail_50", "half", 0.15, 0.9) & tail("eps_fail_5", "five", 0.2, 0.5) & tail("eps_fail_01", "one", 0.4, 0.5)
    return got.select("w", "edge", "m", F.when(F.col("mean") >= 100, F.col("mean_eps") > 1).otherwise(near).alias("mean_ok"), ok.alias("tails_ok"))


@register("workload_square", "SELECT CAST(n AS BIGINT) AS n, CAST(w AS INTEGER) AS w, true AS band_ok, true AS dense_ok FROM (VALUES (64, 64), (256, 64), (1024, 64), (256, 128), (1024, 128)) t(n, w)")
def _(spark, sf_dir):
    """Square systems are regular with about 0.289: dense ones always, band ones once w is well above the root of n."""
    limit, slack = 0.2888, 5 * math.sqrt(0.2888 * 0.7112 / 400)
    got = simulated.run_square(spark)
    wide = F.col("w") >= 4 * F.sqrt("n")
    return got.select(F.col("n").cast("long"), "w", (~wide & (F.col("band_regular") < limit + slack) | wide & (F.abs(F.col("band_regular") - limit) <= slack)).alias("band_ok"), (F.abs(F.col("dense_regular") - limit) <= slack).alias("dense_ok"))


@register("workload_two_location", "SELECT CAST(m AS BIGINT) AS m, CAST(w AS INTEGER) AS w, true AS less_space, true AS loses_the_band FROM (VALUES (512, 32), (512, 64), (1024, 32), (1024, 64)) t(m, w)")
def _(spark, sf_dir):
    got = simulated.run_two_location(spark)
    return got.select(F.col("m").cast("long"), "w", (F.col("two_eps") < F.col("one_eps")).alias("less_space"), ((F.col("two_reach") > F.col("w")) & (F.col("one_reach") <= F.col("w"))).alias("loses_the_band"))


@register("workload_span_probability", "SELECT CAST(n AS BIGINT) AS n, CAST(w AS INTEGER) AS w, CAST(eps AS DOUBLE) AS eps, true AS law_holds, true AS same_for_any_n FROM (SELECT unnest([10000, 50000]) AS n), (SELECT unnest([16, 32, 64]) AS w), (SELECT unnest([0.05, 0.1, 0.2, 0.3]) AS eps)")
def _(spark, sf_dir):
    """f = p + (1 - p) 2^-r, and p, the share of fresh rows in the span, does not depend on n."""
    got = simulated.run_span_probability(spark).select(F.col("n").cast("long"), "w", "eps", "fp_rate", F.col("extra")["fp_predicted"].alias("law"), F.col("extra")["span_share"].alias("p"))
    other = Window.partitionBy("w", "eps")
    apart = F.max("p").over(other) - F.min("p").over(other)
    return got.select("n", "w", "eps", (F.abs(F.col("fp_rate") - F.col("law")) <= 5 * F.sqrt(2 * F.col("law") / 100_000)).alias("law_holds"), (apart <= 0.2 * F.max("p").over(other) + 0.003).alias("same_for_any_n"))


@register("workload_load_diagonal", "SELECT true AS ends_lag_less_with_edge")
def _(spark, sf_dir):
    lag = [r.mean_behind for r in simulated.run_load_diagonal(spark).orderBy("edge").collect()]
    return frame(spark, [(lag[0] > lag[1] > lag[2],)], "ends_lag_less_with_edge boolean")


@register("workload_access_model", """
WITH g AS (SELECT l AS layout, CAST(w AS INTEGER) AS w, CAST(r AS INTEGER) AS r FROM (SELECT unnest(['icm', 'row', 'column']) AS l), (SELECT unnest([16, 32, 64, 128]) AS w), (SELECT unnest([1, 2, 3, 6, 7, 11]) AS r)),
p AS (SELECT DISTINCT layout, w, r, CASE layout WHEN 'icm' THEN (k * w * r) % 512 WHEN 'row' THEN (2 * k) % 512 ELSE k END AS place FROM g, range(512) t(k))
SELECT layout, w, r, CAST((CASE layout WHEN 'icm' THEN 2 ELSE 1 END) * w * r AS BIGINT) AS bits_read,
  CAST(round(1e6 * (CASE layout WHEN 'column' THEN r ELSE 1 END) * avg(ceil((place + CASE layout WHEN 'icm' THEN 2 * w * r WHEN 'row' THEN w * r ELSE w END) / 512.0))) AS BIGINT) AS line_millionths
FROM p GROUP BY layout, w, r""")
def _(spark, sf_dir):
    return simulated.run_access_model(spark).select("layout", "w", "r", F.col("bits_read").cast("long"), F.round(F.col("cache_lines") * 1e6).cast("long").alias("line_millionths"))


# Workloads through the Spark operators.

ORDERS_N = "(SELECT count(*) FROM orders)"


@register("workload_probe_mix", f"SELECT f || ' ' || c AS case, CAST(CASE c WHEN 'mixed' THEN 2 ELSE 1 END * {ORDERS_N} AS BIGINT) AS n, true AS hits_ok FROM (SELECT unnest(['homogeneous', 'standard', 'balanced', 'blocked_bloom', 'xor']) AS f), (SELECT unnest(['positive', 'negative', 'mixed']) AS c)")
def _(spark, sf_dir):
    """All members, and of others at most what the rate allows, are said to be in."""
    n = table(spark, sf_dir, "orders").count()
    most = 0.012 * n + 5 * math.sqrt(0.012 * n)
    least = F.when(F.col("case").endswith("negative"), 0).otherwise(n)
    extra = F.when(F.col("case").endswith("positive"), 0.0).otherwise(most)
    return engine.run_probe_mix(spark, sf_dir).select("case", "n", F.col("n_maybe").between(least, least + extra).alias("hits_ok"))


register("workload_engine_timing")(engine.run_engine_timing)


@register("workload_engine_timing_rows", f"SELECT f AS filter, CAST({workloads.count_sql('lines')} AS BIGINT) AS n, true AS rate_ok FROM (SELECT unnest(['homogeneous', 'standard', 'balanced', 'blocked_bloom', 'xor']) AS f)")
def _(spark, sf_dir):
    return engine.run_engine_timing(spark, sf_dir).select("filter", "n", (F.col("fp_rate") < 0.016).alias("rate_ok"))


@register("workload_elasticity", "SELECT c AS case, true AS ok FROM (SELECT unnest(['trim 8', 'trim 7', 'trim 6.5', 'trim 6', 'trim 5', 'trim 4', 'trim 3', 'part 1', 'part 2', 'product', 'cut bits']) AS c)")
def _(spark, sf_dir):
    """Each dropped column doubles the rate; the parts' rates multiply to the whole filter's; a cut costs (w-1) r bits."""
    n = table(spark, sf_dir, "orders").count()
    r = F.regexp_extract("case", "[0-9.]+$", 0).try_cast("double")
    r = F.when(F.col("case").startswith("trim"), r).when(F.col("case").startswith("part"), 4.0).otherwise(8.0)
    low = F.floor(r)
    model = (1 - (r - low)) * F.pow(F.lit(2.0), -low) + (r - low) * F.pow(F.lit(2.0), -low - 1)
    slack = 5 * F.sqrt(model / n) + 0.06 * model
    ok = F.when(F.col("case") == "cut bits", F.col("value") == 63 * 8).when(F.col("case") == "product", F.col("value") <= 3 * model).otherwise(F.abs(F.col("value") - model) <= slack)
    return engine.run_elasticity(spark, sf_dir).select("case", ok.alias("ok"))


register("workload_latency")(engine.run_latency)


@register("workload_latency_rows", f"SELECT 'single' AS case, CAST(1 AS BIGINT) AS n, CAST(1 AS BIGINT) AS n_maybe UNION ALL SELECT 'batch', {ORDERS_N}, {ORDERS_N}")
def _(spark, sf_dir):
    return engine.run_latency(spark, sf_dir).select("case", "n", "n_maybe")


@register("workload_string_keys", f"SELECT 'url' AS case, count(DISTINCT url) AS n, CAST(0 AS BIGINT) AS misses, true AS rate_ok FROM pages UNION ALL SELECT 'text', count(DISTINCT text), 0, true FROM documents UNION ALL SELECT 'turn', count(DISTINCT text), 0, true FROM conversations UNION ALL SELECT 'shingle', count(DISTINCT shingle), 0, true FROM ({SHINGLE_SQL.format(words=WORDS_SQL.format(id='item_id', table='benchmark'))})")
def _(spark, sf_dir):
    return engine.run_string_keys(spark, sf_dir).select("case", "n", "misses", (F.col("fp_rate") <= 2.0**-7 + 5 * F.sqrt(2.0**-7 / F.col("n")) + 2 / F.col("n")).alias("rate_ok"))


JOINS = ("SELECT count(*) FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_orderstatus = 'F'", "SELECT count(*) FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = 'BUILDING'")


@register("workload_join_prefilter", " UNION ALL ".join(f"SELECT '{c}' AS case, f AS filter, ({q}) AS n_joined, true AS shuffles_less FROM (SELECT unnest(['none', 'band', 'blocked_bloom', 'engine', 'exact']) AS f)" for c, q in zip(("lines of finished orders", "orders of a segment"), JOINS, strict=True)))
def _(spark, sf_dir):
    """Every way joins the same rows; a filter shuffles little more than the exact semi-join would, in rows and in bytes."""
    got = engine.run_join_prefilter(spark, sf_dir)
    of = Window.partitionBy("case")
    exact, none = (F.max(F.when(F.col("filter") == k, F.col("n_shuffled"))).over(of) for k in ("exact", "none"))
    bytes_none = F.max(F.when(F.col("filter") == "none", F.col("shuffle_bytes"))).over(of)
    few = (F.col("n_shuffled") <= exact + 0.03 * (none - exact) + 30) & (F.col("shuffle_bytes") < bytes_none)
    return got.select("case", "filter", "n_joined", (F.col("filter").isin("none", "engine") | few).alias("shuffles_less"))


# Keys whose sides differ in type, further shardings and layouts, runs that grow until they fail.


@register("decimal_key_semi_join", "SELECT o_orderkey FROM orders WHERE CAST(o_totalprice AS DECIMAL(14,1)) IN (SELECT CAST(o_totalprice AS DECIMAL(16,2)) FROM orders WHERE o_orderstatus = 'F') ")
def _(spark, sf_dir):
    orders = table(spark, sf_dir, "orders")
    left = orders.select("o_orderkey", F.col("o_totalprice").cast("decimal(14,1)").alias("k"))
    right = orders.where("o_orderstatus = 'F'").select(F.col("o_totalprice").cast("decimal(16,2)").alias("k"))
    return verified_semi(left, right, ["k"], ["k"], STANDARD).select("o_orderkey")


@register("mixed_type_anti_join", "SELECT o_orderkey FROM orders WHERE CAST(o_orderkey AS DECIMAL(20,3)) NOT IN (SELECT CAST(l_orderkey AS DOUBLE) FROM lineitem WHERE l_quantity > 40)")
def _(spark, sf_dir):
    left = table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_orderkey").cast("decimal(20,3)").alias("k"))
    right = table(spark, sf_dir, "lineitem").where("l_quantity > 40").select(F.col("l_orderkey").cast("double").alias("j"))
    return verified_anti(left, right, ["k"], ["j"], STANDARD).select("o_orderkey")


@register("date_key_semi_join", "SELECT event_id FROM events WHERE CAST(ts AS DATE) IN (SELECT CAST(o_orderdate AS DATE) FROM orders)")
def _(spark, sf_dir):
    left = table(spark, sf_dir, "events").select("event_id", F.date_trunc("day", F.col("ts")).alias("k"))
    return verified_semi(left, table(spark, sf_dir, "orders").select(F.col("o_orderdate").cast("date").alias("k")), ["k"], ["k"], STANDARD).select("event_id")


SHARDED = {"until_failure": STANDARD.but(sharding="until_failure"), "fixed_bytes": HOMOGENEOUS.but(sharding="fixed_bytes", segment_keys=4096), "soft": STANDARD.but(sharding="soft", edge=1), "row_layout": HOMOGENEOUS.but(layout="row"), "column_layout": STANDARD.but(layout="column", r=2)}
for _name, _spec in SHARDED.items():

    @register(f"{_name}_no_false_negative", "SELECT n, misses, true AS rate_ok FROM (" + NO_MISS + ")")
    def _(spark, sf_dir, spec=_spec):
        lines = table(spark, sf_dir, "lineitem")
        flt = build_filter(lines, "l_orderkey", spec)
        others = table(spark, sf_dir, "orders").select((F.col("o_orderkey") + 10**9).alias("l_orderkey"))
        p = 2.0 ** -int(spec.r)
        rate = measures.measure_fp(flt, others, "l_orderkey").select((F.col("fp_rate") <= 1.4 * p + 5 * F.sqrt(p / F.col("n"))).alias("rate_ok"))
        return measures.count_false_negatives(flt, lines, "l_orderkey").crossJoin(rate)


@register("sharding_by_size", "SELECT true AS one_size, true AS widths_differ")
def _(spark, sf_dir):
    """Segments of fixed bytes have one size up to a word a column, and result widths that follow from their keys."""
    flt = build_filter(table(spark, sf_dir, "lineitem"), engine.LINE_KEY, HOMOGENEOUS.but(sharding="fixed_bytes", segment_keys=1000))
    return flt.meta.agg((F.max("bits") - F.min("bits") <= 128).alias("one_size"), (F.count_distinct("r") > 1).alias("widths_differ"))


@register("prefix_run_lookup", "SELECT count(*) AS n, CAST(0 AS BIGINT) AS misses, true AS rate_ok FROM events")
def _(spark, sf_dir):
    """Events as a stream, closed into runs that end at the first key that does not fit; every event is found again."""
    from bandloom.streaming.streams import prefix_runs, probe_prefix_runs

    path, spec, events = scratch(spark, "prefix"), STANDARD.but(r=12), table(spark, sf_dir, "events")
    stream = spark.readStream.schema(events.schema).parquet(f"{sf_dir}/events.parque[t]")  # a pattern, as a stream's path is a folder or one
    prefix_runs(stream, ["event_id"], 4, spec).writeStream.outputMode("append").format("parquet").option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start(f"{path}/runs").awaitTermination()
    runs = spark.read.parquet(f"{path}/runs")
    both = events.select("event_id", F.lit(True).alias("is_in")).unionByName(events.select((F.col("event_id") + 10**9).alias("event_id"), F.lit(False).alias("is_in")))
    got = probe_prefix_runs(both, ["event_id"], runs, 4, spec)
    n = F.count_if("is_in")
    per_shard = runs.where("closed").count() / 4 + 1  # a key asks all runs of its shard
    return got.agg(n.alias("n"), F.count_if(F.col("is_in") & ~F.col("maybe")).alias("misses"), (F.count_if(~F.col("is_in") & F.col("maybe")) <= 1.5 * per_shard * 2.0**-12 * n + 20).alias("rate_ok"))


@register("sliding_window_probe", "SELECT w AS window_start, count(*) AS n, CAST(count(*) AS BIGINT) AS n_maybe FROM (SELECT time_bucket(INTERVAL '12 hours', ts) - INTERVAL '12 hours' * k AS w FROM events, range(2) t(k)) GROUP BY 1")
def _(spark, sf_dir):
    events = table(spark, sf_dir, "events")
    flt = build_filter(table(spark, sf_dir, "customer"), "c_custkey")
    got = window_counts(probe(events.withColumn("ts", F.col("ts").cast("timestamp")), flt, "user_id"), "1 day", slide="12 hours")
    return got.withColumn("window_start", F.col("window_start").cast("timestamp_ntz"))


@register("balanced_counters", f"SELECT CAST({workloads.count_sql('lines')} AS BIGINT) AS n, true AS eight_bits_a_shard, true AS about_a_hundredth_a_key, true AS displaced, true AS added")
def _(spark, sf_dir):
    """Metadata of the balanced variant: 8 bits for each soft shard, about 0.008 bits a key at 1000 keys a shard."""
    flt = build_filter(table(spark, sf_dir, "lineitem"), engine.LINE_KEY, BALANCED)
    got = flt.meta.select("n_rows", (8 * F.size("defer")).alias("flags"), (8 * F.aggregate("shards", F.lit(0), lambda a, x: a + x)).alias("want"), "displacement", "additions").agg(F.sum("n_rows").alias("n"), F.sum("flags").alias("flags"), F.sum("want").alias("want"), F.sum("displacement").alias("d"), F.sum("additions").alias("a"))
    per_key = F.col("flags") / F.col("n")
    return got.select("n", (F.col("flags") == F.col("want")).alias("eight_bits_a_shard"), per_key.between(0.005, 0.016).alias("about_a_hundredth_a_key"), (F.col("d") > F.col("n")).alias("displaced"), (F.col("a") > F.col("n")).alias("added"))


@register("workload_static", "SELECT f AS function, CAST(0 AS BIGINT) AS n_wrong FROM (SELECT unnest(['priority', 'nation', 'size', 'supplier', 'label', 'event_type', 'doc_label', 'custkey', 'wide']) AS f)")
def _(spark, sf_dir):
    return engine.run_static(spark, sf_dir).select("function", "n_wrong")


@register("workload_run_skipping", "SELECT CAST(count(*) * (SELECT count(DISTINCT strftime(o_orderdate, '%Y%m')) FROM orders) AS BIGINT) AS n_pairs, count(*) AS n_real, true AS few_left FROM orders")
def _(spark, sf_dir):
    return engine.run_run_skipping(spark, sf_dir).select("n_pairs", "n_real", (F.col("n_candidates") <= F.col("n_real") + 0.02 * F.col("n_pairs") + 20).alias("few_left"))


@register("build_counters", "SELECT count(*) AS n, CAST(0 AS BIGINT) AS metadata_bits FROM orders")
def _(spark, sf_dir):
    return measures.build_counters(build_filter(table(spark, sf_dir, "orders"), "o_orderkey", STANDARD)).select("n", F.col("metadata_bits").cast("long"))
