"""The surrounding operators on key and probe frames: joins, aggregations, windows, set operations, functions."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from bandloom.operators.build import build_filter
from bandloom.operators.probe import probe
from bandloom.queries.core import STANDARD, register
from bandloom.runtime import table


def flagged(spark, sf_dir):
    """Orders with a verified membership flag: has a line with quantity over 45."""
    lines = table(spark, sf_dir, "lineitem").where("l_quantity > 45").select("l_orderkey")
    marked = probe(table(spark, sf_dir, "orders"), build_filter(lines, "l_orderkey", STANDARD), "o_orderkey")
    exact = lines.select(F.col("l_orderkey").alias("o_orderkey")).distinct().withColumn("big", F.lit(1))
    return marked.join(exact, "o_orderkey", "left").withColumn("big", F.when(F.col("maybe") & F.col("big").isNotNull(), 1).otherwise(0))


FLAGGED = "(SELECT o.*, CASE WHEN o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45) THEN 1 ELSE 0 END AS big FROM orders o)"

for _kind in ("cube", "rollup"):

    @register(f"op_{_kind}", f"SELECT o_orderstatus, o_orderpriority, CAST(grouping(o_orderstatus) * 2 + grouping(o_orderpriority) AS BIGINT) AS gid, count(*) AS n, CAST(sum(big) AS BIGINT) AS n_big FROM {FLAGGED} GROUP BY {_kind} (o_orderstatus, o_orderpriority)")
    def _(spark, sf_dir, kind=_kind):
        grouped = getattr(flagged(spark, sf_dir), kind)("o_orderstatus", "o_orderpriority")
        return grouped.agg(F.grouping_id().alias("gid"), F.count("*").alias("n"), F.sum("big").alias("n_big"))


@register("op_grouping_sets", f"SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM {FLAGGED} GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def _(spark, sf_dir):
    status, priority = F.col("o_orderstatus"), F.col("o_orderpriority")
    return flagged(spark, sf_dir).groupingSets([[status], [priority], []], status, priority).agg(F.count("*").alias("n"))


@register("op_windows", "SELECT o_custkey, o_orderkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER p AS INTEGER) AS rk, CAST(dense_rank() OVER p AS INTEGER) AS dr, CAST(ntile(4) OVER w AS INTEGER) AS nt, lead(o_orderkey) OVER w AS nxt, lag(o_orderkey) OVER w AS prv, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS last3 FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey), p AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def _(spark, sf_dir):
    w, p = Window.partitionBy("o_custkey").orderBy("o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return table(spark, sf_dir, "orders").select(
        "o_custkey", "o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(p).alias("rk"), F.dense_rank().over(p).alias("dr"), F.ntile(4).over(w).alias("nt"),
        F.lead("o_orderkey").over(w).alias("nxt"), F.lag("o_orderkey").over(w).alias("prv"), F.count("*").over(w.rowsBetween(-2, 0)).alias("last3"),
    )


@register("op_top_k", "SELECT o_orderkey, o_custkey FROM orders ORDER BY o_orderkey DESC LIMIT 25")
def _(spark, sf_dir):
    return table(spark, sf_dir, "orders").orderBy(F.col("o_orderkey").desc()).limit(25).select("o_orderkey", "o_custkey")


@register("op_top_k_offset", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 30")
def _(spark, sf_dir):
    return table(spark, sf_dir, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").offset(30).limit(20).select("o_orderkey", "o_totalprice")


def line_keys(spark, sf_dir):
    t = table(spark, sf_dir, "lineitem")
    return t.where("l_quantity > 40").select("l_orderkey"), t.where("l_discount > 0.05").select("l_orderkey")


PAIR = ("SELECT l_orderkey FROM lineitem WHERE l_quantity > 40", "SELECT l_orderkey FROM lineitem WHERE l_discount > 0.05")
for _op, _method, _sql in (("union", "union", "UNION ALL"), ("intersect", "intersect", "INTERSECT"), ("intersect_all", "intersectAll", "INTERSECT ALL"), ("except", "subtract", "EXCEPT"), ("except_all", "exceptAll", "EXCEPT ALL")):

    @register(f"op_{_op}", f"SELECT l_orderkey, count(*) AS n FROM ({PAIR[0]} {_sql} {PAIR[1]}) GROUP BY 1")
    def _(spark, sf_dir, method=_method):
        a, b = line_keys(spark, sf_dir)
        return getattr(a, method)(b).groupBy("l_orderkey").agg(F.count("*").alias("n"))


for _how in ("inner", "left", "right", "full"):

    @register(f"op_join_{_how}", f"SELECT c_nationkey, s_nationkey, c, s FROM (SELECT c_nationkey, count(*) AS c FROM customer WHERE c_acctbal > 0 GROUP BY 1) a {_how.upper()} JOIN (SELECT s_nationkey, count(*) AS s FROM supplier WHERE s_acctbal > 0 GROUP BY 1) b ON c_nationkey = s_nationkey")
    def _(spark, sf_dir, how=_how):
        a = table(spark, sf_dir, "customer").where("c_acctbal > 0").groupBy("c_nationkey").agg(F.count("*").alias("c"))
        b = table(spark, sf_dir, "supplier").where("s_acctbal > 0").groupBy("s_nationkey").agg(F.count("*").alias("s"))
        return a.join(b, F.col("c_nationkey") == F.col("s_nationkey"), how)


for _hint in ("broadcast", "shuffle_hash", "merge"):

    @register(f"op_join_hint_{_hint}", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
    def _(spark, sf_dir, hint=_hint):
        c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_mktsegment").hint(hint)
        return table(spark, sf_dir, "orders").select("o_custkey").join(c, "o_custkey").groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@register("op_as_of_join", "SELECT e.event_id, max(o.o_orderkey) AS last_order FROM events e LEFT JOIN (SELECT o_custkey, o_orderdate, max(o_orderkey) AS o_orderkey FROM orders GROUP BY 1, 2) o ON e.user_id = o.o_custkey AND o.o_orderdate = (SELECT max(o_orderdate) FROM orders x WHERE x.o_custkey = e.user_id AND x.o_orderdate <= e.ts) GROUP BY 1")
def _(spark, sf_dir):
    """Newest order of the user at or before each event: a union sorted by time, and a running last value."""
    e = table(spark, sf_dir, "events").select(F.col("user_id").alias("k"), F.col("ts").alias("t"), "event_id", F.lit(None).cast("long").alias("o"))
    o = table(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("t")).agg(F.max("o_orderkey").alias("o")).select("k", "t", F.lit(None).cast("long").alias("event_id"), "o")
    w = Window.partitionBy("k").orderBy("t", F.col("o").isNull()).rowsBetween(Window.unboundedPreceding, 0)
    return e.unionByName(o).withColumn("last_order", F.last("o", True).over(w)).where("event_id is not null").select("event_id", "last_order")


@register("op_range_join", "SELECT lo, count(*) AS n FROM (SELECT unnest(range(0, 15000, 500)) AS lo) JOIN orders ON o_custkey >= lo AND o_custkey < lo + 500 GROUP BY 1")
def _(spark, sf_dir):
    """Ranges are cut into buckets, so the join has an equality."""
    ranges = spark.range(0, 15000, 500).select(F.col("id").alias("lo"), (F.col("id") + 500).alias("hi")).withColumn("b", F.explode(F.sequence(F.floor(F.col("lo") / 1000), F.floor((F.col("hi") - 1) / 1000))))
    orders = table(spark, sf_dir, "orders").select("o_custkey", F.floor(F.col("o_custkey") / 1000).alias("b"))
    return orders.join(F.broadcast(ranges), "b").where("o_custkey >= lo and o_custkey < hi").groupBy("lo").agg(F.count("*").alias("n"))


@register("op_theta_join", "SELECT cap, count(*) AS n FROM (SELECT unnest([0, 10, 20, 30, 40]) AS cap) JOIN part ON p_size <= cap GROUP BY 1")
def _(spark, sf_dir):
    caps = spark.createDataFrame([(c,) for c in (0, 10, 20, 30, 40)], "cap int")
    return table(spark, sf_dir, "part").select("p_size").join(F.broadcast(caps), F.col("p_size") <= F.col("cap")).groupBy("cap").agg(F.count("*").alias("n"))


@register("op_bit_aggregates", "SELECT c_nationkey, bit_or(c_custkey) AS o, bit_and(c_custkey) AS a, bit_xor(c_custkey) AS x FROM customer GROUP BY 1")
def _(spark, sf_dir):
    return table(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.bit_or("c_custkey").alias("o"), F.bit_and("c_custkey").alias("a"), F.bit_xor("c_custkey").alias("x"))


@register("op_object_aggregates", "SELECT event_type, list_sort(list(DISTINCT user_id % 7)) AS users, max_by(event_id, event_id) AS last_id, CAST(count(DISTINCT user_id) AS BIGINT) AS n_users FROM events GROUP BY 1")
def _(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.array_sort(F.collect_set(F.col("user_id") % 7)).alias("users"), F.max_by("event_id", "event_id").alias("last_id"), F.count_distinct("user_id").alias("n_users"))


@register("op_approx_distinct", "SELECT true AS close_hll, true AS close_sketch")
def _(spark, sf_dir):
    n = F.count_distinct("l_orderkey")
    got = table(spark, sf_dir, "lineitem").agg(n.alias("n"), F.approx_count_distinct("l_orderkey", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("l_orderkey")).alias("h"))
    return got.select((F.abs(F.col("a") - F.col("n")) < 0.1 * F.col("n")).alias("close_hll"), (F.abs(F.col("h") - F.col("n")) < 0.1 * F.col("n")).alias("close_sketch"))


@register("op_strings", "SELECT c_custkey, lower(trim(c_name)) AS low, regexp_replace(c_name, '[^0-9]', '', 'g') AS digits, CAST(length(c_name) AS INTEGER) AS len, md5(c_name) AS h, substr(c_mktsegment, 1, 3) AS seg, c_name LIKE '%1' AS ends_1 FROM customer")
def _(spark, sf_dir):
    c = table(spark, sf_dir, "customer")
    return c.select("c_custkey", F.lower(F.trim("c_name")).alias("low"), F.regexp_replace("c_name", "[^0-9]", "").alias("digits"), F.length("c_name").alias("len"), F.md5("c_name").alias("h"), F.substring("c_mktsegment", 1, 3).alias("seg"), F.col("c_name").like("%1").alias("ends_1"))


@register("op_dates", "SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS m, count(*) AS n, CAST(min(date_diff('day', DATE '1990-01-01', CAST(o_orderdate AS DATE))) AS INTEGER) AS first_day FROM orders GROUP BY 1")
def _(spark, sf_dir):
    o = table(spark, sf_dir, "orders")
    return o.groupBy(F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("m")).agg(F.count("*").alias("n"), F.min(F.datediff("o_orderdate", F.lit("1990-01-01").cast("date"))).alias("first_day"))


@register("op_bits", "SELECT o_orderkey, (o_orderkey << 3) & 1023 AS s, o_orderkey >> 2 AS r, CAST(bit_count(o_orderkey) AS INTEGER) AS b, xor(o_orderkey, 255) AS x, CAST((o_orderkey >> 4) & 1 AS TINYINT) AS bit4 FROM orders")
def _(spark, sf_dir):
    k = F.col("o_orderkey")
    return table(spark, sf_dir, "orders").select("o_orderkey", F.shiftleft(k, 3).bitwiseAND(F.lit(1023).cast("long")).alias("s"), F.shiftright(k, 2).alias("r"), F.bit_count(k).alias("b"), k.bitwiseXOR(F.lit(255).cast("long")).alias("x"), F.getbit(k, F.lit(4)).alias("bit4"))


@register("op_arrays", "SELECT vec_id, CAST(len(embedding) AS INTEGER) AS dims, list_transform(range(3), lambda i: CAST(floor(embedding[i + 1] * 100) AS BIGINT)) AS head FROM embeddings")
def _(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select("vec_id", F.size("embedding").alias("dims"), F.transform(F.slice("embedding", 1, 3), lambda x: F.floor(x * 100)).alias("head"))


@register("op_json", "SELECT event_type, count(*) AS n, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS k_sum FROM events GROUP BY 1")
def _(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k_sum"))


@register("op_maps", "SELECT c_nationkey, r_name FROM (SELECT DISTINCT c_nationkey FROM customer) JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def _(spark, sf_dir):
    """A map of at most 25 nations as one value beside each row."""
    named = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    lookup = named.agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "r_name"))).alias("m"))
    return table(spark, sf_dir, "customer").select("c_nationkey").distinct().crossJoin(F.broadcast(lookup)).select("c_nationkey", F.element_at("m", F.col("c_nationkey")).alias("r_name"))


@register("op_sessions", "SELECT user_id, count(*) AS n, CAST(sum(k) AS BIGINT) AS n_events FROM (SELECT user_id, s, count(*) AS k FROM (SELECT user_id, sum(f) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS f FROM events)) GROUP BY 1, 2) GROUP BY 1")
def _(spark, sf_dir):
    from bandloom.streaming.streams import sessions

    events = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return sessions(events, "user_id", "6 hours").groupBy("user_id").agg(F.count("*").alias("n"), F.sum("n").alias("n_events"))


RECURSION = "WITH RECURSIVE t(i, v, n) AS (SELECT 0, CAST(o_custkey % 64 AS INTEGER), count(*) FROM orders GROUP BY o_custkey % 64 UNION ALL SELECT i + 1, (v * 5 + 3) % 64, n FROM t WHERE i < 63) SELECT i, v, n FROM t"


@register("op_recursion", RECURSION)
def _(spark, sf_dir):
    """64 steps of a full-period sequence from the remainder of every order's customer."""
    table(spark, sf_dir, "orders").createOrReplaceTempView("orders")
    return spark.sql(RECURSION)
