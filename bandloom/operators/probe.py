"""Probing: as a join with the block relation (JVM only), or as Arrow batches against a broadcast of bounded size."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bandloom.functions.hashing import ROUTE, SECOND, START, clamp_start, coefficients, fingerprint, key_hash, reduce32, salted, segment_np, segment_of
from bandloom.kernel import ranges
from bandloom.kernel.balanced import BUCKETS
from bandloom.kernel.bands import Segment, contains, query_segment
from bandloom.operators.build import BandFilter, run_segment, small
from bandloom.plans.planning import bucket_shares
from bandloom.runtime import ship

RELATION_BROADCAST = 10 << 20
COMPACT_BROADCAST = 64 << 20
UNROLLED = 11  # columns times lanes; the code of more is too long for the JVM to compile, and a lambda is faster


def shl(x: Column, by: Column) -> Column:
    return F.call_function("shiftleft", x, by)


class Names:
    """Columns of ours, under a prefix that no column of the caller's begins with."""

    def __init__(self, df: DataFrame):
        self.prefix = "_b"
        while any(c.lower().startswith(self.prefix) for c in df.columns):
            self.prefix += "_"

    def __call__(self, name: str) -> str:
        return f"{self.prefix}_{name}"

    def col(self, name: str) -> Column:
        return F.col(self(name))


def divided(place: Column, size: Column, total: Column) -> Column:
    """place * size // total as longs, exactly."""
    product = place.cast("long") * size
    return ((product - F.pmod(product, total)) / total).cast("long")


def start_column(flt: BandFilter, my: Names, m: Column, seed: Column) -> Column:
    """The first row of a key's window; for the balanced variant, of its primary or secondary shard."""
    spec, key_h = flt.spec, my.col("key")
    starts = m - F.lit(spec.w - 1)
    if spec.sharding == "soft":
        place, total = my.col("place").cast("long"), F.get(my.col("shards"), F.lit(0)).cast("long")
        lo, hi = divided(place, starts, total), divided(place + 1, starts, total)
        return lo + reduce32(salted(key_h, START, seed), hi - lo)
    if spec.variant != "balanced":
        return clamp_start(salted(key_h, START, seed), starts, spec.edge)
    cuts, shards, defer = my.col("cuts"), my.col("shards"), my.col("defer")
    h = salted(key_h, ROUTE, seed)
    upper, lower = F.shiftrightunsigned(h, 32), h.bitwiseAND(F.lit(0xFFFFFFFF).cast("long"))
    # Shards of tier 1 have one weight and the others another, so arithmetic finds the shard up to a neighbour.
    total, first = F.size(cuts), F.get(shards, F.lit(0))
    border = F.get(cuts, first - 1)
    guess = F.when(upper < border, upper * first / border).otherwise(first + (upper - border) * (total - first) / F.greatest(F.lit(1).cast("long"), F.lit(1 << 32) - border))
    guess = F.least(F.greatest(guess.cast("int"), F.lit(0)), total - 1)
    shard = guess + (F.get(cuts, guess) <= upper).cast("int") - (F.coalesce(F.get(cuts, guess - 1), F.lit(0).cast("long")) > upper).cast("int")
    edges = [int(x) for x in np.floor(np.cumsum(bucket_shares(BUCKETS)) * 2.0**32)][:-1]
    bucket = sum(((lower >= F.lit(e)).cast("int") for e in edges), F.lit(0))
    second = F.get(my.col("next_first"), shard) + reduce32(salted(key_h, SECOND, seed), F.get(my.col("next_size"), shard))
    moved = shl(F.lit(1), bucket).bitwiseAND(F.get(defer, shard)) != 0
    place = F.when(moved, second).otherwise(shard).cast("long")
    lo, hi = divided(place, starts, total.cast("long")), divided(place + 1, starts, total.cast("long"))
    return lo + reduce32(salted(key_h, START, seed), hi - lo)


def parity(my: Names, j: int | str, lanes: int) -> str:
    """SQL for column j's result bit (0 or 1) of the window that starts o rows into its block.

    Text, because one parse is far cheaper for the driver than hundreds of calls that build the same tree.
    """

    def aligned(a: str, b: str) -> str:
        a, b, o = f"get({my(a)}, {j})", f"get({my(b)}, {j})", my("o")
        return f"(CASE WHEN {o} = 0 THEN {a} ELSE shiftrightunsigned({a}, {o}) | shiftleft({b}, 64 - {o}) END)"

    mix = f"({aligned('words', 'next_words')} & {my('low')})"
    if lanes == 2:
        mix = f"({mix} ^ ({aligned('next_words', 'third_words')} & {my('high')}))"
    return f"(bit_count({mix}) & 1)"


def keyed(df: DataFrame, keys: list[str] | str, flt: BandFilter, my: Names, run: str | None = None) -> DataFrame:
    """df with the hash of each key and the number of its segment (null where no segment can hold it)."""
    rows = df.withColumn(my("key"), key_hash(df, keys, flt.kinds))
    key = my.col("key")
    if flt.by_run:
        if run is None:
            raise ValueError("this filter is kept by run: name the run column")
        parts = F.lit(flt.parts)
        if flt.run_parts is not None:
            known = flt.run_parts.select(F.col("run").alias(my("run")), F.col("parts").alias(my("parts")))
            rows = rows.join(small(known), F.col(f"`{run}`").cast("int") == my.col("run"), "left")
            parts = my.col("parts")
        return rows.withColumn(my("segment"), run_segment(F.col(f"`{run}`"), key, parts))
    if flt.spec.sharding == "until_failure":
        order = salted(key, ranges.RANGE)
        rows = rows.withColumn(my("range"), reduce32(order, flt.segments)).withColumn(my("order"), order.bitwiseXOR(F.lit(-(1 << 63)).cast("long")))
        # Each task's range has the bounds of its shards in one row: as many as its keys fill, at most ranges.PER_RANGE.
        bounds = flt.meta.groupBy(F.shiftright("segment", 16).alias(my("range"))).agg(F.array_sort(F.collect_list("from_h")).alias(my("bounds")))
        if flt.segments <= 1_000:
            bounds = F.broadcast(bounds)
        rows = rows.join(bounds, my("range"), "left")
        at = F.size(F.filter(my.col("bounds"), lambda b: b <= my.col("order"))) - 1
        return rows.withColumn(my("segment"), F.when(at >= 0, my.col("range") * ranges.PER_RANGE + at))
    return rows.withColumn(my("segment"), F.when(key.isNotNull(), segment_of(key, flt.segments)).cast("long"))


def located(df: DataFrame, keys: list[str] | str, flt: BandFilter, my: Names, run: str | None, hint: str | None) -> DataFrame:
    """df with the window of each key, its coefficients and its fingerprint, and its block row (null if the filter has none)."""
    rows = windowed(df, keys, flt, my, run)
    blocks = flt.blocks.select(F.col("segment").alias(my("segment")), F.col("block").alias(my("block")), *[F.col(c).alias(my(c)) for c in ("words", "next_words", "third_words")])
    if hint == "broadcast":
        blocks = F.broadcast(blocks)
    return rows.join(blocks, [my("segment"), my("block")], "left")


def windowed(df: DataFrame, keys: list[str] | str, flt: BandFilter, my: Names, run: str | None = None) -> DataFrame:
    """df with the window of each key, its coefficients and its fingerprint."""
    spec = flt.spec
    rows = keyed(df, keys, flt, my, run)
    key = my.col("key")
    plain = not flt.by_run and spec.variant != "balanced" and spec.sharding in ("hash", "fixed_bytes")
    one = flt.head if not flt.fixed_m and flt.segments == 1 and plain else None
    if flt.fixed_m:
        m, seed = F.lit(flt.fixed_m).cast("long"), F.lit(0)
    elif one is not None and len(one) == 1:
        m, seed = F.lit(one[0].m).cast("long"), F.lit(one[0].seed)
    else:
        extra = ["cuts", "shards", "defer", "next_first", "next_size"] if spec.variant == "balanced" else ["shards", "defer"] if spec.sharding == "soft" else []
        meta = flt.meta.select(*[F.col(c).alias(my(c)) for c in ("segment", "m", "seed", *extra)])
        rows = rows.join(meta, my("segment"), "left")
        m, seed = my.col("m"), my.col("seed")
        if spec.sharding == "soft":
            rows = rows.withColumn(my("place"), reduce32(salted(key, ROUTE), F.get(my.col("shards"), F.lit(0))))
            rows = rows.withColumn(my("own_seed"), F.get(my.col("defer"), my.col("place").cast("int")))
            seed = my.col("own_seed")
    low, high = coefficients(key, seed, spec.w)
    rows = rows.withColumn(my("start"), start_column(flt, my, m, seed))
    rows = rows.withColumn(my("block"), F.shiftright(my("start"), 6).cast("int")).withColumn(my("o"), my.col("start").bitwiseAND(F.lit(63).cast("long")).cast("int"))
    rows = rows.withColumn(my("low"), low).withColumn(my("high"), high if high is not None else F.lit(None).cast("long"))
    print_ = F.lit(0).cast("long") if spec.variant == "homogeneous" or flt.static else F.shiftrightunsigned(fingerprint(key, seed, flt.first_column + spec.r_hi), flt.first_column)
    return rows.withColumn(my("fp"), print_)


def probe_expr(flt: BandFilter, my: Names, short_circuit: bool | str = "auto") -> Column:
    """True if all result bits of the window match; on the columns that located() adds."""
    return F.expr(f"CASE WHEN {my('words')} IS NOT NULL THEN {probe_text(flt, my, short_circuit)} ELSE false END")


def probe_text(flt: BandFilter, my: Names, short_circuit: bool | str = "auto") -> str:
    spec = flt.spec
    lanes, words, fp = 2 if spec.w == 128 else 1, my("words"), my("fp")
    least = 1 if spec.sharding == "fixed_bytes" else spec.r_lo
    if short_circuit == "auto":
        short_circuit = spec.r_hi > 4

    def differs(j: int | str) -> str:
        miss = f"({parity(my, j, lanes)} ^ CAST(shiftrightunsigned({fp}, {j}) & 1L AS INT))"
        return f"(CASE WHEN size({words}) > {j} THEN {miss} ELSE 0 END)" if isinstance(j, int) and j >= least else miss

    if spec.r_hi * lanes > UNROLLED:
        return f"forall(sequence(0, size({words}) - 1), j -> {differs('j')} = 0)"
    if short_circuit:
        return " AND ".join(f"{differs(j)} = 0" for j in range(spec.r_hi))
    return "(" + " | ".join(differs(j) for j in range(spec.r_hi)) + ") = 0"


def relation_bytes(flt: BandFilter) -> tuple[int, int]:
    """Bytes of the compact form and of the block relation."""
    head = flt.head
    bits = sum(r.bits for r in head) if head is not None else flt.meta.agg(F.sum("bits")).first()[0]
    return bits // 8, (bits // 8) * (3 if flt.spec.w == 128 else 2) + bits // (64 * flt.spec.r_hi) * 40


def pick_mode(flt: BandFilter) -> str:
    compact, relation = relation_bytes(flt)
    if compact <= COMPACT_BROADCAST and not (flt.by_run or flt.first_column or flt.cut) and (relation > RELATION_BROADCAST or long_winded(flt)):
        return "broadcast"
    return "block_broadcast" if relation <= RELATION_BROADCAST else "block_shuffle"


def long_winded(flt: BandFilter) -> bool:
    """Whether a query is so long an expression that Arrow batches answer it several times faster than the join."""
    return flt.spec.variant == "balanced" or flt.spec.sharding == "soft" or flt.spec.r_hi * (2 if flt.spec.w == 128 else 1) > UNROLLED


def others(df: DataFrame, out: str) -> list[str]:
    return [f"`{c}`" for c in df.columns if c != out]


def probe(df: DataFrame, flt: BandFilter, keys: list[str] | str, out: str = "maybe", mode: str = "auto", run: str | None = None, short_circuit: bool | str = "auto") -> DataFrame:
    """df with a boolean: false means certainly not a member. A null key is no member.

    mode: block_broadcast or block_shuffle (the join), broadcast (Arrow batches), auto (by the filter's measured size). A key
    of another type than was stored is compared as an equi-join would, or refused.
    """
    if flt.static:
        raise ValueError("a static function answers no membership queries")
    if flt.spec.layout != "icm" and flt.spec.layout in ("row", "column"):
        from bandloom.operators.layouts import probe_layout

        return probe_layout(df, flt, keys, out, run)
    mode = pick_mode(flt) if mode == "auto" else mode
    if mode == "broadcast" and not (flt.by_run or flt.first_column or flt.cut):
        return probe_broadcast(df, flt, keys, out)
    my = Names(df)
    rows = located(df, keys, flt, my, run, "broadcast" if mode == "block_broadcast" else None)
    return rows.select(*others(df, out), F.coalesce(probe_expr(flt, my, short_circuit), F.lit(False)).alias(out))


def lookup_static(df: DataFrame, flt: BandFilter, keys: list[str] | str, out: str = "value", mode: str = "auto") -> DataFrame:
    """df with the static function's value of each key (arbitrary for keys it was not built for)."""
    mode = pick_mode(flt) if mode == "auto" else mode
    if mode == "broadcast":
        return lookup_broadcast(df, flt, keys, out)
    my = Names(df)
    rows = located(df, keys, flt, my, None, "broadcast" if mode == "block_broadcast" else None)
    lanes, words = 2 if flt.spec.w == 128 else 1, my("words")
    if flt.spec.r_hi * lanes > UNROLLED:
        bits = f"transform({words}, (x, j) -> shiftleft(CAST({parity(my, 'j', lanes)} AS BIGINT), j))"
        value = F.expr(f"aggregate({bits}, 0L, (a, b) -> a | b)")
    else:
        value = F.expr(" | ".join(f"shiftleft(CAST({parity(my, j, lanes)} AS BIGINT), {j})" for j in range(flt.spec.r_hi)))
    return rows.select(*others(df, out), F.when(my.col("words").isNotNull(), value).alias(out))


class Collected:
    """The compact form, in one process: segments by number, and which of them holds a key."""

    def __init__(self, flt: BandFilter, segments: dict[int, Segment]):
        self.spec, self.n, self.segments = flt.spec, flt.segments, segments
        self.names = np.array(sorted(segments), np.int64)
        self.bounds = np.array([segments[s].from_h for s in self.names.tolist()], np.int64) if flt.spec.sharding == "until_failure" else None

    def home(self, key_h: np.ndarray) -> np.ndarray:
        if self.bounds is None:
            return segment_np(key_h, self.n)
        return self.names[np.searchsorted(self.bounds, ranges.order_hash(key_h), "right") - 1] if len(self.names) else np.zeros(len(key_h), np.int64)

    def each(self, key_h: np.ndarray):
        """(rows, segment) of the keys of each segment that some key falls into."""
        home = self.home(key_h)
        order = np.argsort(home, kind="stable")
        for rows in np.split(order, np.flatnonzero(np.diff(home[order])) + 1):
            if len(rows) and (seg := self.segments.get(int(home[rows[0]]))):
                yield rows, seg

    def contains(self, key_h: np.ndarray) -> np.ndarray:
        got = np.zeros(len(key_h), bool)
        for rows, seg in self.each(key_h):
            got[rows] = contains(seg, self.spec, key_h[rows])
        return got

    def values(self, key_h: np.ndarray) -> np.ndarray:
        got = np.zeros(len(key_h), np.int64)
        for rows, seg in self.each(key_h):
            got[rows] = query_segment(seg, self.spec, key_h[rows]).view(np.int64)
        return got


def collected(flt: BandFilter, limit: int = COMPACT_BROADCAST) -> Collected:
    """The compact form on the driver; refused above a checked size."""
    if flt.by_run or flt.first_column or flt.cut:
        raise ValueError("filters kept by run, split by columns or cut by rows are probed by the join")
    compact, _ = relation_bytes(flt)
    if compact > limit:
        raise ValueError(f"{compact} bytes exceed the broadcast bound of {limit}")
    return Collected(flt, segments_of(flt))


def segments_of(flt: BandFilter) -> dict[int, Segment]:
    """All segments, on the driver; for filters whose size was checked."""
    out = {}
    for m in flt.meta.collect():
        width = flt.spec.r_hi if m.r is None else flt.spec.but(r=m.r).r_hi
        out[m.segment] = Segment(m.segment, m.m, m.seed, m.n_rows, np.zeros((m.m // 64, width), np.uint64), m.split_block, np.array(m.defer, np.int64), list(m.shards), m.alpha, r=m.r, from_h=m.from_h)
    rows = flt.blocks.select("segment", "block", "words").toArrow()
    words = rows.column("words").combine_chunks()
    flat, ends = words.flatten().to_numpy().view(np.uint64), np.cumsum(words.value_lengths().to_numpy())
    for s, b, lo, hi in zip(rows.column("segment").to_pylist(), rows.column("block").to_pylist(), [0, *ends.tolist()][:-1], ends.tolist(), strict=True):
        out[s].words[b, : hi - lo] = flat[lo:hi]
    return out


def in_bulk(answer, batches: Iterator[pd.Series], at_once: int = 1 << 18) -> Iterator[pd.Series]:
    """The answers to each batch, many batches asked together: a batch of Arrow's has few keys of each of many segments, and a
    call for these costs as much as one for thousands."""
    held: list[np.ndarray] = []

    def flush() -> Iterator[pd.Series]:
        got = answer(np.concatenate(held))
        yield from map(pd.Series, np.split(got, np.cumsum([len(h) for h in held])[:-1]))
        held.clear()

    for batch in batches:
        held.append(batch.to_numpy())
        if sum(map(len, held)) >= at_once:
            yield from flush()
    if held:
        yield from flush()


def hashed_call(df: DataFrame, flt: BandFilter, keys: list[str] | str, out: str, kind: str, method: str, absent: Column) -> DataFrame:
    """df with a vectorised call of the collected filter on the key hash."""
    spark = df.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(collected(flt))

    @F.pandas_udf(kind)
    def call(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        return in_bulk(getattr(shared.value, method), batches)

    # A nullable long would reach pandas as a double and lose bits, so nulls are replaced before the call.
    my = Names(df)
    hashed = df.withColumn(my("key"), key_hash(df, keys, flt.kinds))
    value = F.when(my.col("key").isNotNull(), call(F.coalesce(my.col("key"), F.lit(0).cast("long")))).otherwise(absent)
    return hashed.select(*others(df, out), value.alias(out))


def probe_broadcast(df: DataFrame, flt: BandFilter, keys: list[str] | str, out: str = "maybe") -> DataFrame:
    return hashed_call(df, flt, keys, out, "boolean", "contains", F.lit(False))


def lookup_broadcast(df: DataFrame, flt: BandFilter, keys: list[str] | str, out: str = "value") -> DataFrame:
    return hashed_call(df, flt, keys, out, "long", "values", F.lit(None).cast("long"))
