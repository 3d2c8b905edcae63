"""Solutions stored by rows or by columns instead of interleaved words, and probes of them; JVM only.

By rows: a relation row holds the r-bit values of 64 solution rows and of those that follow, and a query XORs the values
that its coefficients select. By columns: a relation row holds one column's bits of 64 rows, so a query needs a row per
column (one join each), and is cheap only for very few columns.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bandloom.operators.build import BandFilter


def values_of(words: Column) -> Column:
    """The 64 row values of a block's words, column j as bit j."""
    return F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.aggregate(
        F.transform(words, lambda w, j: F.call_function("shiftleft", F.call_function("shiftrightunsigned", w, i).bitwiseAND(F.lit(1).cast("long")), j)),
        F.lit(0).cast("long"), lambda a, x: a.bitwiseOR(x)))


def relation(blocks: DataFrame, layout: str) -> DataFrame:
    """The blocks of a filter in another layout."""
    if layout == "row":
        parts = [values_of(F.col("words")), values_of(F.coalesce("next_words", F.array().cast("array<long>"))), values_of(F.coalesce("third_words", F.array().cast("array<long>")))]
        return blocks.select("segment", "block", F.size("words").alias("width"), F.concat(*parts).alias("rows"))
    if layout == "column":
        third = F.coalesce("third_words", F.transform("words", lambda w: F.lit(0).cast("long")))
        return blocks.select("segment", "block", F.posexplode(F.arrays_zip("words", "next_words", third.alias("third_words"))).alias("column", "z")).select(
            "segment", "block", "column", F.col("z.words").alias("word"), F.col("z.next_words").alias("next_word"), F.col("z.third_words").alias("third_word")
        )
    raise ValueError(f"no relation of layout {layout}")


def probe_layout(df: DataFrame, flt: BandFilter, keys, out: str, run: str | None = None) -> DataFrame:
    from bandloom.operators.probe import Names, others, windowed

    my, spec = Names(df), flt.spec
    laid = flt.laid if flt.laid is not None else relation(flt.blocks, spec.layout)
    rows = windowed(df, keys, flt, my, run)
    here = [my("segment"), my("block")]
    low, high, o, fp = (my(c) for c in ("low", "high", "o", "fp"))
    if spec.layout == "row":
        rows = rows.join(laid.select(*[F.col(c).alias(my(c)) for c in ("segment", "block", "width", "rows")]), here, "left")
        pick = f"CASE WHEN (shiftrightunsigned(IF(t < 64, {low}, {high}), t % 64) & 1L) = 1L THEN get({my('rows')}, {o} + t) ELSE 0L END"
        got = f"aggregate(sequence(0, {spec.w - 1}), 0L, (a, t) -> a ^ {pick})"
        match = F.expr(f"(({got} ^ {fp}) & (shiftleft(1L, {my('width')}) - 1L)) = 0L")
        return rows.select(*others(df, out), F.coalesce(match, F.lit(False)).alias(out))
    match = F.lit(True)
    for j in range(spec.r_hi):
        word = {c: my(f"{c}_{j}") for c in ("word", "next_word", "third_word")}
        own = laid.where(F.col("column") == j).select(F.col("segment").alias(here[0]), F.col("block").alias(here[1]), *[F.col(c).alias(n) for c, n in word.items()])
        rows = rows.join(own, here, "left")

        def window(a: str, b: str) -> str:
            return f"(CASE WHEN {o} = 0 THEN {a} ELSE shiftrightunsigned({a}, {o}) | shiftleft({b}, 64 - {o}) END)"

        mix = f"({window(word['word'], word['next_word'])} & {low})"
        if spec.w == 128:
            mix = f"({mix} ^ ({window(word['next_word'], word['third_word'])} & {high}))"
        same = F.expr(f"(bit_count({mix}) & 1) = CAST(shiftrightunsigned({fp}, {j}) & 1L AS INT)")
        present = F.col(word["word"]).isNotNull()
        match = match & (F.coalesce(same, F.lit(False)) if j == 0 else F.when(present, same).otherwise(F.lit(j >= spec.r_lo or spec.sharding == "fixed_bytes")))
    return rows.select(*others(df, out), match.alias(out))
