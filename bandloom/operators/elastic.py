"""Changing a finished filter without rebuilding it: drop columns, split by columns, cut by rows."""

from __future__ import annotations

from pyspark.sql import functions as F

from bandloom.operators.build import BandFilter

WORDS = ("words", "next_words", "third_words")


def trim(flt: BandFilter, r: float) -> BandFilter:
    """Keep r result bits (fractional: the last column only from a block on). Each dropped column doubles the FP rate.

    A block's width follows its own row; the next blocks' words keep what it compares.
    """
    spec = flt.spec.but(r=r)
    if r > flt.spec.r:
        raise ValueError("a filter can be trimmed, not widened")
    edge = F.round((spec.r_hi - F.lit(float(r))) * F.col("n_blocks")).cast("int")
    width = F.when(F.col("block") < edge, spec.r_lo).otherwise(spec.r_hi) if spec.r_lo != spec.r_hi else F.lit(spec.r_hi)
    width = F.least(width, F.size("words"))
    blocks = flt.blocks.select("segment", "block", "n_blocks", *[F.slice(c, F.lit(1), width).alias(c) for c in WORDS])
    n = F.col("m") / 64
    split = F.greatest(F.col("split_block") if flt.spec.r_hi == spec.r_hi else F.lit(0), F.round((spec.r_hi - F.lit(float(r))) * n).cast("int") if spec.r_lo != spec.r_hi else F.lit(0))
    bits = (64 * (split * spec.r_lo + (n - split) * spec.r_hi) + 8 * F.greatest(F.size("defer"), F.lit(0))).cast("long")
    return flt.but(spec=spec, blocks=blocks, meta=flt.meta.withColumn("bits", bits).withColumn("split_block", split.cast("int")))


def split_columns(flt: BandFilter, widths: list[int]) -> list[BandFilter]:
    """Several filters from one; their rates multiply at best to the original's (less so for the homogeneous variant,
    whose degraded share is common to all parts)."""
    if flt.spec.r_lo != flt.spec.r_hi or sum(widths) > flt.spec.r_hi or min(widths) < 1:
        raise ValueError("widths are positive whole numbers within a whole r")
    out, at = [], 0
    for k in widths:
        blocks = flt.blocks.select("segment", "block", "n_blocks", *[F.slice(c, at + 1, k).alias(c) for c in WORDS])
        bits = (F.col("m") * k + 8 * F.greatest(F.size("defer"), F.lit(0))).cast("long")
        out.append(flt.but(spec=flt.spec.but(r=k), blocks=blocks, meta=flt.meta.withColumn("bits", bits), first_column=flt.first_column + at))
        at += k
    return out


def repartition_filter(flt: BandFilter, cuts: list[int]) -> list[tuple[int, int, BandFilter]]:
    """(first block, end block, part) for parts cut at block boundaries. A block row already holds the rows that follow
    it, which is the (w-1) * r bits a cut duplicates; a query needs the one part that holds its start."""
    edges = [0, *cuts, 1 << 30]
    return [(a, b, flt.but(cut=True, blocks=flt.blocks.where((F.col("block") >= a) & (F.col("block") < b)))) for a, b in zip(edges, edges[1:], strict=False)]


def cut_bits(flt: BandFilter, cuts: list[int]) -> int:
    return len(cuts) * (flt.spec.w - 1) * flt.spec.r_hi

