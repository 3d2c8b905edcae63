"""Joins that a filter shortens: the probe sits right above the scan of the large side, before its exchange.

Where the two sides' keys differ in type, both are cast to the type that the join would compare them in, before they are
hashed; types that a join does not compare without loss are refused.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandloom.functions.hashing import common_keys
from bandloom.operators.build import BandFilter, build_filter
from bandloom.operators.probe import probe
from bandloom.spec import FilterSpec


def renamed(dim: DataFrame, dim_keys: list[str], keys: list[str]) -> DataFrame:
    out = dim
    for a, b in zip(dim_keys, keys, strict=True):
        out = out.withColumnRenamed(a, b)
    return out


def filter_for(fact: DataFrame, dim: DataFrame, fact_keys: list[str], dim_keys: list[str], spec: FilterSpec) -> BandFilter:
    """A filter of the dimension's keys that answers the fact's keys as an equi-join would."""
    casts = common_keys(fact, dim, fact_keys, dim_keys)
    thin = dim.select(*[F.col(f"`{k}`").cast(c).alias(k) if c else F.col(f"`{k}`") for k, c in zip(dim_keys, casts, strict=True)])
    return build_filter(thin, dim_keys, spec)


def marked(fact: DataFrame, dim: DataFrame, fact_keys: list[str], dim_keys: list[str], spec: FilterSpec, mode: str, out: str) -> DataFrame:
    """fact with the filter's answer; its own key columns stay as they are."""
    casts = common_keys(fact, dim, fact_keys, dim_keys)
    if not any(casts):
        return probe(fact, filter_for(fact, dim, fact_keys, dim_keys, spec), fact_keys, out, mode)
    extra = [f"{out}_{i}" if c else k for i, (k, c) in enumerate(zip(fact_keys, casts, strict=True))]
    cast = fact.withColumns({e: F.col(f"`{k}`").cast(c) for e, k, c in zip(extra, fact_keys, casts, strict=True) if c})
    got = probe(cast, filter_for(fact, dim, fact_keys, dim_keys, spec), extra, out, mode)
    return got.drop(*[e for e, c in zip(extra, casts, strict=True) if c])


def flag(df: DataFrame) -> str:
    name = "_maybe"
    while any(c.lower().startswith(name) for c in df.columns):
        name += "_"
    return name


def prefilter(fact: DataFrame, keys: list[str], flt: BandFilter, mode: str = "auto") -> DataFrame:
    """The rows of fact that may have a partner."""
    out = flag(fact)
    return probe(fact, flt, keys, out, mode).where(out).drop(out)


def prefilter_join(fact: DataFrame, dim: DataFrame, fact_keys: list[str], dim_keys: list[str], spec: FilterSpec = FilterSpec(), how: str = "inner", mode: str = "auto") -> DataFrame:
    if how not in ("inner", "left_semi", "right"):
        raise ValueError("only joins that drop unmatched rows of the large side can be shortened")
    out = flag(fact)
    left = marked(fact, dim, fact_keys, dim_keys, spec, mode, out).where(out).drop(out)
    return left.join(renamed(dim, dim_keys, fact_keys), fact_keys, how)


def verified_semi(df: DataFrame, members: DataFrame, keys: list[str], member_keys: list[str], spec: FilterSpec = FilterSpec(), mode: str = "auto") -> DataFrame:
    """Exactly the rows of df with a partner: filter first, then the exact join on what is left."""
    exact, out = renamed(members.select(*member_keys), member_keys, keys), flag(df)
    return marked(df, members, keys, member_keys, spec, mode, out).where(out).drop(out).join(exact, keys, "left_semi").select(*df.columns)


def verified_anti(df: DataFrame, members: DataFrame, keys: list[str], member_keys: list[str], spec: FilterSpec = FilterSpec(), mode: str = "auto") -> DataFrame:
    """Exactly the rows of df without a partner: sure negatives as they are, the rest verified."""
    exact, out = renamed(members.select(*member_keys), member_keys, keys), flag(df)
    seen = marked(df, members, keys, member_keys, spec, mode, out)
    sure = seen.where(~F.col(out)).drop(out).select(*df.columns)
    return sure.unionByName(seen.where(out).drop(out).join(exact, keys, "left_anti").select(*df.columns))
