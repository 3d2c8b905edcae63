"""What SQL users and other systems see: views and functions, the two-structure filter, the engine's own Bloom filter."""

from __future__ import annotations

from contextlib import contextmanager
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.classic.column import Column as ClassicColumn

from bandloom.functions.hashing import ROUTE, START, coefficients_np, clamp_start_np, key_hash, salted, salted_np
from bandloom.operators.build import BandFilter, build_filter
from bandloom.operators.probe import collected, probe
from bandloom.runtime import ship
from bandloom.spec import FilterSpec


def register_sql(spark: SparkSession, flt: BandFilter, prefix: str = "filter") -> None:
    """Views <prefix>_meta and <prefix>_blocks; functions band_start, band_coeff and <prefix>_might_be_member of a key hash
    (xxhash64 of the key columns). The membership function holds a broadcast of checked size."""
    ship(spark)
    flt.meta.createOrReplaceTempView(f"{prefix}_meta")
    flt.blocks.createOrReplaceTempView(f"{prefix}_blocks")
    spec = flt.spec
    shared = spark.sparkContext.broadcast(collected(flt))

    @F.arrow_udf("boolean")  # a null among longs would make pandas round them all to doubles
    def member(key_h: pa.Array) -> pa.Array:
        return pa.array(shared.value.contains(key_h.fill_null(0).to_numpy()) & key_h.is_valid().to_numpy(zero_copy_only=False))

    @F.pandas_udf("long")
    def start(key_h: pd.Series, m: pd.Series) -> pd.Series:
        return pd.Series(clamp_start_np(salted_np(key_h.to_numpy(), START), m.to_numpy() - spec.w + 1, spec.edge))

    @F.pandas_udf("long")
    def coeff(key_h: pd.Series) -> pd.Series:
        return pd.Series(coefficients_np(key_h.to_numpy(), 0, spec.w)[0].view(np.int64))

    spark.udf.register(f"{prefix}_might_be_member", member)
    spark.udf.register("band_start", start)
    spark.udf.register("band_coeff", coeff)


@dataclass(frozen=True)
class TwoStructures:
    """Fractional r as two filters of whole widths; a hash sends a share of the keys to the wider one."""

    narrow: BandFilter
    wide: BandFilter
    share: float


def to_wide(key_h, share: float):
    return F.shiftrightunsigned(salted(key_h, ROUTE), 32) < F.lit(int(share * 2**32))


def split_structures(df: DataFrame, keys: list[str] | str, r: float, spec: FilterSpec = FilterSpec()) -> TwoStructures:
    if r == int(r):
        raise ValueError("a whole r needs one structure")
    share = r - int(r)
    wide = to_wide(key_hash(df, keys), share)
    return TwoStructures(build_filter(df.where(~wide), keys, spec.but(r=int(r))), build_filter(df.where(wide), keys, spec.but(r=int(r) + 1)), share)


def probe_structures(df: DataFrame, two: TwoStructures, keys: list[str] | str, out: str = "maybe") -> DataFrame:
    wide = F.coalesce(to_wide(key_hash(df, keys), two.share), F.lit(False))
    return probe(df.where(wide), two.wide, keys, out).unionByName(probe(df.where(~wide), two.narrow, keys, out))


def jvm_bloom(df: DataFrame, column: str, n: int, fpp: float = 0.01):
    """The engine's own Bloom sketch of a long column; its size follows from n and fpp, and it is merged on the driver."""
    return df._jdf.stat().bloomFilter(column, n, fpp)


def jvm_might_contain(spark: SparkSession, sketch, column: str) -> Column:
    """The sketch's answer as a column expression of the engine, on a long column."""
    buffer = spark._jvm.java.io.ByteArrayOutputStream()
    sketch.writeTo(buffer)
    utils = spark._jvm.org.apache.spark.sql.classic.ExpressionUtils
    parts = [utils.expression(c._jc) for c in (F.lit(bytearray(buffer.toByteArray())), F.col(f"`{column}`"))]
    return ClassicColumn(utils.column(spark._jvm.org.apache.spark.sql.catalyst.expressions.BloomFilterMightContain(*parts)))


@contextmanager
def settings(spark: SparkSession, values: dict[str, str]):
    """Runtime settings of the session for a while."""
    before = {k: spark.conf.get(k, None) for k in values}
    try:
        for k, v in values.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def runtime_filtered(spark: SparkSession, fact: DataFrame, dim: DataFrame, on: list[str]) -> tuple[DataFrame, dict[str, str]]:
    """The engine's runtime join filter as a baseline: the plain join, and the session settings (for the caller to set and
    restore) under which it fires on inputs of test size."""
    wanted = {
        "spark.sql.optimizer.runtime.bloomFilter.enabled": "true", "spark.sql.optimizer.runtime.bloomFilter.applicationSideScanSizeThreshold": "0",
        "spark.sql.autoBroadcastJoinThreshold": "-1",
    }
    return fact.join(dim, on), wanted
