"""Hashes of keys, as Spark columns and as their exact numpy twins.

A key becomes one 64-bit value key_h, once. Everything else is expanded from it with xxhash64 under different salts, so
segment, start, coefficients and fingerprint are independent. Salts and seeds are longs everywhere.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

U64 = np.uint64
# The primes of XXH64.
P1, P2, P3, P4, P5 = (U64(p) for p in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
SEGMENT, START, LOW, HIGH, PRINT, ROUTE, SECOND = range(1, 8)
DEFAULT_SEED = 42
PIECE = 1 << 14


def distinct_np(x: np.ndarray) -> np.ndarray:
    """The values in order, each once, as np.unique; which hashes whole numbers, and takes forty times as long for a million."""
    x = np.sort(x)
    return x[np.concatenate([[True], x[1:] != x[:-1]])] if len(x) else x


def rotl(x: np.ndarray, k: int) -> np.ndarray:
    return (x << U64(k)) | (x >> U64(64 - k))


def xxh64_long(x: np.ndarray, seed) -> np.ndarray:
    """XXH64 of one 8-byte value per element, as Spark's xxhash64 takes a long; seed may be an array."""
    with np.errstate(over="ignore"):
        h = np.asarray(seed, U64) + P5 + U64(8)
        h = h ^ (rotl(np.asarray(x).astype(U64) * P2, 31) * P1)
        h = rotl(h, 27) * P1 + P4
        h = (h ^ (h >> U64(33))) * P2
        h = (h ^ (h >> U64(29))) * P3
        return h ^ (h >> U64(32))


def salted_np(key_h: np.ndarray, salt: int, seed: int = 0) -> np.ndarray:
    """Twin of salted(); in pieces that stay in the processor's cache, each hashed in place."""
    keys, out = np.asarray(key_h).view(U64) if key_h.dtype == np.int64 else key_h, np.empty(len(key_h), U64)
    spare = np.empty(min(PIECE, len(keys)), U64)
    with np.errstate(over="ignore"):
        start = U64(DEFAULT_SEED) + P5 + U64(8)
        second, third = (rotl(np.full(1, v).astype(np.int64).view(U64) * P2, 31) * P1 for v in (salt, seed))
    for at in range(0, len(keys), PIECE):
        h = out[at : at + PIECE]
        t = spare[: len(h)]
        np.multiply(keys[at : at + PIECE], P2, out=h, casting="unsafe")
        rotate(h, 31, t)
        h *= P1
        h ^= start
        finish(h, t)
        for word in (second, third):  # the hash so far is the seed of the next
            h += P5 + U64(8)
            h ^= word
            finish(h, t)
    return out


def rotate(h: np.ndarray, k: int, t: np.ndarray) -> None:
    np.right_shift(h, U64(64 - k), out=t)
    h <<= U64(k)
    h |= t


def finish(h: np.ndarray, t: np.ndarray) -> None:
    """The last steps of XXH64, in place."""
    rotate(h, 27, t)
    h *= P1
    h += P4
    for shift, prime in ((33, P2), (29, P3), (32, None)):
        np.right_shift(h, U64(shift), out=t)
        h ^= t
        if prime is not None:
            h *= prime


def salted(key_h: Column, salt: int, seed: Column | int = 0) -> Column:
    seed = F.lit(seed).cast("long") if isinstance(seed, int) else seed.cast("long")
    return F.xxhash64(key_h, F.lit(salt).cast("long"), seed)


def reduce32(h: Column, size: Column | int) -> Column:
    """Upper 32 bits times size, over 2^32: a number in [0, size); size below 2^31."""
    size = F.lit(size).cast("long") if isinstance(size, int) else size.cast("long")
    return F.shiftrightunsigned(F.shiftrightunsigned(h, 32) * size, 32)


def reduce32_np(h: np.ndarray, size) -> np.ndarray:
    return (((h >> U64(32)) * np.asarray(size, U64)) >> U64(32)).astype(np.int64)


EXACT = (T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.DecimalType)


def kind_of(t: T.DataType) -> str:
    """What a key type is compared as: values that an equi-join finds equal have equal hashes within one kind."""
    if isinstance(t, EXACT):
        return "exact"
    if isinstance(t, (T.FloatType, T.DoubleType)):
        return "double"
    if isinstance(t, (T.StringType, T.CharType, T.VarcharType)):
        return "string"
    if isinstance(t, T.ArrayType):
        return f"array<{kind_of(t.elementType)}>"
    if isinstance(t, T.StructType):
        return f"struct<{','.join(kind_of(f.dataType) for f in t.fields)}>"
    if isinstance(t, (T.BinaryType, T.BooleanType, T.DateType, T.TimestampType, T.TimestampNTZType)):
        return t.typeName()
    raise TypeError(f"{t.simpleString()} cannot be a key")


def canonical(column: Column, t: T.DataType) -> Column:
    """A key in the form that is hashed: whole numbers of any type and scale as longs, other decimals as a long made of their
    whole part and fraction, one NaN and one zero, also inside arrays and structs."""
    if isinstance(t, T.DecimalType):
        whole = column.try_cast("long")
        rest = (column % 1).cast("decimal(38,38)")
        return F.when(whole.isNull(), F.xxhash64(F.format_number(column, 38))).when(rest == 0, whole).otherwise(F.xxhash64(whole, rest))
    if isinstance(t, EXACT):
        return column.cast("long")
    if isinstance(t, (T.FloatType, T.DoubleType)):
        return F.when(F.isnan(column), F.lit(float("nan"))).when(column == 0, F.lit(0.0)).otherwise(column.cast("double"))
    if isinstance(t, T.ArrayType):
        return F.transform(column, lambda x: F.when(x.isNotNull(), canonical(x, t.elementType)))
    if isinstance(t, T.StructType):
        parts = [F.when(column.getField(f.name).isNotNull(), canonical(column.getField(f.name), f.dataType)).alias(f"c{i}") for i, f in enumerate(t.fields)]
        return F.when(column.isNotNull(), F.struct(*parts))
    return column


def key_kinds(df: DataFrame, keys: list[str] | str) -> tuple[str, ...]:
    return tuple(kind_of(df.select(f"`{k}`").schema[0].dataType) for k in ([keys] if isinstance(keys, str) else keys))


def as_kind(column: Column, t: T.DataType, kind: str) -> tuple[Column, T.DataType]:
    """A probed key as an equi-join would compare it with keys of the kind; refused where the join would change the
    stored side instead."""
    have = kind_of(t)
    if have == kind:
        return column, t
    if have == "exact" and kind == "double":
        return column.cast("double"), T.DoubleType()
    if have == "date" and kind in ("timestamp", "timestamp_ntz"):
        return column.cast(kind), T.TimestampType() if kind == "timestamp" else T.TimestampNTZType()
    if kind == "date" and have in ("timestamp", "timestamp_ntz"):  # only a date's own first moment equals it
        return F.when(column.cast("date").cast(have) == column, column.cast("date")), T.DateType()
    raise TypeError(f"keys were stored as {kind} and are asked as {have}: cast one side, as the join would")


def normalised(df: DataFrame, name: str, kind: str | None = None) -> Column:
    """A key column in the form that is hashed, compared as the kind if one is given."""
    t = df.select(f"`{name}`").schema[0].dataType
    column, t = as_kind(F.col(f"`{name}`"), t, kind or kind_of(t))
    return canonical(column, t)


def key_hash(df: DataFrame, keys: list[str] | str, kinds: tuple[str, ...] | None = None) -> Column:
    """One 64-bit value for the key columns; null where any of them is null (SQL's rule: such a row is no member)."""
    keys = [keys] if isinstance(keys, str) else list(keys)
    kinds = kinds or (None,) * len(keys)
    if len(kinds) != len(keys):
        raise ValueError(f"{len(kinds)} key columns were stored, {len(keys)} are asked")
    parts = [normalised(df, k, kind) for k, kind in zip(keys, kinds, strict=True)]
    missing = F.lit(False)
    for k, part in zip(keys, parts, strict=True):
        missing = missing | F.col(f"`{k}`").isNull() | part.isNull()
    return F.when(~missing, F.xxhash64(*parts))


def common_keys(left: DataFrame, right: DataFrame, left_keys: list[str], right_keys: list[str]) -> list[str | None]:
    """For each key pair the type that both sides must be cast to before they are hashed, None where they need no cast."""
    out = []
    for a, b in zip(key_kinds(left, left_keys), key_kinds(right, right_keys), strict=True):
        pair = {a, b}
        if pair == {"exact", "double"}:
            out.append("double")
        elif pair == {"date", "timestamp"} or pair == {"timestamp", "timestamp_ntz"}:
            out.append("timestamp")
        elif pair == {"date", "timestamp_ntz"}:
            out.append("timestamp_ntz")
        elif len(pair) > 1:
            raise TypeError(f"keys of kinds {a} and {b} are not compared: cast one side")
        else:
            out.append(None)
    return out


def with_key_hash(df: DataFrame, keys: list[str] | str, name: str = "key_h") -> DataFrame:
    return df.withColumn(name, key_hash(df, keys))


def segment_of(key_h: Column, segments: int) -> Column:
    return reduce32(salted(key_h, SEGMENT), segments).cast("int")


def segment_np(key_h: np.ndarray, segments: int) -> np.ndarray:
    return reduce32_np(salted_np(key_h, SEGMENT), segments)


def clamp_start(u: Column, starts: Column | int, edge: int) -> Column:
    """Uniform over starts + 2 * (edge - 1) values, clamped to [0, starts): the two ends have `edge` times the mass."""
    more = 2 * (max(edge, 1) - 1)
    size = starts + more if isinstance(starts, int) else starts.cast("long") + F.lit(more)
    if not more:
        return reduce32(u, size)
    last = F.lit(starts - 1) if isinstance(starts, int) else starts.cast("long") - 1
    return F.greatest(F.lit(0).cast("long"), F.least(reduce32(u, size) - (more // 2), last.cast("long")))


def clamp_start_np(u: np.ndarray, starts, edge: int) -> np.ndarray:
    more = 2 * (max(edge, 1) - 1)
    return np.clip(reduce32_np(u, np.asarray(starts) + more) - more // 2, 0, np.asarray(starts) - 1)


def fingerprint(key_h: Column, seed: Column | int, r: int) -> Column:
    return salted(key_h, PRINT, seed).bitwiseAND(F.lit((1 << r) - 1).cast("long"))


def fingerprint_np(key_h: np.ndarray, seed: int, r: int) -> np.ndarray:
    return salted_np(key_h, PRINT, seed) & U64((1 << r) - 1)


def coefficients(key_h: Column, seed: Column | int, w: int) -> tuple[Column, Column | None]:
    """The w coefficient bits, first position lowest, first bit 1; a second word for w = 128."""
    low = salted(key_h, LOW, seed)
    if w < 64:
        low = low.bitwiseAND(F.lit((1 << w) - 1).cast("long"))
    low = low.bitwiseOR(F.lit(1).cast("long"))
    return low, salted(key_h, HIGH, seed) if w == 128 else None


def coefficients_np(key_h: np.ndarray, seed: int, w: int) -> np.ndarray:
    """[lanes, n]"""
    low = salted_np(key_h, LOW, seed)
    if w < 64:
        low = low & U64((1 << w) - 1)
    low = low | U64(1)
    return np.stack([low, salted_np(key_h, HIGH, seed)]) if w == 128 else low[None, :]


# The portable digest: the same numbers in Spark and in DuckDB.


def portable_digest(key: Column, seed: int = 0) -> dict[str, Column]:
    """start32, fp32 (longs below 2^32) and coeff64 (a signed long) from the MD5 of 'seed:key'."""
    h = F.md5(F.concat(F.lit(f"{seed}:"), key.cast("string")))
    return {
        "start32": F.conv(F.substring(h, 1, 8), 16, 10).cast("long"),
        "fp32": F.conv(F.substring(h, 9, 8), 16, 10).cast("long"),
        "coeff64": F.conv(F.substring(h, 17, 16), 16, -10).cast("long"),
    }
