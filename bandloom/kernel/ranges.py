"""Shards that grow along the order of a hash until a key does not fit: a shard is a range of that hash."""

from __future__ import annotations

import time

import numpy as np

from bandloom.functions.hashing import START, U64, clamp_start_np, coefficients_np, salted_np
from bandloom.kernel.banding import back_substitute, band_until_failure, many_until_failure
from bandloom.kernel.bands import Segment, build_segments, rhs_of
from bandloom.plans.planning import natural_shard, round_rows
from bandloom.spec import FilterSpec

RANGE = 8  # salt of the order hash
PER_RANGE = 1 << 16  # numbers that the shards of one task's range may take
SIGN = U64(1 << 63)


def order_hash(key_h: np.ndarray) -> np.ndarray:
    """The hash whose ranges are shards, as longs in its unsigned order."""
    return (salted_np(key_h, RANGE) ^ SIGN).view(np.int64)


def shard_rows(spec: FilterSpec) -> int:
    return round_rows(spec.shard_rows or max(natural_shard(spec.w), 2 * spec.w))


def build(number: int, least: int, key_h: np.ndarray, spec: FilterSpec, values: np.ndarray | None = None) -> list[Segment]:
    """The shards of one range, which begins at the order hash `least`; the last holds what is left and is sized for it."""
    m, w = shard_rows(spec), spec.w
    order = np.argsort(order_hash(key_h), kind="stable")
    keys, out = key_h[order], []
    own_values = None if values is None else values[order]
    h, at = order_hash(keys), 0
    while len(keys) - at > 0.85 * m:
        began = time.perf_counter_ns()
        part = slice(at, at + m + w)
        start, rhs = clamp_start_np(salted_np(keys[part], START), m - w + 1, spec.edge), rhs_of(keys[part], 0, spec, None if own_values is None else own_values[part])
        bank, n = band_until_failure(m, start, coefficients_np(keys[part], 0, w), rhs, int(0.9 * m))
        end = at + n
        while at + n < len(keys) and end > at + 1 and h[end - 1] == h[end]:
            end -= 1  # equal hashes stay in one range
        seg = Segment(number * PER_RANGE + len(out), m, 0, end - at, back_substitute(bank, spec.r_hi, m, spec.free)[0], 0, redundant=n - int(bank.used.sum()))
        seg.from_h, seg.displacement = (int(h[at]) if out else least), int(np.flatnonzero(bank.used).sum() - start[:n].sum())
        seg.build_ns = time.perf_counter_ns() - began
        out.append(seg)
        at = end
    if at < len(keys) or not out:
        name = number * PER_RANGE + len(out)
        (seg,) = build_segments({name: keys[at:]}, spec, None if own_values is None else {name: own_values[at:]})
        seg.from_h = int(h[at]) if out else least
        out.append(seg)
    if len(out) > PER_RANGE:
        raise ValueError("too many shards in a range: use more ranges")
    return out


def build_many(groups: dict[int, tuple[int, np.ndarray]], spec: FilterSpec) -> dict[int, list[Segment]]:
    """build() of many ranges at once: the next shard of every range that is not finished is grown in lock-step.

    groups: least order hash and keys by range. The shards are those that build() makes, since the longest prefix that fits,
    the rows it fills and the solution do not depend on the order of elimination.
    """
    m, w, lanes = shard_rows(spec), spec.w, 2 if spec.w == 128 else 1
    sorted_keys, hashes, out, at = {}, {}, {}, {}
    for g, (_, key_h) in groups.items():
        h = order_hash(key_h)
        order = np.argsort(h, kind="stable")
        sorted_keys[g], hashes[g], out[g], at[g] = key_h[order], h[order], [], 0
    while live := [g for g in groups if len(sorted_keys[g]) - at[g] > 0.85 * m]:
        began = time.perf_counter_ns()
        sizes = np.array([min(m + w, len(sorted_keys[g]) - at[g]) for g in live])
        keys = np.concatenate([sorted_keys[g][at[g] : at[g] + k] for g, k in zip(live, sizes.tolist(), strict=True)])
        where = np.repeat(np.arange(len(live)), sizes)
        column = np.arange(len(keys)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        start, rhs = np.zeros((len(live), m + w), np.int64), np.zeros((len(live), m + w), np.uint64)
        coeff = np.zeros((lanes, len(live), m + w), np.uint64)
        start[where, column], rhs[where, column] = clamp_start_np(salted_np(keys, START), m - w + 1, spec.edge), rhs_of(keys, 0, spec, None)
        coeff[:, where, column] = coefficients_np(keys, 0, w)
        bank, fitted = many_until_failure(m, start, coeff, rhs, int(0.9 * m), sizes)
        words = back_substitute(bank, spec.r_hi, m, spec.free)
        used = bank.used.reshape(len(live), m)
        spent = (time.perf_counter_ns() - began) // len(live)
        for k, g in enumerate(live):
            h, n, end = hashes[g], int(fitted[k]), at[g] + int(fitted[k])
            while at[g] + n < len(h) and end > at[g] + 1 and h[end - 1] == h[end]:
                end -= 1  # equal hashes stay in one range
            filled = np.flatnonzero(used[k])
            seg = Segment(g * PER_RANGE + len(out[g]), m, 0, end - at[g], words[k], 0, redundant=n - len(filled))
            seg.from_h, seg.displacement = (int(h[at[g]]) if out[g] else groups[g][0]), int(filled.sum() - start[k, :n].sum())
            seg.build_ns = spent
            out[g].append(seg)
            at[g] = end
    for g, keys in sorted_keys.items():
        if at[g] < len(keys) or not out[g]:
            name = g * PER_RANGE + len(out[g])
            (seg,) = build_segments({name: keys[at[g] :]}, spec)
            seg.from_h = int(hashes[g][at[g]]) if out[g] else groups[g][0]
            out[g].append(seg)
        if len(out[g]) > PER_RANGE:
            raise ValueError("too many shards in a range: use more ranges")
    return out
