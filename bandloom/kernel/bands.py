"""Band systems of one or more segments, built together in one task."""

from __future__ import annotations

import math
import time
from dataclasses import dataclass, field

import numpy as np

from bandloom.functions.hashing import START, U64, clamp_start_np, coefficients_np, fingerprint_np, salted_np
from bandloom.kernel import balanced, softshards
from bandloom.kernel.banding import Bank, back_substitute, lookup
from bandloom.plans.planning import recommended_eps, rows_for
from bandloom.spec import FilterSpec


class NoSolution(RuntimeError):
    """No seed or size gave a solvable system."""


@dataclass
class Segment:
    """A finished system: its solution words (a list of arrays per block for fractional widths) and its counters."""

    segment: int
    m: int
    seed: int
    n: int
    words: np.ndarray
    split: int  # blocks before it hold r_lo columns only
    flags: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    shards: list[int] = field(default_factory=list)
    alpha: float = 0.0
    redundant: int = 0
    attempts: int = 1
    additions: int = 0
    displacement: int = 0
    build_ns: int = 0
    stats: dict = field(default_factory=dict)
    r: float | None = None  # result bits, where segments differ in them
    from_h: int | None = None  # least order hash, where segments are ranges
    flag_bits: int = 8  # metadata bits of each shard

    def own_spec(self, spec: FilterSpec) -> FilterSpec:
        return spec if self.r is None else spec.but(r=self.r)

    def bits(self, spec: FilterSpec) -> int:
        blocks, own = self.m // 64, self.own_spec(spec)
        return 64 * (self.split * own.r_lo + (blocks - self.split) * own.r_hi) + self.flag_bits * len(self.flags)


def split_block(spec: FilterSpec, blocks: int) -> int:
    """Number of leading blocks that hold floor(r) columns, so that the mean width is r."""
    return 0 if spec.r_lo == spec.r_hi else round((spec.r_hi - spec.r) * blocks)


def rhs_of(key_h: np.ndarray, seed: int, spec: FilterSpec, values: np.ndarray | None) -> np.ndarray:
    if values is not None:
        return values.astype(U64)
    if spec.variant == "homogeneous":
        return np.zeros(len(key_h), U64)
    return fingerprint_np(key_h, seed, spec.r_hi)


def build_segments(groups: dict[int, np.ndarray], spec: FilterSpec, values: dict[int, np.ndarray] | None = None, fixed_m: int | None = None, budget: int | None = None) -> list[Segment]:
    """Build all segments of a task in lock-step. groups: distinct key hashes by segment; values: for static functions.

    fixed_m: rows of every segment (else from its own count). budget: bits of every segment, whose result width then
    follows from its rows, up to spec.r. Failing segments alone try the next seed (or, for retry="grow", more rows); the
    homogeneous variant cannot fail.
    """
    todo = {s: fixed_m or rows_for(len(k), recommended_eps(spec, len(k)), spec.w, spec.step) for s, k in groups.items()}
    done: dict[int, Segment] = {}
    lanes = 2 if spec.w == 128 else 1
    for attempt in range(spec.seeds):
        if not todo:
            break
        began = time.perf_counter_ns()
        seed = attempt if spec.retry == "reseed" else 0
        names = sorted(todo)
        stride = max(todo.values())
        bank = Bank(stride * len(names), lanes)
        good: dict[int, Segment] = {}
        if spec.variant == "balanced":
            systems = [balanced.System(groups[s], coefficients_np(groups[s], seed, spec.w), rhs_of(groups[s], seed, spec, values and values[s]), todo[s], balanced.Routing.plan(len(groups[s]), spec.w, spec.alpha)) for s in names]
            balanced.build(bank, systems, stride, spec.w, seed)
            for s, y in zip(names, systems, strict=True):
                if y.ok and not (spec.redundant == "fail" and y.redundant):
                    good[s] = Segment(s, y.m, seed, len(y.key_h), None, 0, y.flags, y.routing.shards, y.routing.alpha, y.redundant, attempt + 1, y.additions, y.displacement, 0, y.stats)
        else:
            sizes = np.array([len(groups[s]) for s in names])
            keys = np.concatenate([groups[s] for s in names])
            where = np.repeat(np.arange(len(names)), sizes)
            starts = np.array([todo[s] for s in names])[where] - spec.w + 1
            start = clamp_start_np(salted_np(keys, START, seed), starts, spec.edge) + where * stride
            rhs = rhs_of(keys, seed, spec, values and np.concatenate([values[s] for s in names]))
            got = bank.insert(start, coefficients_np(keys, seed, spec.w), rhs, home=where, homes=len(names))
            bad = set(np.unique(where[got.failed]).tolist())
            if spec.redundant == "fail":
                bad |= set(np.flatnonzero(got.by_home[1]).tolist())
            for at, s in enumerate(names):
                if at not in bad:
                    rows = slice(at * stride, (at + 1) * stride)
                    filled = int(bank.used[rows].sum())
                    moved = int(np.flatnonzero(bank.used[rows]).sum()) - int((start[where == at] - at * stride).sum())
                    good[s] = Segment(s, todo[s], seed, int(sizes[at]), None, 0, redundant=int(sizes[at]) - filled, attempts=attempt + 1, additions=int(got.by_home[0, at]), displacement=moved)
        if good:
            words = back_substitute(bank, spec.r_hi, stride, spec.free)
            spent = (time.perf_counter_ns() - began) // max(1, sum(len(groups[s]) for s in names))
            for at, s in enumerate(names):
                if s in good:
                    seg = good[s]
                    if budget:
                        seg.r = min(spec.r, budget // 64 / (seg.m // 64))
                        if seg.r < 1:
                            raise NoSolution(f"{budget} bits cannot hold a result bit for the {seg.n} keys of segment {s}")
                    own = seg.own_spec(spec)
                    seg.words, seg.split = words[at, : seg.m // 64], split_block(own, seg.m // 64)
                    if seg.r is not None:  # rounding may not pass the budget
                        seg.split = min(seg.m // 64, -(-max(0, own.r_hi * seg.m - budget) // 64)) if own.r_lo != own.r_hi else 0
                    seg.words = seg.words[:, : own.r_hi]
                    if seg.split:
                        seg.words = seg.words.copy()
                        seg.words[: seg.split, own.r_lo :] = 0
                    seg.build_ns = int(spent * seg.n)
                    done[s] = seg
                    del todo[s]
        if spec.retry == "grow":
            todo = {s: rows_for(0, 0, spec.w) if not m else (math.ceil(m * (spec.w + 1) / spec.w / 64) * 64) for s, m in todo.items()}
    if todo:
        raise NoSolution(f"{len(todo)} segments (first: {min(todo)}) had no solution in {spec.seeds} attempts; give more space or seeds")
    return [done[s] for s in sorted(done)]


def query_segment(seg: Segment, spec: FilterSpec, key_h: np.ndarray) -> np.ndarray:
    """Result bits (static function) of keys of this segment; columns a straddling or narrow query lacks are absent."""
    out = np.zeros(len(key_h), U64)
    for rows, start, seed in windows(seg, spec, key_h):
        out[rows] = lookup(seg.words[None], np.zeros(len(start), np.int64), start, coefficients_np(key_h[rows], seed, spec.w))
    return out


def windows(seg: Segment, spec: FilterSpec, key_h: np.ndarray):
    """(rows, starts, seed) of the keys that share a seed; one triple unless shards have seeds of their own."""
    if spec.sharding == "soft":
        start, seeds = softshards.start_of(key_h, seg.m, spec.w, len(seg.flags), seg.flags)
        for seed in np.unique(seeds).tolist():
            rows = np.flatnonzero(seeds == seed)
            yield rows, start[rows], seed
    elif spec.variant == "balanced":
        yield slice(None), balanced.query_starts(key_h, seg.m, spec.w, balanced.Routing(seg.shards, seg.alpha), seg.flags, seg.seed), seg.seed
    else:
        yield slice(None), clamp_start_np(salted_np(key_h, START, seg.seed), seg.m - spec.w + 1, spec.edge), seg.seed


def columns_of(seg: Segment, spec: FilterSpec, start: np.ndarray) -> np.ndarray:
    """How many result bits each query may compare: floor(r) unless its whole window lies in the wide part."""
    own = seg.own_spec(spec)
    return np.where(start // 64 >= seg.split, own.r_hi, own.r_lo)


def contains(seg: Segment, spec: FilterSpec, key_h: np.ndarray) -> np.ndarray:
    out = np.zeros(len(key_h), bool)
    for rows, start, seed in windows(seg, spec, key_h):
        own = key_h[rows]
        got = lookup(seg.words[None], np.zeros(len(own), np.int64), start, coefficients_np(own, seed, spec.w))
        mask = (U64(1) << columns_of(seg, spec, start).astype(U64)) - U64(1)
        out[rows] = ((got ^ rhs_of(own, seed, spec, None)) & mask) == 0
    return out


def contains_ranges(built: list[Segment], spec: FilterSpec, key_h: np.ndarray) -> np.ndarray:
    """contains() where segments are ranges of the order hash: those of one size and seed are asked together."""
    from bandloom.kernel.ranges import order_hash

    at, out = np.searchsorted(np.array([s.from_h for s in built]), order_hash(key_h), "right") - 1, np.zeros(len(key_h), bool)
    kinds: dict[tuple, list[int]] = {}
    for k, s in enumerate(built[:-1]):  # the last one is sized for what was left
        kinds.setdefault((s.m, s.seed, s.split, s.r), []).append(k)
    place, kind = np.zeros(len(built), np.int64), np.full(len(built), len(kinds))
    for number, members in enumerate(kinds.values()):
        place[members], kind[members] = np.arange(len(members)), number
    for number, members in enumerate([*kinds.values(), [len(built) - 1]]):
        rows, first = np.flatnonzero(kind[at] == number), built[members[0]]
        if len(members) == 1:
            out[rows] = contains(first, spec, key_h[rows])
            continue
        own = key_h[rows]
        start = clamp_start_np(salted_np(own, START, first.seed), first.m - spec.w + 1, spec.edge)
        got = lookup(np.stack([built[k].words for k in members]), place[at[rows]], start, coefficients_np(own, first.seed, spec.w))
        mask = (U64(1) << columns_of(first, spec, start).astype(U64)) - U64(1)
        out[rows] = ((got ^ rhs_of(own, first.seed, spec, None)) & mask) == 0
    return out
