"""Tiered load balancing inside contiguous band systems, for all systems of a task in lock-step.

Soft shards are ranges of start rows; tier 1 is overloaded by 1 + alpha, later tiers underloaded by 1 - alpha. A shard's
keys fall into eight geometric buckets. Which buckets a shard takes is chosen by where their keys start, so that few rows
stay empty; these are inserted largest first, rank by rank over all shards of a tier, and a bucket that contradicts the
rows present is undone, after which others may fit. Buckets left out are flagged, and their keys go to a shard of the next
tier. The last tier's shard takes everything or the attempt fails.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from bandloom.functions.hashing import ROUTE, SECOND, START, U64, reduce32_np, salted_np
from bandloom.kernel.banding import Bank, Report
from bandloom.plans.planning import alpha_plan, bucket_shares, tier_plan

BUCKETS = 8
SETS = ((np.arange(1 << BUCKETS)[:, None] >> np.arange(BUCKETS)) & 1).astype(np.float32)  # of buckets, by their bits
AHEAD, MOST = 0.4, 0.6  # of a band: keys that a shard should end ahead of its rows, and keys ahead that are likely to contradict
PASSES = 3


@dataclass
class Routing:
    """Where the keys of a system of n keys go: tier sizes, start ranges and weights, all from n, w, alpha."""

    shards: list[int]
    alpha: float
    cuts: np.ndarray = field(init=False)  # cumulative primary weights, of 2^32
    buckets: np.ndarray = field(init=False)  # cumulative bucket shares, of 2^32

    def __post_init__(self):
        s, first = sum(self.shards), self.shards[0]
        weight = np.ones(s) if s == 1 else np.where(np.arange(s) < first, 1 + self.alpha, 1 - self.alpha)
        if s > 1:
            weight *= s / weight.sum()
        self.cuts = np.floor(np.cumsum(weight / weight.sum()) * 2.0**32).astype(np.int64)
        self.cuts[-1] = 1 << 32
        self.buckets = np.floor(np.cumsum(bucket_shares(BUCKETS)) * 2.0**32).astype(np.int64)
        self.buckets[-1] = 1 << 32

    @classmethod
    def plan(cls, n: int, w: int, alpha: float | None = None) -> Routing:
        shards = tier_plan(n, w)
        return cls(shards, alpha_plan(n / sum(shards)) if alpha is None else alpha)

    @property
    def total(self) -> int:
        return sum(self.shards)

    def tier_of(self, shard: np.ndarray) -> np.ndarray:
        return np.searchsorted(np.cumsum(self.shards), shard, "right")

    def primary(self, key_h: np.ndarray, seed: int) -> tuple[np.ndarray, np.ndarray]:
        """Shard and bucket of each key."""
        h = salted_np(key_h, ROUTE, seed)
        shard = np.searchsorted(self.cuts, (h >> U64(32)).astype(np.int64), "right")
        return shard, np.searchsorted(self.buckets, (h & U64(0xFFFFFFFF)).astype(np.int64), "right")

    def following(self) -> tuple[np.ndarray, np.ndarray]:
        """For each shard the first shard, and the number of shards, of the tier after its own (the last tier stays)."""
        tier = np.minimum(self.tier_of(np.arange(self.total)) + 1, len(self.shards) - 1)
        return np.concatenate([[0], np.cumsum(self.shards)])[tier], np.array(self.shards)[tier]

    def secondary(self, key_h: np.ndarray, shard: np.ndarray, seed: int) -> np.ndarray:
        """A shard of the tier after the primary one's."""
        first, size = self.following()
        return first[shard] + reduce32_np(salted_np(key_h, SECOND, seed), size[shard])

    def start_in(self, key_h: np.ndarray, shard: np.ndarray, starts: int, seed: int) -> np.ndarray:
        """Start row within the shard's share of the start range."""
        lo = shard * starts // self.total
        size = (shard + 1) * starts // self.total - lo
        return lo + reduce32_np(salted_np(key_h, START, seed), size)


@dataclass
class System:
    """One system: its keys with coefficients and right-hand sides, its rows, and what became of it."""

    key_h: np.ndarray
    coeff: np.ndarray
    rhs: np.ndarray
    m: int
    routing: Routing
    ok: bool = True
    flags: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))  # 8 bits of each shard
    redundant: int = 0
    additions: int = 0
    displacement: int = 0
    stats: dict = field(default_factory=lambda: {"deferred": [], "tier_keys": []})


def build(bank: Bank, systems: list[System], stride: int, w: int, seed: int) -> None:
    """Fill the bank, in which system k has the rows from k * stride on; sets each system's outcome and counters."""
    routes = [s.routing for s in systems]
    sizes = [len(s.key_h) for s in systems]
    home = np.repeat(np.arange(len(systems)), sizes)
    key_h, coeff, rhs = np.concatenate([s.key_h for s in systems]), np.concatenate([s.coeff for s in systems], 1), np.concatenate([s.rhs for s in systems])
    base = np.concatenate([[0], np.cumsum([r.total for r in routes])])  # shards are numbered over all systems
    drawn = []
    for k, s in enumerate(systems):
        shard, bucket = s.routing.primary(s.key_h, seed)
        second, starts = s.routing.secondary(s.key_h, shard, seed), s.m - w + 1
        drawn.append((shard + base[k], bucket, s.routing.tier_of(shard), second + base[k], s.routing.start_in(s.key_h, shard, starts, seed) + k * stride, s.routing.start_in(s.key_h, second, starts, seed) + k * stride))
    shard, bucket, tier, second, first_start, second_start = (np.concatenate([p[i] for p in drawn]) for i in range(6))
    parts = max(1, w // 2)
    last = np.array([len(r.shards) - 1 for r in routes])
    flags, load = np.zeros(base[-1], np.int64), np.zeros((base[-1], parts), np.float32)  # load: keys that were put, by shard and part of its rows
    alive = np.ones(len(systems), bool)
    total = Report()

    def put(rows: np.ndarray, start: np.ndarray, log: list | None) -> np.ndarray:
        """Systems in which something contradicts, or, with a log, the rows that do."""
        got = bank.insert(start[rows], coeff[:, rows], rhs[rows], log, home=home[rows], homes=len(systems))
        total.add(got)
        bad = rows[got.failed]
        if log is None:
            alive[home[bad]] = False
        return bad

    ahead = np.zeros(len(systems))  # by how much the keys before the current tier's rows exceed the rows before them
    rows_of = [np.arange(r.total + 1) * (s.m - w + 1) // r.total for r, s in zip(routes, systems, strict=True)]
    share, low = np.concatenate([np.diff(x) for x in rows_of]), np.concatenate([x[:-1] + k * stride for k, x in enumerate(rows_of)])

    def piece(where: np.ndarray, start: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """The part of its shard's rows in which a key starts."""
        at = where[rows]
        return (start[rows] - low[at]) * parts // np.maximum(share[at], 1)

    def count(into: np.ndarray, where: np.ndarray, start: np.ndarray, rows: np.ndarray) -> None:
        np.add.at(into, (where[rows], piece(where, start, rows)), 1)

    def choose(size: np.ndarray, t: int) -> tuple[np.ndarray, np.ndarray]:
        """Buckets to put into each shard of tier t, as bits, and what is then ahead at the tier's end.

        size: keys by shard, bucket and part of the shard's rows. For each set of buckets, keys are followed from part to part:
        a row that no key is left for by then stays empty, and keys far ahead of the rows would contradict. The set that
        leaves the fewest rows empty is taken, with a price on those keys and on a shard that ends with few keys ahead.
        """
        out, past = np.zeros(base[-1], np.int64), ahead.copy()
        here = np.flatnonzero(alive & (last > t))
        tier_size, first = (np.array([f(routes[k].shards) for k in here], np.int64) for f in (lambda x: x[t], lambda x: sum(x[:t])))
        for at in range(int(tier_size.max(initial=0))):
            own = here[tier_size > at]
            s = base[own] + first[tier_size > at] + at
            come, step = SETS @ size[s] + load[s][:, None], (share[s] / parts)[:, None]
            now = np.repeat(past[own][:, None], len(SETS), 1)
            cost = np.zeros_like(now)
            for part in range(parts):
                now += come[:, :, part] - step
                cost -= np.minimum(now, 0)
                np.maximum(now, 0, out=now)
                cost += np.maximum(now - MOST * w, 0) / 2
            out[s] = best = np.argmin(cost + np.maximum(AHEAD * w - now, 0) * 0.3, 1)
            past[own] = now[np.arange(len(own)), best]
        return out, past

    def attempt(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Put buckets; those that contradict are taken out. Rows of the buckets that stay, and of the others."""
        log: list = []
        bad = put(rows, first_start, log)
        if not len(bad):
            return rows, bad
        # Undo the batch in the systems that failed and put the buckets that did not again. Rows that did not fail are
        # consistent with one another, so this second time nothing can fail.
        again, full = np.zeros(len(systems), bool), np.zeros(base[-1], bool)
        again[home[bad]], full[shard[bad]] = True, True
        bank.rollback([at[again[at // stride]] for at in log])
        out = full[shard[rows]]
        if len(put(rows[~out & again[home[rows]]], first_start, [])):
            raise AssertionError("a consistent batch failed")
        return rows[~out], rows[out]

    waiting = np.zeros(0, np.int64)  # keys deferred into the current tier
    for t in range(int(last.max(initial=0)) + 1):
        put(waiting, second_start, None)
        waiting = waiting[alive[home[waiting]]]
        own = np.flatnonzero((tier == t) & alive[home])
        into = np.bincount(home[waiting], minlength=len(systems)) + np.bincount(home[own], minlength=len(systems))
        final = last[home[own]] == t
        put(own[final], first_start, None)
        own = own[~final]
        count(load, second, second_start, waiting)
        left, size = own, np.zeros((base[-1], BUCKETS, parts), np.float32)
        np.add.at(size, (shard[own], bucket[own], piece(shard, first_start, own)), 1)
        refused = []
        for _ in range(PASSES):  # what failed leaves room, perhaps for a bucket that was not chosen
            chosen = ((choose(size, t)[0][shard[left]] >> bucket[left]) & 1).astype(bool)
            some, left, before = left[chosen], left[~chosen], sum(map(len, refused))
            for rank in range(BUCKETS):
                held, failed = attempt(some[bucket[some] == rank])
                count(load, shard, first_start, held)
                size[shard[held], rank] = size[shard[failed], rank] = 0
                refused.append(failed)
            if sum(map(len, refused)) == before:
                break
        ahead = choose(np.zeros_like(size), t)[1]
        waiting = np.concatenate([left, *refused])
        np.bitwise_or.at(flags, shard[waiting], 1 << bucket[waiting])
        out = np.bincount(home[waiting], minlength=len(systems))
        for k, s in enumerate(systems):
            if t <= last[k]:
                s.stats["tier_keys"].append(int(into[k]))
            if t < last[k]:
                s.stats["deferred"].append(int(out[k]))
    for k, s in enumerate(systems):
        s.ok, s.flags = bool(alive[k]), flags[base[k] : base[k + 1]].copy()
        s.additions = int(total.by_home[0][k]) if total.by_home is not None else 0
        filled = np.flatnonzero(bank.used[k * stride : k * stride + s.m])
        s.redundant = sizes[k] - len(filled)
        mine = slice(sum(sizes[:k]), sum(sizes[: k + 1]))
        moved = ((s.flags[shard[mine] - base[k]] >> bucket[mine]) & 1).astype(bool)
        s.displacement = int(filled.sum()) - int((np.where(moved, second_start[mine], first_start[mine]) - k * stride).sum())


def query_starts(key_h: np.ndarray, m: int, w: int, routing: Routing, flags: np.ndarray, seed: int) -> np.ndarray:
    """The start row that holds for each key: primary, or secondary where its bucket's flag is set."""
    shard, bucket = routing.primary(key_h, seed)
    moved = ((flags[shard] >> bucket) & 1).astype(bool)
    shard = np.where(moved, routing.secondary(key_h, shard, seed), shard)
    return routing.start_in(key_h, shard, m - w + 1, seed)
