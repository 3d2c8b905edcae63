"""Soft shards that change their seed instead of deferring keys: ranges of one contiguous system, built in order.

A shard that contradicts what is there is undone and tried under another seed; when its seeds are used up, the shard before
it moves on to its next seed, and so on back. The seed of each shard is its metadata.
"""

from __future__ import annotations

import numpy as np

from bandloom.functions.hashing import ROUTE, START, coefficients_np, reduce32_np, salted_np
from bandloom.kernel.banding import Bank

SEEDS = 8  # three bits of metadata a shard


def home_of(key_h: np.ndarray, shards: int) -> np.ndarray:
    return reduce32_np(salted_np(key_h, ROUTE), shards)


def build(key_h: np.ndarray, rhs_of, m: int, w: int, shards: int, seeds: int = SEEDS, budget: int | None = None) -> tuple[bool, Bank, list[int], int]:
    """Success, bank, seed per shard, attempts. rhs_of(rows, seed) gives right-hand sides of key_h[rows]."""
    starts, budget = m - w + 1, budget or 400 + 8 * shards
    home = home_of(key_h, shards)
    order = np.argsort(home, kind="stable")
    groups = np.split(order, np.searchsorted(home[order], np.arange(1, shards)))
    bank, chosen, logs, tried = Bank(m, 2 if w == 128 else 1), [0] * shards, [None] * shards, 0
    s = 0
    while s < shards:
        if tried >= budget:
            return False, bank, chosen, tried
        keys, seed = key_h[groups[s]], chosen[s]
        lo = s * starts // shards
        start = lo + reduce32_np(salted_np(keys, START, seed), (s + 1) * starts // shards - lo)
        log: list = []
        tried += 1
        if bank.insert(start, coefficients_np(keys, seed, w), rhs_of(groups[s], seed), log).ok():
            logs[s] = log
            s += 1
            continue
        bank.rollback(log)
        chosen[s] += 1
        while chosen[s] == seeds:  # back to the shard before
            chosen[s] = 0
            s -= 1
            if s < 0:
                return False, bank, chosen, tried
            bank.rollback(logs[s])
            chosen[s] += 1
    return True, bank, chosen, tried


def start_of(key_h: np.ndarray, m: int, w: int, shards: int, chosen) -> tuple[np.ndarray, np.ndarray]:
    """Start row and seed of each key of a finished system."""
    starts, home = m - w + 1, home_of(key_h, shards)
    seed, start = np.asarray(chosen, np.int64)[home], np.zeros(len(key_h), np.int64)
    lo = home * starts // shards
    size = (home + 1) * starts // shards - lo
    for v in np.unique(seed).tolist():
        own = seed == v
        start[own] = lo[own] + reduce32_np(salted_np(key_h[own], START, v), size[own])
    return start, seed
