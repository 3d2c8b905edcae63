"""Set-at-a-time elimination of band equations, and block-wise back substitution, in numpy.

Several systems (segments) lie end to end in one Bank and advance together. Equations have a start row, one or two
64-bit coefficient words (first position lowest, first bit 1) and a right-hand side of up to 64 bits.

A round: each empty row takes one of the equations that point at it; all others absorb the row they point at and move to
their next set position. Rows never change once filled, the set of filled rows and the verdict do not depend on the
order, so this is the sequential elimination done for all keys at once.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

U64 = np.uint64
ONE, ZERO = U64(1), U64(0)
FEW = 24
LOOKED_UP = 1 << 13  # queries whose words are fetched at once


def ctz(x: np.ndarray) -> np.ndarray:
    """Trailing zeros of nonzero words."""
    return np.bitwise_count((x & (~x + ONE)) - ONE).astype(np.int64)


@dataclass
class Report:
    inserted: int = 0
    redundant: int = 0
    inconsistent: int = 0
    additions: int = 0
    rounds: int = 0
    displacement: int = 0
    failed: np.ndarray | None = None  # positions, in the batch, of equations found contradictory
    by_home: np.ndarray | None = None  # additions and redundant equations of each system, where systems were named

    def ok(self) -> bool:
        return self.inconsistent == 0

    def add(self, other: Report) -> None:
        for name in ("inserted", "redundant", "inconsistent", "additions", "rounds", "displacement"):
            setattr(self, name, getattr(self, name) + getattr(other, name))
        if other.by_home is not None:
            self.by_home = other.by_home if self.by_home is None else self.by_home + other.by_home


class Bank:
    """Echelon rows of one or more systems; lanes is 1, or 2 for width 128."""

    def __init__(self, rows: int, lanes: int = 1):
        self.lanes, self.rows = lanes, rows
        self.used = np.zeros(rows, bool)
        self.c = np.zeros((lanes, rows), U64)
        self.b = np.zeros(rows, U64)
        self._claim = np.zeros(rows, np.int64)

    def insert(self, start: np.ndarray, coeff: np.ndarray, rhs: np.ndarray, log: list | None = None, stop: bool = False, home: np.ndarray | None = None, homes: int = 0) -> Report:
        """Insert a batch. log collects the filled rows, for rollback. stop: end at the first contradiction.

        home: the number, of `homes`, of the system that each equation belongs to, to count additions by system. Rows past a
        system's end are never reached, since coefficient bits there are never set by construction.
        """
        out = Report(by_home=np.zeros((2, homes), np.int64) if home is not None else None)
        i = np.asarray(start, np.int64).copy()
        c = [x.copy() for x in coeff]
        b = np.asarray(rhs, U64).copy()
        pos = np.arange(len(i))
        failed = []
        while len(i):
            if len(i) <= FEW:
                self._finish(i, c, b, pos, np.asarray(start, np.int64), out, failed, log, home)
                break
            out.rounds += 1
            empty = np.flatnonzero(~self.used[i])
            if len(empty):
                rows = i[empty]
                self._claim[rows] = empty  # one of those that point at a row remains
                won = empty[self._claim[rows] == empty]
                at = i[won]
                self.used[at] = True
                for lane in range(self.lanes):
                    self.c[lane, at] = c[lane][won]
                self.b[at] = b[won]
                out.inserted += len(won)
                out.displacement += int(at.sum() - np.asarray(start, np.int64)[pos[won]].sum())
                if log is not None:
                    log.append(at)
                keep = np.ones(len(i), bool)
                keep[won] = False
                i, b, pos, c = i[keep], b[keep], pos[keep], [x[keep] for x in c]
                if not len(i):
                    break
            out.additions += len(i)
            if home is not None:
                out.by_home[0] += np.bincount(home[pos], minlength=homes)
            c = [x ^ self.c[lane, i] for lane, x in enumerate(c)]
            b = b ^ self.b[i]
            live = c[0] != ZERO if self.lanes == 1 else (c[0] | c[1]) != ZERO
            if not live.all():
                gone = ~live
                bad = gone & (b != ZERO)
                n_bad = int(bad.sum())
                out.redundant += int(gone.sum()) - n_bad
                if home is not None:
                    out.by_home[1] += np.bincount(home[pos[gone & ~bad]], minlength=homes)
                if n_bad:
                    out.inconsistent += n_bad
                    failed.append(pos[bad])
                    if stop:
                        break
                i, b, pos, c = i[live], b[live], pos[live], [x[live] for x in c]
            if self.lanes == 1:
                j = ctz(c[0])
                c[0] = c[0] >> j.astype(U64)
            else:
                low = c[0] != ZERO
                lo, hi = np.where(low, c[0], c[1]), np.where(low, c[1], ZERO)
                j = ctz(lo)
                k = j.astype(U64)
                carry = np.where(k > ZERO, hi << ((U64(64) - k) & U64(63)), ZERO)
                c = [(lo >> k) | carry, hi >> k]
                j = j + np.where(low, 0, 64)
            i = i + j
        out.failed = np.concatenate(failed) if failed else np.zeros(0, np.int64)
        return out

    def _finish(self, i, c, b, pos, start, out: Report, failed: list, log: list | None, home) -> None:
        """The last few equations one after another: rounds of a handful would pay numpy's call overhead hundreds of times."""
        rows, bad = [], []
        used, cells, right = self.used, [self.c[lane] for lane in range(self.lanes)], self.b
        for k in range(len(i)):
            at, right_k = int(i[k]), int(b[k])
            word = int(c[0][k]) | (int(c[1][k]) << 64 if self.lanes == 2 else 0)
            steps = 0
            while used[at]:
                steps += 1
                word ^= int(cells[0][at]) | (int(cells[1][at]) << 64 if self.lanes == 2 else 0)
                right_k ^= int(right[at])
                if not word:
                    break
                shift = (word & -word).bit_length() - 1
                at, word = at + shift, word >> shift
            out.additions += steps
            out.rounds += steps
            if home is not None:
                out.by_home[0, home[pos[k]]] += steps
            if word:
                used[at] = True
                for lane in range(self.lanes):
                    cells[lane][at] = (word >> (64 * lane)) & 0xFFFFFFFFFFFFFFFF
                right[at] = right_k
                out.inserted += 1
                out.displacement += at - int(start[pos[k]])
                rows.append(at)
            elif right_k:
                out.inconsistent += 1
                bad.append(pos[k])
            else:
                out.redundant += 1
                if home is not None:
                    out.by_home[1, home[pos[k]]] += 1
        if log is not None and rows:
            log.append(np.array(rows))
        if bad:
            failed.append(np.array(bad))

    def rollback(self, log: list) -> None:
        """Undo the most recent insertions that log lists."""
        for rows in log:
            self.used[rows] = False
            self.c[:, rows] = ZERO
            self.b[rows] = ZERO
        log.clear()

    def in_span(self, start: np.ndarray, coeff: np.ndarray) -> np.ndarray:
        """Which left-hand sides are sums of rows: a dry run that never fills a row."""
        i = np.asarray(start, np.int64).copy()
        c, pos = [x.copy() for x in coeff], np.arange(len(i))
        inside = np.zeros(len(i), bool)
        while len(i):
            hit = self.used[i]
            i, pos, c = i[hit], pos[hit], [x[hit] for x in c]
            c = [x ^ self.c[lane, i] for lane, x in enumerate(c)]
            live = c[0] != ZERO if self.lanes == 1 else (c[0] | c[1]) != ZERO
            inside[pos[~live]] = True
            i, pos, c = i[live], pos[live], [x[live] for x in c]
            if self.lanes == 1:
                j = ctz(c[0])
                c[0] = c[0] >> j.astype(U64)
            else:
                low = c[0] != ZERO
                lo, hi = np.where(low, c[0], c[1]), np.where(low, c[1], ZERO)
                j = ctz(lo)
                k = j.astype(U64)
                c = [(lo >> k) | np.where(k > ZERO, hi << ((U64(64) - k) & U64(63)), ZERO), hi >> k]
                j = j + np.where(low, 0, 64)
            i = i + j
        return inside


class XorBasis:
    """One equation at a time over whole-width integers, as the reference that tests compare the rounds with.

    An equation is the integer of its m coefficient bits with the right-hand side above them; the basis keeps one vector
    for each lowest set bit.
    """

    def __init__(self, m: int):
        self.m, self.vectors = m, {}

    def offer(self, start: int, coeff: int, rhs: int) -> str:
        v = (coeff << start) | (rhs << self.m)
        left = (1 << self.m) - 1
        while v & left and (low := v & -v) in self.vectors:
            v ^= self.vectors[low]
        if v & left:
            self.vectors[v & -v] = v
            return "inserted"
        return "inconsistent" if v else "redundant"

    def rows(self) -> list[int]:
        return sorted(low.bit_length() - 1 for low in self.vectors)


def band_until_failure(rows: int, start: np.ndarray, coeff: np.ndarray, rhs: np.ndarray, first: int = 64) -> tuple[Bank, int]:
    """The longest prefix of the given order that has a solution, and its bank: doubling batches, undo, bisection.

    Consistency of prefixes is monotone, so a failing batch is undone and halved until the failing equation is found.
    first: size of the first batch; what surely fits is cheapest in one. A short system's last equations go one by one, as
    rounds of a handful that move far pay numpy's call overhead for nothing.
    """
    bank, done, step, n = Bank(rows, len(coeff)), 0, first, len(start)
    while done < n:
        if done >= 0.85 * rows and rows <= 1 << 16:
            return bank, done + one_by_one(bank, start[done:], coeff[:, done:], rhs[done:])
        step = min(step, n - done)
        log: list = []
        part = slice(done, done + step)
        if bank.insert(start[part], coeff[:, part], rhs[part], log, stop=True).ok():
            done += step
            step = min(2 * step, 64) if done >= 0.5 * rows else 2 * step
        else:
            bank.rollback(log)
            if step == 1:
                break
            step //= 2
    return bank, done


def one_by_one(bank: Bank, start: np.ndarray, coeff: np.ndarray, rhs: np.ndarray) -> int:
    """Insert equations in order until one contradicts, on plain integers; returns how many were consistent."""

    def whole(lanes: np.ndarray) -> list[int]:
        low = lanes[0].tolist()
        return low if len(lanes) == 1 else [a | (b << 64) for a, b in zip(low, lanes[1].tolist(), strict=True)]

    used, cells, right, filled, n = bank.used.tolist(), whole(bank.c), bank.b.tolist(), [], 0
    for at, word, b in zip(start.tolist(), whole(coeff), rhs.tolist(), strict=True):
        while used[at]:
            word ^= cells[at]
            b ^= right[at]
            if not word:
                break
            shift = (word & -word).bit_length() - 1
            at += shift
            word >>= shift
        if word:
            used[at], cells[at], right[at] = True, word, b
            filled.append(at)
        elif b:
            break
        n += 1
    bank.used[filled] = True
    bank.b[filled] = np.array([right[i] for i in filled], U64)
    for lane in range(bank.lanes):
        bank.c[lane, filled] = np.array([(cells[i] >> (64 * lane)) & 0xFFFFFFFFFFFFFFFF for i in filled], U64)
    return n


def many_until_failure(rows: int, start: np.ndarray, coeff: np.ndarray, rhs: np.ndarray, first: int = 64, sizes: np.ndarray | None = None) -> tuple[Bank, np.ndarray]:
    """band_until_failure for many systems in lock-step: start and rhs [systems, n], coeff [lanes, systems, n].

    sizes: equations of each system, where they are fewer than n. The first batch goes in as ever; a system that it does not
    fit is undone. All that is left is inserted by age, which finds a system's first failing equation without a second attempt.
    """
    systems, n = start.shape[0], np.full(start.shape[0], start.shape[1]) if sizes is None else sizes
    bank = Bank(rows * systems, len(coeff))

    def equations(lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, ...]:
        size = hi - lo
        home = np.repeat(np.arange(systems), size)
        at = np.arange(len(home)) - np.repeat(np.cumsum(size) - size, size) + lo[home]
        return start[home, at] + home * rows, coeff[:, home, at], rhs[home, at], home, at

    log, done = [], np.minimum(first, n)
    i, c, b, home, _ = equations(np.zeros(systems, np.int64), done)
    bad = np.zeros(systems, bool)
    bad[home[bank.insert(i, c, b, log).failed]] = True
    bank.rollback([r[bad[r // rows]] for r in log])
    done[bad] = 0
    return bank, insert_by_age(bank, rows, *equations(done, n), n)


def insert_by_age(bank: Bank, rows: int, i: np.ndarray, coeff: np.ndarray, rhs: np.ndarray, home: np.ndarray, age: np.ndarray, limit: np.ndarray) -> np.ndarray:
    """Insert what does not contradict older equations of its system; returns the age of each system's first contradiction, or
    its limit where there is none. home, age: an equation's system and its place there.

    A row keeps the oldest equation that reached it, and a newer one is pushed out. So an equation absorbs older ones only, what
    is left of one names the first prefix that contradicts itself, and rows as old as that or older are those of the prefix before it.
    """
    limit, c, b = np.asarray(limit, np.int64).copy(), [x.copy() for x in coeff], np.asarray(rhs, U64).copy()
    i, lanes = np.asarray(i, np.int64).copy(), range(bank.lanes)
    home, age, since = home.copy(), np.asarray(age, np.int64).copy(), np.full(bank.rows, -1, np.int64)  # rows filled before are older than all
    while len(i):
        if len(i) <= FEW:
            by_age_one_by_one(bank, i, c, b, home, age, since, limit)
            break
        empty = np.flatnonzero(~bank.used[i])
        go = np.ones(len(i), bool)
        if len(empty):
            bank._claim[i[empty]] = empty
            won = empty[bank._claim[i[empty]] == empty]
            at = i[won]
            bank.used[at], bank.b[at], since[at] = True, b[won], age[won]
            for lane in lanes:
                bank.c[lane, at] = c[lane][won]
            go[won] = False
        older = np.flatnonzero(go & (age < since[i]))
        if len(older):
            bank._claim[i[older]] = older
            won = older[bank._claim[i[older]] == older]
            at = i[won]
            for lane in lanes:
                bank.c[lane, at], c[lane][won] = c[lane][won], bank.c[lane, at]
            bank.b[at], b[won] = b[won], bank.b[at]
            since[at], age[won] = age[won], since[at]
        steps = np.flatnonzero(go & (age > since[i]))
        at = i[steps]
        own = [c[lane][steps] ^ bank.c[lane, at] for lane in lanes]
        right = b[steps] ^ bank.b[at]
        gone = own[0] == ZERO if bank.lanes == 1 else (own[0] | own[1]) == ZERO
        if gone.any():
            bad = steps[gone & (right != ZERO)]
            np.minimum.at(limit, home[bad], age[bad])
            go[steps[gone]] = False
        if bank.lanes == 1:
            j = ctz(own[0])
            own[0] >>= j.astype(U64) & U64(63)
        else:
            low = own[0] != ZERO
            lo, hi = np.where(low, own[0], own[1]), np.where(low, own[1], ZERO)
            j = ctz(lo)
            k = j.astype(U64) & U64(63)
            own = [(lo >> k) | np.where(k > ZERO, hi << ((U64(64) - k) & U64(63)), ZERO), hi >> k]
            j = j + np.where(low, 0, 64)
        for lane in lanes:
            c[lane][steps] = own[lane]
        b[steps] = right
        i[steps] += np.where(gone, 0, j)
        go &= age < limit[home]
        i, b, home, age, c = i[go], b[go], home[go], age[go], [x[go] for x in c]
    new = np.flatnonzero(since >= limit[np.arange(bank.rows) // rows])
    bank.rollback([new])
    return limit


def by_age_one_by_one(bank: Bank, i, c, b, home, age, since: np.ndarray, limit: np.ndarray) -> None:
    """insert_by_age for the last few equations, one after another."""
    used, cells, right = bank.used, [bank.c[lane] for lane in range(bank.lanes)], bank.b

    def held(at: int) -> int:
        return int(cells[0][at]) | (int(cells[1][at]) << 64 if bank.lanes == 2 else 0)

    def keep(at: int, word: int, value: int, own: int) -> None:
        used[at], right[at], since[at] = True, value, own
        for lane, cell in enumerate(cells):
            cell[at] = (word >> (64 * lane)) & 0xFFFFFFFFFFFFFFFF

    for k in np.argsort(age, kind="stable").tolist():
        at, value, own, system = int(i[k]), int(b[k]), int(age[k]), int(home[k])
        word = int(c[0][k]) | (int(c[1][k]) << 64 if bank.lanes == 2 else 0)
        while own < limit[system]:
            if not used[at]:
                keep(at, word, value, own)
                break
            there, value_there, age_there = held(at), int(right[at]), int(since[at])
            if own < age_there:
                keep(at, word, value, own)
                own = age_there
            word, value = word ^ there, value ^ value_there
            if not word:
                if value:
                    limit[system] = min(int(limit[system]), own)  # a pushed-out one may be newer than the limit
                break
            shift = (word & -word).bit_length() - 1
            at, word = at + shift, word >> shift


def free_values(rows: np.ndarray, r: int, rule: str) -> np.ndarray:
    """Right-hand sides of empty rows, from the row number inside the segment alone."""
    if rule == "zero":
        return np.zeros(len(rows), U64)
    mask = U64((1 << r) - 1)
    if rule == "odd_multiple":
        return (rows.astype(U64) * U64(0x9E3779B97F4A7C15)) & mask
    from bandloom.functions.hashing import xxh64_long

    return xxh64_long(rows.astype(U64), U64(99)) & mask


def back_substitute(bank: Bank, r: int, m: int, rule: str = "zero") -> np.ndarray:
    """Solution words [segments, blocks, r]: bit i of word (s, k, j) is column j of row 64k + i of segment s.

    All systems have m rows, a multiple of 64. Inside a block every row's own-block bits are cleared by the rows below it,
    for all blocks at once; what is left is a recurrence over blocks, from the last to the first.
    """
    segments, blocks, lanes = bank.rows // m, m // 64, bank.lanes
    n = segments * blocks
    empty = ~bank.used
    rhs = bank.b.copy()
    local = np.arange(bank.rows) % m
    rhs[empty] = free_values(local[empty], r, rule)
    c = bank.c.copy()
    c[:, empty] = ZERO
    c[0, empty] = ONE
    # Row i of every block side by side, so that each step works on whole runs of memory.
    c = np.ascontiguousarray(c.reshape(lanes, n, 64).transpose(0, 2, 1))
    rhs = np.ascontiguousarray(rhs.reshape(n, 64).T)
    o = np.arange(64, dtype=U64)[:, None]
    spill = c >> ((U64(64) - o) & U64(63))
    spill[:, 0] = ZERO
    own = c[0] << o
    after = [spill[0] | (c[1] << o), spill[1]] if lanes == 2 else [spill[0]]
    for at in range(0, n, 2048):
        cut = slice(at, at + 2048)
        bits, values, words_ = own[:, cut].copy(), rhs[:, cut].copy(), [a[:, cut].copy() for a in after]
        for j in range(63, 0, -1):
            mask = ZERO - ((bits[:j] >> U64(j)) & ONE)
            for a in words_:
                a[:j] ^= a[j] & mask
            values[:j] ^= values[j] & mask
        rhs[:, cut] = values
        for a, b in zip(after, words_, strict=True):
            a[:, cut] = b
    rhs, after = rhs.T, [np.ascontiguousarray(a.T).reshape(segments, blocks, 64) for a in after]
    # Right-hand sides as one word per column.
    cols = np.arange(r, dtype=U64)
    bits = ((rhs[:, :, None] >> cols) & ONE).astype(np.uint8)
    base = np.packbits(bits, axis=1, bitorder="little").transpose(0, 2, 1)
    base = np.ascontiguousarray(base).view("<u8")[..., 0].reshape(segments, blocks, r)
    words = np.zeros((segments, blocks + lanes, r), U64)
    for k in range(blocks - 1, -1, -1):
        parity = np.zeros((segments, 64, r), np.uint8)
        for lane, a in enumerate(after):
            parity ^= np.bitwise_count(a[:, k, :, None] & words[:, k + 1 + lane, None, :]) & 1
        got = np.ascontiguousarray(np.packbits(parity, axis=1, bitorder="little").transpose(0, 2, 1)).view("<u8")[..., 0]
        words[:, k] = base[:, k] ^ got
    return words[:, :blocks]


def lookup(words: np.ndarray, segment: np.ndarray, start: np.ndarray, coeff: np.ndarray, columns: int | None = None) -> np.ndarray:
    """Result bits of each query, column j as bit j. A block's words are fetched together, in pieces that fit the cache."""
    segments, blocks, r = words.shape
    lanes, r = len(coeff), r if columns is None else columns
    flat = np.concatenate([words[:, :, :r], np.zeros((segments, lanes, r), U64)], 1).reshape(-1, r)
    out = np.zeros((len(start), 8), np.uint8)
    for at in range(0, len(start), LOOKED_UP):
        cut = slice(at, at + LOOKED_UP)
        s = start[cut]
        row, o = segment[cut] * (blocks + lanes) + (s >> 6), (s & 63).astype(U64)[:, None]
        here, odd = flat[row], None
        for k in range(lanes):
            after = flat[row + k + 1]
            window = here >> o
            window |= (after << ONE) << (U64(63) - o)  # two shifts, as one by 64 would not clear the word
            window &= coeff[k][cut, None]
            count = np.bitwise_count(window)
            odd, here = count if odd is None else odd ^ count, after
        bits = np.packbits(odd & 1, axis=1, bitorder="little")
        out[cut, : bits.shape[1]] = bits
    return out.view("<u8")[:, 0]


def any_matches(words: np.ndarray, start: np.ndarray, coeff: np.ndarray, fp: np.ndarray, at_once: int = 1024) -> np.ndarray:
    """Whether some of many systems of one size has the fingerprint of each query; words [systems, blocks, r].

    A row and column of all systems is one bit vector, so a query's sum is that of its rows' vectors, for 64 systems in a
    word. Sums of each 8 neighbouring rows are tabulated, column by column, and queries that no system can match are dropped.
    """
    systems, blocks, r = words.shape
    lanes, m, out = len(coeff), 64 * blocks, np.zeros(len(start), bool)
    # The coefficients as bytes of the aligned groups of 8 rows that they fall into.
    raw = np.zeros((len(start), 8 * lanes + 2), np.uint16)
    raw[:, 1:-1] = np.ascontiguousarray(coeff.T).astype("<u8").view(np.uint8).reshape(len(start), -1)
    shift = (start & 7).astype(np.uint16)[:, None]
    pieces = (((raw[:, 1:] << shift) | (raw[:, :-1] >> (8 - shift))) & 255).astype(np.uint8)
    group = start >> 3
    for first in range(0, systems, at_once):
        some = np.ascontiguousarray(words[first : first + at_once])
        k, wide = len(some), -(-len(some) // 64)
        bits = np.unpackbits(some.astype("<u8").view(np.uint8).reshape(k, blocks, r, 8), axis=3, bitorder="little")
        padded = np.zeros((r, m + 8 * (8 * lanes + 1), 64 * wide), np.uint8)
        padded[:, :m, :k] = bits.transpose(2, 1, 3, 0).reshape(r, m, k)
        vectors = np.packbits(padded, axis=2, bitorder="little").view("<u8")
        real = np.packbits(np.arange(64 * wide) < k, bitorder="little").view("<u8")
        for at in range(0, len(start), 1 << 16):
            rows = at + np.flatnonzero(~out[at : at + (1 << 16)])
            alive = np.repeat(real[None], len(rows), 0)
            for j in range(r):
                if not len(rows):
                    break
                table = np.zeros((vectors.shape[1] // 8, 256, wide), U64)
                for b in range(8):
                    table[:, 1 << b : 2 << b] = table[:, : 1 << b] ^ vectors[j, b::8][:, None]
                for lo in range(0, len(rows), 4096):
                    own = rows[lo : lo + 4096]
                    got = ZERO - (((fp[own] >> U64(j)) & ONE) ^ ONE)[:, None]
                    for i in range(pieces.shape[1]):
                        got = got ^ table[group[own] + i, pieces[own, i]]
                    alive[lo : lo + 4096] &= got
                keep = alive.any(1)
                rows, alive = rows[keep], alive[keep]
            out[rows] = True
    return out
