"""The filters that band filters are compared with, as set-at-a-time numpy kernels on distinct 64-bit key hashes.

Every family has build(keys, ...), contains(keys) without false negatives, and bits (its size as a compact structure).
"""

from __future__ import annotations

import itertools
import math
from dataclasses import dataclass

import numpy as np

from bandloom.functions.hashing import START, U64, clamp_start_np, coefficients_np, distinct_np, fingerprint_np, reduce32_np, salted_np
from bandloom.kernel.banding import Bank, back_substitute, lookup
from bandloom.kernel.bands import NoSolution
from bandloom.plans.planning import rows_for


def at(h: np.ndarray, size: int) -> np.ndarray:
    return reduce32_np(h, size)


class BitSet:
    def __init__(self, size: int):
        self.words = np.zeros(-(-size // 64), U64)

    def set(self, pos: np.ndarray) -> None:
        flat = np.zeros(len(self.words) * 64, np.uint8)
        flat[pos] = 1
        self.words |= np.packbits(flat, bitorder="little").view("<u8")

    def get(self, pos: np.ndarray) -> np.ndarray:
        return ((self.words[pos >> 6] >> (pos & 63).astype(U64)) & U64(1)).astype(bool)


class Bloom:
    """k bits anywhere (AND probing)."""

    def __init__(self, keys: np.ndarray, bits_per_key: float = 10, k: int | None = None):
        self.size = max(64, math.ceil(len(keys) * bits_per_key / 64) * 64)
        self.k = k or max(1, round(bits_per_key * math.log(2)))
        self.set = BitSet(self.size)
        for p in self._positions(keys):
            self.set.set(p)
        self.bits = self.size

    def _positions(self, keys):
        a, b = salted_np(keys, 21), salted_np(keys, 22) | U64(1)
        for i in range(self.k):
            yield at(a + U64(i) * b, self.size)

    def contains(self, keys):
        out = np.ones(len(keys), bool)
        for p in self._positions(keys):
            live = np.flatnonzero(out)
            out[live] = self.set.get(p[live])
        return out


class BlockedBloom(Bloom):
    """All bits in one aligned 512-bit block. fixed8: one bit in each of its 8 words; any_k: k bits anywhere in it.

    blocks=2 splits them over two independent blocks.
    """

    def __init__(self, keys, bits_per_key=10, k=None, variant="fixed8", blocks=1):
        self.n_blocks = max(1, math.ceil(len(keys) * bits_per_key / 512))
        self.variant, self.parts = variant, blocks
        super().__init__(keys, self.n_blocks * 512 / max(1, len(keys)), 8 if variant == "fixed8" else k or max(1, round(bits_per_key * math.log(2))))
        self.bits = self.n_blocks * 512

    def _positions(self, keys):
        self.size = self.n_blocks * 512
        if len(self.set.words) * 64 < self.size:
            self.set = BitSet(self.size)
        homes = [at(salted_np(keys, 30 + p), self.n_blocks) * 512 for p in range(self.parts)]
        low, high = salted_np(keys, 33), salted_np(keys, 34)
        for i in range(self.k):
            h = low if i < 7 else high
            nine = ((h >> U64(9 * (i % 7))) & U64(511)).astype(np.int64)
            inside = (i % 8) * 64 + (nine & 63) if self.variant == "fixed8" else nine
            yield homes[i % self.parts] + inside


class Cuckoo:
    """Fingerprints in one of two buckets (OR probing). Placed in rounds; full buckets evict.

    cell_bits: bits per cell; slots per bucket. sorted_cells: each bucket's cells are kept sorted by their lowest 4 bits,
    whose sorted combinations take one bit less per cell. block: (buckets, cells) per 512-bit block with counters instead
    of empty cells (capacity limits per bucket and per block).
    """

    def __init__(self, keys, cell_bits=12, load=0.95, slots=4, sorted_cells=False, block=None, rounds=4000):
        self.cell_bits, self.slots, self.block = cell_bits, slots, block
        n = len(keys)
        if block:
            self.buckets = max(1, math.ceil(n / (block[1] * load))) * block[0]
            self.bits = self.buckets // block[0] * 512
        else:
            self.buckets = max(2, math.ceil(n / (slots * load)))
            self.bits = self.buckets * slots * (cell_bits - 1 if sorted_cells else cell_bits)
        self.sorted_cells = sorted_cells
        rng = np.random.default_rng(1)
        fp, b1, b2 = self._hash(keys)
        cells = np.full((self.buckets, slots), -1, np.int64)  # number of the key in each cell
        inblock = np.zeros(self.buckets // block[0] if block else 1, np.int64)
        pending, where = np.arange(n), b1.copy()
        for _ in range(rounds):
            if not len(pending):
                break
            order = np.lexsort((rng.random(len(pending)), where[pending]))
            pending = pending[order]
            b = where[pending]
            rank = np.arange(len(b)) - np.searchsorted(b, b, "left")
            free = (cells[b] < 0).sum(1)
            fits = rank < free
            if block:
                blk = b // block[0]
                room = block[1] - inblock[blk]
                share = np.zeros(len(b), np.int64)
                share[fits] = np.arange(int(fits.sum())) - np.searchsorted(blk[fits], blk[fits], "left")
                fits &= share < room
            put, bb = pending[fits], b[fits]
            slot = np.argsort(cells[bb] >= 0, axis=1, kind="stable")[np.arange(len(bb)), rank[fits]]
            cells[bb, slot] = put
            if block:
                np.add.at(inblock, bb // block[0], 1)
            left, lb = pending[~fits], b[~fits]
            # Half of the losers try the other bucket; one per bucket evicts a random cell.
            first = np.concatenate([[True], lb[1:] != lb[:-1]]) if len(lb) else np.zeros(0, bool)
            if block:
                left, lb, moved = self._make_room(cells, left, lb, block[0], rng)
                where[moved] = b1[moved] + b2[moved] - where[moved]
                pending = np.concatenate([left, moved])
                where[left] = b1[left] + b2[left] - where[left]
                continue
            kick = first & (rng.random(len(lb)) < 0.5) & ((cells[lb] >= 0).sum(1) > 0)
            kb, kk = lb[kick], left[kick]
            slot = np.argmax(rng.random((len(kb), slots)) * (cells[kb] >= 0), axis=1)
            victims = cells[kb, slot]
            cells[kb, slot] = kk
            where[victims] = b1[victims] + b2[victims] - where[victims]
            stay = left[~kick]
            where[stay] = b1[stay] + b2[stay] - where[stay]
            pending = np.concatenate([stay, victims])
        if len(pending):
            raise NoSolution("cuckoo buckets overflow; lower the load")
        self.cells = np.where(cells >= 0, fp[np.maximum(cells, 0)], 0 if sorted_cells else -1)
        if sorted_cells:
            self.coded, self.cells = SortedBuckets.encode(self.cells, cell_bits), None

    def _make_room(self, cells, left, lb, per_block, rng):
        """One key per full block takes a cell of its bucket; a random cell of that bucket or block gives way."""
        order = rng.permutation(len(lb))
        _, first = np.unique(lb[order] // per_block, return_index=True)
        chosen = np.zeros(len(lb), bool)
        chosen[order[first]] = rng.random(len(first)) < 0.5
        victims = []
        for key, bucket in zip(left[chosen].tolist(), lb[chosen].tolist(), strict=True):
            full = (cells[bucket] >= 0).all()
            lo = bucket if full else bucket // per_block * per_block
            rows, slots = np.nonzero(cells[lo : lo + (1 if full else per_block)] >= 0)
            k = rng.integers(len(rows))
            victims.append(int(cells[lo + rows[k], slots[k]]))
            cells[lo + rows[k], slots[k]] = -1
            cells[bucket, np.flatnonzero(cells[bucket] < 0)[0]] = key
        return left[~chosen], lb[~chosen], np.array(victims, np.int64)

    def _hash(self, keys):
        h = salted_np(keys, 41)
        fp = (h & U64((1 << self.cell_bits) - 1)).astype(np.int64)
        fp = np.maximum(fp, 1)
        b1 = at(h, self.buckets)
        # The other bucket mirrors around an amount that the fingerprint alone decides, so it can be found from either.
        turn = at(salted_np(fp, 42), self.buckets)
        return fp, b1, (turn - b1) % self.buckets

    def contains(self, keys):
        fp, b1, b2 = self._hash(keys)
        if self.sorted_cells:
            first, second = (SortedBuckets.decode(self.coded[b], self.cell_bits) for b in (b1, b2))
        else:
            first, second = self.cells[b1], self.cells[b2]
        return (first == fp[:, None]).any(1) | (second == fp[:, None]).any(1)


class SortedBuckets:
    """Buckets of four cells in one word each: the four lowest nibbles, sorted, are one of 3876 combinations (12 bits), and
    the cells' upper bits follow in that order. Cells of 16 bits so take 60 bits a bucket."""

    nibbles = np.array(list(itertools.combinations_with_replacement(range(16), 4)), np.int64)
    place = np.zeros(1 << 16, np.int64)
    place[(nibbles << np.array([0, 4, 8, 12])).sum(1)] = np.arange(len(nibbles))

    @classmethod
    def encode(cls, cells: np.ndarray, bits: int) -> np.ndarray:
        cells = np.take_along_axis(cells, np.argsort(cells & 15, axis=1, kind="stable"), 1)
        word = cls.place[((cells & 15) << np.array([0, 4, 8, 12])).sum(1)].astype(U64)
        for i in range(4):
            word |= (cells[:, i] >> 4).astype(U64) << U64(12 + (bits - 4) * i)
        return word

    @classmethod
    def decode(cls, words: np.ndarray, bits: int) -> np.ndarray:
        low, mask = cls.nibbles[(words & U64(4095)).astype(np.int64)], U64((1 << (bits - 4)) - 1)
        high = np.stack([(words >> U64(12 + (bits - 4) * i)) & mask for i in range(4)], 1).astype(np.int64)
        return (high << 4) | low


class Quotient:
    """Sorted remainders in runs per quotient, three metadata bits a slot (OR probing)."""

    def __init__(self, keys, r=7, load=0.95):
        self.r = r
        self.slots = max(64, math.ceil(len(keys) / load))
        self.stored = distinct_np(self._print(keys))
        self.bits = self.slots * (r + 3)

    def _print(self, keys):
        h = salted_np(keys, 51)
        return (at(h, self.slots).astype(U64) << U64(self.r)) | (h & U64((1 << self.r) - 1))

    def contains(self, keys):
        p = self._print(keys)
        k = np.minimum(np.searchsorted(self.stored, p), len(self.stored) - 1)
        return self.stored[k] == p if len(self.stored) else np.zeros(len(p), bool)


class Xor:
    """Three random cells XOR to the fingerprint; solved by peeling.

    window: share of the cell range that a key's positions span (None: three fixed thirds). plus: empty cells of the last
    third are compressed away behind a rank bitmap. cells_per_word: i cells of 64/i bits a word (r = 64/i).
    """

    def __init__(self, keys, r=8, expansion=1.23, plus=False, window=None, cells_per_word=None, seeds=32, solve_core=False):
        self.r = int(64 // cells_per_word) if cells_per_word else r
        self.cell_bits = 64 / cells_per_word if cells_per_word else r
        self.window, n = window, len(keys)
        self.third = max(4, math.ceil((n * expansion + 32) / 3))
        self.m = 3 * self.third
        for self.seed in range(seeds):
            if self.seed and self.seed % 8 == 0:  # small sets need more room than the asymptotic expansion
                self.third = math.ceil(self.third * 1.05)
                self.m = 3 * self.third
            pos = self._positions(keys)
            order, core = peel(pos, self.m, 2 * self.third if plus else self.m)
            if not len(core) or solve_core:
                self.z = np.zeros(self.m, U64)
                b = self._print(keys)
                if len(core) and not solve_dense(self.z, pos[:, core], b[core]):
                    continue
                break
        else:
            raise NoSolution("no seed peels; give more expansion")
        self.core = len(core)
        for rows, own in reversed(order):
            self.z[own] = U64(0)
            p = pos[:, rows]
            self.z[own] = b[rows] ^ self.z[p[0]] ^ self.z[p[1]] ^ self.z[p[2]]
        self.bits, self.ranks, self.per_word = self.m * self.cell_bits, None, cells_per_word
        if plus:
            last = np.zeros(self.third, bool)
            for _, own in order:
                last[own[own >= 2 * self.third] - 2 * self.third] = True
            self._drop_empty(last)
        elif cells_per_word:
            self._pack()

    def _print(self, keys):
        return salted_np(keys, 61, self.seed) & U64((1 << self.r) - 1)

    def _positions(self, keys):
        h = [salted_np(keys, 62 + i, self.seed) for i in range(3)]
        if self.window is None:
            return np.stack([at(x, self.third) + i * self.third for i, x in enumerate(h)])
        span = max(4, int(self.m * self.window) // 3)
        base = at(salted_np(keys, 66, self.seed), max(1, self.m - 3 * span))
        return np.stack([base + at(x, span) + i * span for i, x in enumerate(h)])

    def _drop_empty(self, filled: np.ndarray) -> None:
        """Keep the last third's filled cells only, found by the rank of their bit: a word of bits at a time, and counts
        of what lies before each run of eight words."""
        bits = np.zeros(-(-self.third // 512) * 512, bool)
        bits[: self.third] = filled
        self.mask = np.packbits(bits, bitorder="little").view("<u8")
        counts = np.bitwise_count(self.mask).astype(np.int64)
        self.ranks = np.cumsum(counts.reshape(-1, 8).sum(1)) - counts.reshape(-1, 8).sum(1)
        self.inside = (np.cumsum(counts.reshape(-1, 8), axis=1) - counts.reshape(-1, 8)).ravel()
        self.z = np.concatenate([self.z[: 2 * self.third], self.z[2 * self.third :][filled]])
        self.bits = len(self.z) * self.cell_bits + self.third * (1 + 16 / 512)

    def _pack(self) -> None:
        """Several cells to a 64-bit word."""
        i = self.per_word
        cells = np.concatenate([self.z, np.zeros(-len(self.z) % i, U64)]).reshape(-1, i)
        self.z = np.bitwise_or.reduce(cells << (np.arange(i, dtype=U64) * U64(self.r)), axis=1)
        self.bits = 64 * len(self.z)

    def _cell(self, p: np.ndarray, third: int) -> np.ndarray:
        if self.per_word:
            word, at = p // self.per_word, (p % self.per_word).astype(U64)
            return (self.z[word] >> (at * U64(self.r))) & U64((1 << self.r) - 1)
        if self.ranks is None or third < 2:
            return self.z[p]
        p = p - 2 * self.third
        word, at = self.mask[p >> 6], (p & 63).astype(U64)
        there = (word >> at) & U64(1) == 1
        rank = self.ranks[p >> 9] + self.inside[p >> 6] + np.bitwise_count(word & ((U64(1) << at) - U64(1)))
        return np.where(there, self.z[np.minimum(2 * self.third + rank, len(self.z) - 1)], U64(0))

    def contains(self, keys):
        p = self._positions(keys)
        return (self._cell(p[0], 0) ^ self._cell(p[1], 1) ^ self._cell(p[2], 2)) == self._print(keys)


def peel(pos: np.ndarray, m: int, early: int) -> tuple[list[tuple[np.ndarray, np.ndarray]], np.ndarray]:
    """Rounds of (keys, cells that only they use), and the keys left over. Cells from `early` on are taken only when no other
    offers itself, so that most of the empty ones lie there."""
    n = pos.shape[1]
    flat = pos.ravel()
    degree = np.bincount(flat, minlength=m)
    ids = np.zeros(m, np.int64)
    np.bitwise_xor.at(ids, flat, np.tile(np.arange(n), 3))
    alive, rounds = np.ones(n, bool), []
    ready, later = np.flatnonzero(degree == 1), np.zeros(0, np.int64)
    while len(ready) or len(later):
        later = np.concatenate([later, ready[ready >= early]])
        single = ready[ready < early]
        if not len(single):
            single, later = np.unique(later[degree[later] == 1]), later[:0]
            if not len(single):
                break
        keys, first = np.unique(ids[single], return_index=True)
        own = single[first]
        rounds.append((keys, own))
        alive[keys] = False
        touched = pos[:, keys].ravel()
        np.subtract.at(degree, touched, 1)
        np.bitwise_xor.at(ids, touched, np.tile(keys, 3))
        touched = np.unique(touched)
        ready = touched[degree[touched] == 1]
    return rounds, np.flatnonzero(alive)


def solve_dense(z: np.ndarray, pos: np.ndarray, b: np.ndarray) -> bool:
    """Gaussian elimination of what peeling leaves, on Python integers as bit rows; fills z at the core's cells.

    A right-hand side stands below its row's bits, so that a step is one XOR. The solution is kept as a bit row for each of
    its columns, so that a cell's value takes a parity a column, however many cells its row names.
    """
    cells, local = np.unique(pos.ravel(), return_inverse=True)
    local, width = local.reshape(pos.shape), int(b.max()).bit_length() if len(b) else 0
    rows = [0] * (width + len(cells) + 1)
    first, second, third = ([1 << c for c in (line + width).tolist()] for line in local)
    for x, y, q, rhs in zip(first, second, third, b.tolist(), strict=True):
        v = x ^ y ^ q ^ rhs
        while (top := v.bit_length()) > width:
            row = rows[top]
            if not row:
                rows[top] = v
                break
            v ^= row
        else:
            if v:
                return False
    columns, values, right = [0] * width, [0] * len(cells), (1 << width) - 1
    for c in range(len(cells)):
        if v := rows[width + c + 1]:
            row, value = v >> width, v & right
            for j, column in enumerate(columns):
                value ^= ((row & column).bit_count() & 1) << j
            values[c], bit = value, 1 << c
            for j in range(width):
                if value >> j & 1:
                    columns[j] |= bit
    solved = np.flatnonzero([bool(v) for v in rows[width + 1 :]])
    z[cells[solved]] = np.array(values, U64)[solved]
    return True


def dense_rank_full(n: int, seed: int) -> bool:
    """Whether a random square bit matrix is regular."""
    rng = np.random.default_rng(seed)
    rows: dict[int, int] = {}
    for _ in range(n):
        v = int.from_bytes(rng.bytes(-(-n // 8)), "little") & ((1 << n) - 1)
        while v and (top := v.bit_length()) in rows:
            v ^= rows[top]
        if not v:
            return False
        rows[top] = v
    return True


@dataclass
class SortedBand:
    """The earlier batch solver of the same band system: sort by start, explicit pivots, one conditional step per pair.

    steps counts pairs looked at, additions those that needed a row addition; redundant rows fail, as they did there.
    rows holds each row in the order of elimination, as its coefficient bits from `base` on, and its right-hand side.
    """

    ok: bool
    steps: int
    additions: int
    pivots: list[int]
    rows: list[tuple[int, int, int]]

    @classmethod
    def solve(cls, start: np.ndarray, coeff: np.ndarray, rhs: np.ndarray) -> SortedBand:
        order = np.argsort(start, kind="stable")
        s = start[order].tolist()
        low, high = coeff[0][order].tolist(), coeff[1][order].tolist() if len(coeff) > 1 else [0] * len(s)
        rows = [(x | (y << 64)) << (at % 64) for x, y, at in zip(low, high, s, strict=True)]
        base = [x - x % 64 for x in s]
        b = np.asarray(rhs)[order].tolist()
        steps = additions = 0
        pivots: list[int] = []
        n = len(s)
        for k in range(n):
            if not rows[k]:
                return cls(False, steps, additions, pivots, [])
            low = (rows[k] & -rows[k]).bit_length() - 1
            pivot = base[k] + low
            pivots.append(pivot)
            j = k + 1
            while j < n and s[j] <= pivot:
                steps += 1
                shift = pivot - base[j]
                if (rows[j] >> shift) & 1:
                    additions += 1
                    d = base[k] - base[j]
                    rows[j] ^= rows[k] >> -d if d < 0 else rows[k] << d
                    b[j] ^= b[k]
                j += 1
        return cls(True, steps, additions, pivots, list(zip(base, rows, b, strict=True)))

    def bank(self, rows: int) -> Bank:
        """The rows as a bank's, each from its pivot on."""
        shifted = [row >> (pivot - base) for pivot, (base, row, _) in zip(self.pivots, self.rows, strict=True)]
        bank = Bank(rows, 2 if any(row >> 64 for row in shifted) else 1)
        bank.used[self.pivots] = True
        for lane in range(bank.lanes):
            bank.c[lane, self.pivots] = np.array([(row >> (64 * lane)) & 0xFFFFFFFFFFFFFFFF for row in shifted], U64)
        bank.b[self.pivots] = np.array([value for _, _, value in self.rows], U64)
        return bank

    def words(self, m: int, r: int) -> np.ndarray:
        """Solution words [blocks, r], empty rows zero; m is a multiple of 64."""
        return back_substitute(self.bank(m), r, m)[0]

    def solution(self, m: int, r: int) -> np.ndarray:
        """The r-bit value of each of m rows."""
        bits = np.unpackbits(self.words(-(-m // 64) * 64, r).astype("<u8").view(np.uint8).reshape(-1, r, 8), axis=2, bitorder="little")
        return (bits.transpose(0, 2, 1).astype(U64) << np.arange(r, dtype=U64)).sum(2, dtype=U64).ravel()[:m]


class SortedBandFilter:
    """A band filter by the earlier solver: a tighter failure rule, and a whole new attempt when a row is redundant."""

    def __init__(self, keys: np.ndarray, r: int = 7, w: int = 64, eps: float = 0.15, seeds: int = 32):
        self.r, self.w = r, w
        self.m = rows_for(len(keys), eps, w)
        for self.seed in range(seeds):
            got = SortedBand.solve(self._start(keys), coefficients_np(keys, self.seed, w), fingerprint_np(keys, self.seed, r))
            if got.ok:
                break
        else:
            raise NoSolution("the sorted solver met dependent rows under every seed; give more space")
        self.words = got.words(self.m, r)
        self.bits = self.m * r

    def _start(self, keys: np.ndarray) -> np.ndarray:
        return clamp_start_np(salted_np(keys, START, self.seed), self.m - self.w + 1, self.w // 4)

    def contains(self, keys: np.ndarray) -> np.ndarray:
        got = lookup(self.words[None], np.zeros(len(keys), np.int64), self._start(keys), coefficients_np(keys, self.seed, self.w))
        return got == fingerprint_np(keys, self.seed, self.r)


def build(family: str, keys: np.ndarray, **params):
    """A filter of a named family; names as in the survey's list of baselines."""
    made = {
        "bloom": lambda: Bloom(keys, **params),
        "blocked_bloom": lambda: BlockedBloom(keys, **params),
        "two_block_bloom": lambda: BlockedBloom(keys, **({"variant": "any_k"} | params), blocks=2),
        "cuckoo": lambda: Cuckoo(keys, **params),
        "cuckoo_sorted": lambda: Cuckoo(keys, **({"cell_bits": 16} | params), sorted_cells=True),
        "cuckoo_blocked": lambda: Cuckoo(keys, **({"cell_bits": 8, "slots": 3, "load": 0.9} | params), block=(64, 46)),
        "quotient": lambda: Quotient(keys, **params),
        "xor": lambda: Xor(keys, **params),
        "xor_word": lambda: Xor(keys, **({"cells_per_word": 6} | params)),
        "xor_plus": lambda: Xor(keys, **params, plus=True),
        "xor_coupled": lambda: Xor(keys, **({"expansion": 1.18, "window": 0.05 if len(keys) >= 20_000 else 0.3, "seeds": 96} | params)),
        "sparse_gauss": lambda: Xor(keys, **({"expansion": 1.10} | params), solve_core=True),
        "band_sorted": lambda: SortedBandFilter(keys, **params),
    }
    if family not in made:
        raise ValueError(f"unknown family {family}; known: {sorted(made)}")
    return made[family]()


NAMES = ("bloom", "blocked_bloom", "two_block_bloom", "cuckoo", "cuckoo_sorted", "cuckoo_blocked", "quotient", "xor", "xor_word", "xor_plus", "xor_coupled", "sparse_gauss", "band_sorted")
SMALL = {"sparse_gauss": 4096, "band_sorted": 8192}  # keys a segment, where building is superlinear or slow
