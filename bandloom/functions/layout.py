"""Three layouts of a solution, and queries on each. Interleaved column-major words are what the filters store."""

from __future__ import annotations

import numpy as np

U64 = np.uint64
LAYOUTS = ("icm", "row", "column")


def rows_of(words: np.ndarray) -> np.ndarray:
    """[rows] of r-bit integers from interleaved words [blocks, r]."""
    blocks, r = words.shape
    bits = np.unpackbits(np.ascontiguousarray(words).view(np.uint8).reshape(blocks, r, 8), axis=2, bitorder="little")
    return (bits.astype(U64) << np.arange(r, dtype=U64)[None, :, None]).sum(1, dtype=U64).ravel()


def pack(rows: np.ndarray, r: int, layout: str) -> np.ndarray:
    """Words of the layout: icm [blocks, r]; row: r-bit values end to end; column: r bit columns, one after another."""
    bits = ((rows[:, None] >> np.arange(r, dtype=U64)) & U64(1)).astype(np.uint8)
    if layout == "icm":
        blocks = bits.reshape(-1, 64, r).transpose(0, 2, 1)
        return np.ascontiguousarray(np.packbits(blocks, axis=2, bitorder="little")).view("<u8")[..., 0]
    flat = bits.ravel() if layout == "row" else bits.T.ravel()
    flat = np.concatenate([flat, np.zeros(-len(flat) % 64, np.uint8)])
    return np.packbits(flat, bitorder="little").view("<u8")


def unpack(words: np.ndarray, m: int, r: int, layout: str) -> np.ndarray:
    if layout == "icm":
        return rows_of(words)[:m]
    flat = np.unpackbits(words.view(np.uint8), bitorder="little")[: m * r]
    bits = flat.reshape(m, r) if layout == "row" else flat.reshape(r, m).T
    return (bits.astype(U64) << np.arange(r, dtype=U64)).sum(1, dtype=U64)


def query(words: np.ndarray, m: int, r: int, layout: str, start: int, coeff: int, w: int) -> int:
    """The result of one query, reading only the bits that the layout makes it read."""
    if layout == "row":  # XOR of the selected rows
        flat = np.unpackbits(words.view(np.uint8), bitorder="little")
        out = 0
        for t in range(w):
            if (coeff >> t) & 1:
                at = (start + t) * r
                out ^= sum(int(b) << j for j, b in enumerate(flat[at : at + r]))
        return out
    out = 0
    for j in range(r):
        if layout == "column":
            lo = j * m + start
            window = sum(int((int(words[k // 64]) >> (k % 64)) & 1) << t for t, k in enumerate(range(lo, min(lo + w, (j + 1) * m))))
        else:
            block, o = divmod(start, 64)
            window = 0
            for k in range(block, min(len(words), (start + w - 1) // 64 + 1)):
                window |= int(words[k, j]) << (64 * (k - block))
            window >>= o
        out |= ((window & coeff).bit_count() & 1) << j
    return out


def straddle_share(w: int, m: int) -> float:
    """Share of queries that see both widths of a two-width filter."""
    return w / m
