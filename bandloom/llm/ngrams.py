"""Character n-gram hashing over whole texts, as numpy arrays of code points."""

from __future__ import annotations

import numpy as np

MIX = np.uint64(0x9E3779B97F4A7C15)
STEP = np.uint64(0xD6E8FEB86659FD93)


def code_points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "replace"), "<u4")


def hashed(text: str, orders: tuple[int, ...]) -> np.ndarray:
    """64-bit hashes of all character n-grams of the given orders, repeats included, order mixed in."""
    cps = code_points(text).astype(np.uint64)
    out, h = [], np.zeros(len(cps), np.uint64)
    for n in range(1, max(orders) + 1):
        if len(cps) < n:
            break
        h = h[: len(cps) - n + 1] * STEP + cps[n - 1 :] + np.uint64(n)
        if n in orders:
            out.append(h * MIX)
    return np.concatenate(out) if out else np.zeros(0, np.uint64)


def pieces(text: str, size: int = 1 << 19, overlap: int = 8):
    """The whole text in slices of bounded memory that share overlap characters, so that no n-gram is lost."""
    if len(text) <= size:
        yield text
        return
    for at in range(0, len(text) - overlap, size - overlap):
        yield text[at : at + size]
