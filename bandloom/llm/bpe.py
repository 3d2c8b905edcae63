"""BPE encoding and decoding with a segment tree over adjacent pair ranks.

Each pre-token is a row of symbols. The leaves of its tree hold, for each adjacent pair, rank * width + position (or
infinity where the pair has no merge), so the root is always the leftmost lowest-rank merge. A merge updates at most
three leaves (the pair itself and its two neighbours) and their paths to the root, until the root is infinite.
Distinct short pre-tokens of a batch share one array of trees and advance together; long ones get a tree of their own.

Input: any DataFrame with the id and text columns. Null text counts as empty. Empty text: no ids, empty decoding.
Repeated rows give repeated rows; other columns are not read. The vocabulary file's path is a parameter, and its bytes
(a few MB, fixed) travel to the executors in a broadcast variable.
"""

from __future__ import annotations

import hashlib
import json
from array import array
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandloom.runtime import ship, spread

# The pre-token pattern that the vocabulary's byte-level pre-tokenizer defines.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
SHORT = 64
CACHE = 400_000
KEEP = 256  # longer pre-tokens are not kept
NONE = np.iinfo(np.int64).max
SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def byte_letters() -> dict[str, int]:
    """The byte-level alphabet: printable bytes stand for themselves, the rest follow from code point 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(others)}


@dataclass
class Codec:
    """Tables of one vocabulary, and the cache of pre-tokens already encoded by this worker."""

    pieces: list[bytes]
    leaf: np.ndarray
    pair_keys: np.ndarray
    pair_rank: np.ndarray
    pair_into: np.ndarray
    specials: dict[str, int]
    split: object
    merges: dict = field(default_factory=dict)
    cache: dict = field(default_factory=dict)

    @classmethod
    def from_json(cls, text: str) -> Codec:
        spec = json.loads(text)
        letters, vocab = byte_letters(), spec["model"]["vocab"]
        size = max([*vocab.values(), *(t["id"] for t in spec["added_tokens"])]) + 1
        pieces = [b""] * size
        for token, i in vocab.items():
            pieces[i] = bytes(letters[c] for c in token)
        specials = {t["content"]: t["id"] for t in spec["added_tokens"]}
        for token, i in specials.items():
            pieces[i] = token.encode()
        leaf = np.zeros(256, np.int64)
        for c, b in letters.items():
            leaf[b] = vocab[c]
        pairs = [m.split(" ") if isinstance(m, str) else m for m in spec["model"]["merges"]]
        left = np.array([vocab[a] for a, _ in pairs], np.int64)
        right = np.array([vocab[b] for _, b in pairs], np.int64)
        into = np.array([vocab[a + b] for a, b in pairs], np.int64)
        keys = (left << 32) | right
        order = np.argsort(keys, kind="stable")
        found = regex.compile("(" + "|".join(map(regex.escape, sorted(specials, key=len, reverse=True))) + ")") if specials else None
        merges = {int(k): (r, int(i)) for r, (k, i) in enumerate(zip(keys, into, strict=True))}
        return cls(pieces, leaf, keys[order], order.astype(np.int64), into[order], specials, found, merges)

    def ranks(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank and merged id of each pair; rank -1 where there is no merge."""
        key = (left << 32) | right
        at = np.minimum(np.searchsorted(self.pair_keys, key), len(self.pair_keys) - 1)
        hit = (self.pair_keys[at] == key) & (left >= 0) & (right >= 0)
        return np.where(hit, self.pair_rank[at], -1), self.pair_into[at]

    def encode_long(self, raw: bytes) -> list[int]:
        """One tree for one piece."""
        ids = self.leaf[np.frombuffer(raw, np.uint8)].tolist()
        n, merges = len(ids), self.merges
        width = 1 << max(1, (n - 1).bit_length())
        far = width << 40
        tree = array("q", [far]) * (2 * width)
        for i in range(n - 1):
            if m := merges.get((ids[i] << 32) | ids[i + 1]):
                tree[width + i] = m[0] * width + i
        for k in range(width - 1, 0, -1):
            tree[k] = min(tree[2 * k], tree[2 * k + 1])
        after, before = array("q", range(1, n + 1)), array("q", range(-1, n - 1))

        def put(i: int, value: int) -> None:
            k = width + i
            tree[k] = value
            k >>= 1
            while k:
                low = min(tree[2 * k], tree[2 * k + 1])
                if tree[k] == low:
                    break
                tree[k] = low
                k >>= 1

        while (root := tree[1]) < far:
            i = root % width
            j = after[i]
            ids[i] = merges[(ids[i] << 32) | ids[j]][1]
            ids[j] = -1
            k = after[i] = after[j]
            if k < n:
                before[k] = i
            put(j, far)
            m = merges.get((ids[i] << 32) | ids[k]) if k < n else None
            put(i, m[0] * width + i if m else far)
            if (h := before[i]) >= 0:
                m = merges.get((ids[h] << 32) | ids[i])
                put(h, m[0] * width + h if m else far)
        return [i for i in ids if i >= 0]

    def encode_rows(self, raws: list[bytes], width: int) -> list[bytes]:
        """Pieces of up to width bytes (a power of two): all their trees move one merge a round."""
        n = len(raws)
        lens = np.array([len(r) for r in raws])
        ids = np.full((n, width + 1), -1, np.int64)
        mask = np.arange(width + 1)[None, :] < lens[:, None]
        ids[mask] = self.leaf[np.frombuffer(b"".join(raws), np.uint8)]
        after = np.broadcast_to(np.arange(1, width + 2), (n, width + 1)).copy()
        before = np.broadcast_to(np.arange(-1, width), (n, width + 1)).copy()
        tree = np.full((n, 2 * width), NONE, np.int64)
        rank, _ = self.ranks(ids[:, :-1], ids[:, 1:])
        tree[:, width:] = np.where(rank >= 0, rank * width + np.arange(width), NONE)
        k = width
        while k > 1:
            k >>= 1
            tree[:, k : 2 * k] = np.minimum(tree[:, 2 * k : 4 * k : 2], tree[:, 2 * k + 1 : 4 * k : 2])
        rows = np.flatnonzero(tree[:, 1] != NONE)

        def put(r: np.ndarray, at: np.ndarray, value: np.ndarray) -> None:
            node = at + width
            tree[r, node] = value
            while node[0] > 1:  # all leaves are on one level
                node >>= 1
                tree[r, node] = np.minimum(tree[r, 2 * node], tree[r, 2 * node + 1])

        while len(rows):
            i = tree[rows, 1] % width
            j = after[rows, i]
            _, into = self.ranks(ids[rows, i], ids[rows, j])
            ids[rows, i] = into
            ids[rows, j] = -1
            k = after[rows, j]
            after[rows, i] = k
            before[rows, k] = i
            put(rows, j, np.full(len(rows), NONE))
            rank, _ = self.ranks(into, ids[rows, k])
            put(rows, i, np.where(rank >= 0, rank * width + i, NONE))
            h = before[rows, i]
            if (some := h >= 0).any():
                r, h = rows[some], h[some]
                rank, _ = self.ranks(ids[r, h], into[some])
                put(r, h, np.where(rank >= 0, rank * width + h, NONE))
            rows = rows[tree[rows, 1] != NONE]
        kept = ids[:, :width] >= 0
        flat = ids[:, :width][kept].astype("<u4").tobytes()
        ends = 4 * np.cumsum(kept.sum(1))
        return [flat[a:b] for a, b in zip([0, *ends[:-1].tolist()], ends.tolist(), strict=True)]

    def learn(self, words: set[str]) -> None:
        """Encode new pre-tokens into the cache."""
        by_width: dict[int, list[tuple[str, bytes]]] = {}
        for w in words:
            raw = w.encode()
            if len(raw) == 1:
                self.cache[w] = int(self.leaf[raw[0]]).to_bytes(4, "little")
            elif len(raw) > SHORT:
                self.cache[w] = np.array(self.encode_long(raw), "<u4").tobytes()
            else:
                by_width.setdefault(max(4, 1 << (len(raw) - 1).bit_length()), []).append((w, raw))
        for width, found in by_width.items():
            for at in range(0, len(found), 8192):
                block = found[at : at + 8192]
                self.cache.update(zip((w for w, _ in block), self.encode_rows([r for _, r in block], width), strict=True))

    def encode_all(self, texts: list[str], pattern=regex.compile(PATTERN)) -> list[bytes]:
        """The ids of each text as little-endian unsigned 32-bit integers; new pre-tokens are encoded together."""
        cut = [self.split.split(t) if self.split and any(s in t for s in self.specials) else [t] for t in texts]
        words = [[[p] if p in self.specials else pattern.findall(p) for p in parts] for parts in cut]
        if len(self.cache) > CACHE:
            self.cache.clear()
        new: set[str] = set()
        for parts in words:
            new.update(*parts)
        new.difference_update(self.cache, self.specials)
        self.learn(new)
        self.cache.update((s, i.to_bytes(4, "little")) for s, i in self.specials.items())
        known = self.cache.__getitem__
        out = [b"".join([b"".join(map(known, p)) for p in parts]) for parts in words]
        for w in [w for w in new if len(w) > KEEP]:
            del self.cache[w]
        return out

    def decode(self, ids: bytes) -> bytes:
        pieces = self.pieces
        return b"".join([pieces[i] for i in np.frombuffer(ids, "<u4").tolist()])


_codecs: dict[int, Codec] = {}


def codec_of(shared) -> Codec:
    """The worker's codec for a broadcast vocabulary; kept between tasks."""
    text = shared.value
    if (key := hash(text)) not in _codecs:
        _codecs.clear()
        _codecs[key] = Codec.from_json(text)
    return _codecs[key]


def batches(texts: list[str], chars: int = 2_000_000):
    """Runs of texts of about so many characters, so that a batch of long texts stays small."""
    run, size = [], 0
    for t in texts:
        run.append(t)
        size += len(t)
        if size >= chars:
            yield run
            run, size = [], 0
    if run:
        yield run


def bpe_encode(docs: DataFrame, vocabulary: str, digests: bool = True) -> DataFrame:
    """doc_id with ids (array<int>) and decoded text, or, for digests, their counts and SHA-256 values.

    vocabulary: path of a byte-level BPE file of the tokenizers library, read by the driver.
    """
    spark = docs.sparkSession
    ship(spark)
    with open(vocabulary, encoding="utf-8") as f:
        shared = spark.sparkContext.broadcast(f.read())

    def run(it):
        codec = codec_of(shared)
        for batch in it:
            ids = batch.column(0).to_pylist()
            texts = [t or "" for t in batch.column(1).to_pylist()]
            out = []
            for block in batches(texts):
                for t, coded in zip(block, codec.encode_all(block), strict=True):
                    back = codec.decode(coded)
                    if digests:
                        # a token may cut a code point; the whole sequence never does
                        out.append((len(coded) // 4, hashlib.sha256(coded).hexdigest(), hashlib.sha256(back).hexdigest()))
                    else:
                        out.append((np.frombuffer(coded, "<u4").astype(np.int32).tolist(), back.decode("utf-8", "replace")))
            cols = list(zip(*out, strict=True)) if out else [[]] * (3 if digests else 2)
            if digests:
                arrays = [pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.string()), pa.array(cols[2], pa.string())]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            else:
                arrays = [pa.array(cols[0], pa.list_(pa.int32())), pa.array(cols[1], pa.string())]
                names = ["doc_id", "ids", "decoded"]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), *arrays], names)

    thin = spread(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"))
    return thin.mapInArrow(run, SCHEMA if digests else "doc_id long, ids array<int>, decoded string")
