"""Benchmark decontamination by spaced-seed hashing.

Fixed masks ignore some token positions of a window; a document window and a benchmark window that agree on a mask's
selected positions have equal hashes. Test hashes are joined with training hashes, and each hit is verified around its
diagonal: the longest window of aligned tokens with an identity of MIN_IDENTITY or more must hold at least MIN_SPAN
tokens (or the whole of a shorter item), wherever its substitutions lie. Items of fewer than SHORT_ITEM tokens have one
lighter mask more. What no mask hits is not verified.

The benchmark side is built in blocks of at most about BLOCK_TOKENS tokens, whose size bounds what is broadcast; a larger
benchmark means more passes, each over all documents, and of several blocks one at a time is on the driver and in flight.
Nothing of the documents is shuffled. A seed that repeats in a document and in the benchmark gives its pairs in chunks of
PAIRS, of which the distinct diagonals are verified, and items found whole are left out of later chunks.

Defined results: tokens are runs of word characters of the lower-cased text; null and empty texts match nothing; items
of fewer than LEAST_TOKENS tokens are no evidence and match nothing; of an item's windows that with the most equal tokens
counts, then the longest, then the first; repeated documents give repeated rows, repeated items (equal id and text)
one; null item ids are not read; an empty benchmark leaves every document clean; documents with null ids are judged like
others; other columns are not read.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandloom.runtime import delete, scratch, ship, spread, written

# The seeds; 1 marks a position that is compared.
MASKS = ("111111", "1110111", "11011011", "1010110101")
SHORT_MASK, SHORT_ITEM = "1111", 14
MIN_SPAN, MIN_IDENTITY, LEAST_TOKENS = 13, 0.8, 8
BLOCK_TOKENS = 2_000_000
BATCH_CHARS = 1_000_000
PAIRS = 1_000_000
GAP = max(map(len, MASKS))  # unknown tokens between documents that are hashed together
WORD = regex.compile(r"\w+")
SCHEMA = "doc_id long, item_id long, n_tokens int, n_equal int, doc_token int, item_token int"


def tokens(text: str | None) -> list[str]:
    return WORD.findall((text or "").lower())


def offsets(mask: str) -> list[int]:
    return [i for i, c in enumerate(mask) if c == "1"]


def mix(h: np.ndarray, ids: np.ndarray) -> np.ndarray:
    h = (h ^ ids) * np.uint64(0x9E3779B97F4A7C15)
    return h ^ (h >> np.uint64(32))


def window_hashes(ids: np.ndarray, mask: str) -> tuple[np.ndarray, np.ndarray]:
    """(start, hash) of every whole window of the mask whose selected tokens are all known (not 0)."""
    n, places = len(ids) - len(mask) + 1, offsets(mask)
    if n <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    known, ok = ids > 0, np.ones(n, bool)
    for o in places:
        ok &= known[o : o + n]
    at = np.flatnonzero(ok)
    h = np.full(len(at), len(mask), np.uint64)
    for o in places:
        h = mix(h, ids[at + o])
    return at, h


@dataclass
class Seed:
    """One mask over the items that it is for: sorted hashes, and the item and the place in it of each."""

    mask: str
    hashes: np.ndarray
    items: np.ndarray
    places: np.ndarray

    @classmethod
    def build(cls, mask: str, items: list[tuple[int, np.ndarray]]) -> Seed:
        found = [(k, *window_hashes(ids, mask)) for k, ids in items]
        h = np.concatenate([h for _, _, h in found])
        order = np.argsort(h, kind="stable")
        number = np.concatenate([np.full(len(at), k, np.int64) for k, at, _ in found])
        return cls(mask, h[order], number[order], np.concatenate([at for _, at, _ in found])[order])


@dataclass
class Seeds:
    """One block of the benchmark: token numbers, the items' tokens as numbers, and the sorted seed hashes."""

    vocabulary: dict[str, int]
    item_ids: list[int]
    coded: list[np.ndarray]
    seeds: list[Seed]

    @classmethod
    def build(cls, items: list[tuple[int, list[str]]]) -> Seeds:
        vocabulary: dict[str, int] = {}
        coded = [np.array([vocabulary.setdefault(t, len(vocabulary) + 1) for t in ts], np.uint64) for _, ts in items]
        whole = list(enumerate(coded))
        seeds = [Seed.build(mask, whole) for mask in MASKS]
        if short := [(k, ids) for k, ids in whole if len(ids) < SHORT_ITEM]:
            seeds.append(Seed.build(SHORT_MASK, short))
        return cls(vocabulary, [i for i, _ in items], coded, seeds)

    def matches(self, texts: list[str | None]) -> list[list[tuple[int, int, int, int, int]]]:
        """For each text, (item_id, tokens, equal tokens, first token in the document, in the item) of each item's best window."""
        number, flat, first = self.vocabulary.get, [], [0]
        for t in texts:
            flat += [number(w, 0) for w in tokens(t)]
            flat += [0] * GAP
            first.append(len(flat))
        ids, first = np.array(flat, np.uint64), np.array(first)
        hits = []
        for s, seed in enumerate(self.seeds):
            at, h = window_hashes(ids, seed.mask)
            lo = np.searchsorted(seed.hashes, h, "left")
            some = np.flatnonzero((lo < len(seed.hashes)) & (seed.hashes[np.minimum(lo, len(seed.hashes) - 1)] == h)) if len(seed.hashes) else at[:0]
            n = np.searchsorted(seed.hashes, h[some], "right") - lo[some]
            hits.append(np.stack([np.full(len(some), s), at[some], lo[some], n]))
        every = np.concatenate(hits, 1)
        doc = np.searchsorted(first, every[1], "right") - 1
        out: list[list] = [[] for _ in texts]
        for d in np.unique(doc).tolist():
            own = every[:, doc == d]
            own[1] -= first[d]
            out[d] = self.verified(ids[first[d] : first[d + 1] - GAP], own)
        return out

    def diagonals(self, hits: np.ndarray):
        """Chunks of distinct (item << 32) + shift + 2^31, shift being the document's place less the item's."""
        held, size = [], 0
        cuts = np.flatnonzero(np.diff(hits[0], prepend=-1) | np.diff(np.cumsum(hits[3]) // PAIRS, prepend=0))
        for part in np.split(hits, cuts[cuts > 0], axis=1):
            seed, n = self.seeds[part[0, 0]], part[3]
            row = np.repeat(np.arange(len(n)), n)
            k = part[2][row] + np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n)
            held.append(np.unique((seed.items[k] << 32) + part[1][row] - seed.places[k] + (1 << 31)))
            size += len(held[-1])
            if size > PAIRS:
                yield np.unique(np.concatenate(held))
                held, size = [], 0
        if held:
            yield np.unique(np.concatenate(held))

    def verified(self, ids: np.ndarray, hits: np.ndarray) -> list[tuple[int, int, int, int, int]]:
        best: dict[int, tuple] = {}
        for codes in self.diagonals(hits):
            items, shifts = codes >> 32, (codes & 0xFFFFFFFF) - (1 << 31)
            for item in np.unique(items).tolist():
                own = self.coded[item]
                need = min(MIN_SPAN, len(own))
                if item in best and best[item][0] == len(own):
                    continue  # found whole: nothing is better
                mine, step = shifts[items == item], max(1, PAIRS // len(own))
                for at in range(0, len(mine), step):
                    some = mine[at : at + step]
                    place = some[:, None] + np.arange(len(own))
                    inside = (place >= 0) & (place < len(ids))
                    equal = inside & (ids[np.clip(place, 0, len(ids) - 1)] == own)
                    for d in np.flatnonzero(equal.sum(1) >= MIN_IDENTITY * need).tolist():
                        a, b = np.flatnonzero(inside[d])[[0, -1]].tolist()
                        start, end, same = longest_window(equal[d, a : b + 1])
                        if end - start >= need:
                            found = (same, end - start, -int(some[d]), a + start)
                            best[item] = max(best.get(item, found), found)
                            if same == len(own):
                                break
        return [(self.item_ids[i], size, same, at - back, at) for i, (same, size, back, at) in sorted(best.items())]


def longest_window(equal: np.ndarray) -> tuple[int, int, int]:
    """[start, end) of the longest window with an identity of MIN_IDENTITY or more, and its equal count; most equal first on ties."""
    percent = round(100 * MIN_IDENTITY)
    count = np.concatenate([[0], np.cumsum(equal)])
    score = 100 * count - percent * np.arange(len(count))  # a window is good if its ends' difference is not negative
    starts = np.searchsorted(-np.minimum.accumulate(score), -score)  # for every end the first start that is good
    sizes, same = np.arange(len(count)) - starts, count - count[starts]
    end = int(np.lexsort((same, sizes))[-1])
    return int(starts[end]), end, int(same[end])


def seed_blocks(benchmark: DataFrame, block_tokens: int = BLOCK_TOKENS):
    """The benchmark's items in blocks of bounded size; rows stream through the driver one block at a time."""
    items, size = [], 0
    rows = benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("long"), "text").distinct().orderBy("item_id", "text")
    for item_id, text in rows.toLocalIterator():
        ts = tokens(text)
        if len(ts) < LEAST_TOKENS:
            continue
        items.append((item_id, ts))
        size += len(ts)
        if size >= block_tokens:
            yield Seeds.build(items)
            items, size = [], 0
    if items:
        yield Seeds.build(items)


def texts_of(batch: pa.RecordBatch, column: int):
    """(first row, texts) of runs of rows of about BATCH_CHARS characters."""
    run, size, at = [], 0, 0
    for i, t in enumerate(batch.column(column)):
        run.append(t.as_py())
        size += len(run[-1] or "")
        if size >= BATCH_CHARS:
            yield at, run
            run, size, at = [], 0, i + 1
    if run:
        yield at, run


def each_block(spark, benchmark: DataFrame):
    """(the block's broadcast, whether more follow); a block is dropped before the next is built."""
    blocks = seed_blocks(benchmark)
    seeds = next(blocks, None)
    while seeds is not None:
        shared = spark.sparkContext.broadcast(seeds)
        seeds = next(blocks, None)
        yield shared, seeds is not None
        if seeds is not None:
            shared.unpersist()


def contamination(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """One row per contaminated document and item: SCHEMA. Clean documents have no row."""
    spark = docs.sparkSession
    ship(spark)
    thin = spread(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"))
    path = None
    kinds = [pa.int64(), pa.int64(), *[pa.int32()] * 4]
    names = [f.split()[0] for f in SCHEMA.split(", ")]
    found = spark.createDataFrame([], SCHEMA)
    for shared, more in each_block(spark, benchmark):

        def run(it, shared=shared):
            for batch in it:
                ids = batch.column(0).to_pylist()
                for at, texts in texts_of(batch, 1):
                    rows = [(ids[at + k], *m) for k, ms in enumerate(shared.value.matches(texts)) for m in ms]
                    cols = list(zip(*rows, strict=True)) or [[]] * len(names)
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names)

        found = thin.mapInArrow(run, SCHEMA)
        if more or path:
            path = path or scratch(spark, "contamination")
            found.write.mode("append").parquet(path)
    return spark.read.schema(SCHEMA).parquet(path) if path else found


def without_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The documents in which no benchmark item is found, with their columns; no shuffle."""
    spark = docs.sparkSession
    ship(spark)
    path, docs = None, spread(docs)
    for shared, more in each_block(spark, benchmark):

        def run(it, shared=shared):
            for batch in it:
                clean = [not m for _, texts in texts_of(batch, batch.schema.get_field_index("text")) for m in shared.value.matches(texts)]
                yield batch.filter(pa.array(clean, pa.bool_()))

        docs = docs.mapInArrow(run, docs.schema)
        if more:
            before = path
            docs, path = written(docs, "clean")
            if before:
                delete(spark, before)
    return docs
