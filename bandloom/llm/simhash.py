"""SimHash near-dedup by meet-in-the-middle ball hashing.

Fingerprints: majority bits of the XXH64 values of all word shingles, repeats included. Two fingerprints link at
`radius` (4) or fewer differing bits; two within 4 always share a variant that lies within 2 of both, and two that share
one are within 4 of each other. So every distinct fingerprint emits all 2081 variants within 2, equal variants meet, and
the verified collisions are the links. The radius is even: for an odd one, fingerprints that share a variant need not link,
and then linking them all to the least one would lose links.

The shuffle on variants is by their leading bits, and lazy: a fingerprint travels once to each cell of leading bits in
which any of its variants lies (1 + b + b(b-1)/2 of 2^b cells), and the cell's task expands the variants that fall into
it. This moves the same variants to the same place for a fraction of the bytes. Exact copies collapse to one
fingerprint before, so large groups of copies cost nothing; a variant shared by g fingerprints links them to the least
one, never all pairs; and a cell returns a spanning forest of its links.

Components come from alternating star contraction on (fingerprint, fingerprint) links, each round written to the shared
folder. Defined results: null and empty texts and texts without words have fingerprint zero and link like any other;
texts of fewer words than a shingle hash the whole word sequence; null ids stay rows of the result and never name a
component unless all ids of it are null; repeated rows give repeated rows; other columns are not read.
"""

from __future__ import annotations

import itertools
import math
from functools import cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandloom.runtime import delete, ship, spread, written

SHINGLE = 4
CELL_VARIANTS = 4_000_000
ROW = "_simhash_row"


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    """Majority bits of the shingles' XXH64 values (seed 42)."""
    words = (text or "").encode().lower().split()  # bytes: A-Z only, and white space is 20, 09-0D
    if not words:
        return 0
    if len(words) <= shingle:
        return xxhash.xxh64_intdigest(b" ".join(words), 42)
    line = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words])
    starts = np.concatenate([[0], ends[: len(words) - shingle]]).tolist()
    stops = (ends[shingle - 1 :] - 1).tolist()
    digest = xxhash.xxh64_intdigest
    h = np.array([digest(line[a:b], 42) for a, b in zip(starts, stops, strict=True)], np.uint64)
    votes = np.zeros(64, np.int64)
    for at in range(0, len(h), 1 << 16):
        votes += np.unpackbits(h[at : at + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(votes * 2 > len(h), bitorder="little").view("<u8")[0])


def prints_of(rows: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """rows with their last column, a text, replaced by fp (the fingerprint's 64 bits as a long)."""
    ship(rows.sparkSession)
    rows, kept = spread(rows), rows.columns[:-1]

    def run(it):
        for batch in it:
            fps = np.array([fingerprint(t.as_py(), shingle) for t in batch.column(len(kept))], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(fps)], [*kept, "fp"])

    return rows.mapInArrow(run, ", ".join([*(f"{c} {t}" for c, t in rows.dtypes[:-1]), "fp bigint"]))


def fingerprints(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """doc_id, fp for every row."""
    return prints_of(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), shingle)


@cache
def flips(bits: int, most: int) -> np.ndarray:
    """Masks of up to `most` set bits among the low `bits`."""
    return np.array([sum(1 << i for i in c) for k in range(most + 1) for c in itertools.combinations(range(bits), k)], np.uint64)


def cell_links(fps: np.ndarray, cell: int, lead: int, radius: int, most: int = CELL_VARIANTS) -> tuple[np.ndarray, np.ndarray]:
    """Spanning forest of the links whose shared variant lies in this cell; fps are distinct and sorted.

    A cell of more than `most` variants is halved by its next bit, and its halves' forests are merged, so beyond
    the fingerprints themselves (8 bytes each) memory stays bounded.
    """
    low, reach = 64 - lead, radius // 2
    away = np.bitwise_count((fps >> np.uint64(low)) ^ np.uint64(cell))
    masks = [flips(low, reach - spent) for spent in range(reach + 1)]
    if sum(int((away == spent).sum()) * len(m) for spent, m in enumerate(masks)) > most and low > 1:
        own = fps[away <= reach]
        halves = [cell_links(own, 2 * cell + bit, lead + 1, radius, most) for bit in (0, 1)]
        node, root = (np.searchsorted(own, np.concatenate(ends)) for ends in zip(*halves, strict=True))
        return forest(own, node, root)
    variants, owner = [], []
    suffix = fps & np.uint64((1 << low) - 1)
    for spent in range(reach + 1):
        own = np.flatnonzero(away == spent)
        variants.append((suffix[own][:, None] ^ masks[spent][None, :]).ravel())
        owner.append(np.repeat(own, len(masks[spent])))
    v, who = np.concatenate(variants), np.concatenate(owner)
    order = np.argsort(v)
    v, who = v[order], who[order]
    first = np.concatenate([[True], v[1:] != v[:-1]]) if len(v) else np.zeros(0, bool)
    if first.all():
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    least = np.minimum.reduceat(who, np.flatnonzero(first))[np.cumsum(first) - 1]  # fps are sorted: the least owner is the least fingerprint
    differ = least != who
    pair = np.unique(least[differ].astype(np.uint64) << np.uint64(32) | who[differ].astype(np.uint64))
    a, b = (pair >> np.uint64(32)).astype(np.int64), (pair & np.uint64(0xFFFFFFFF)).astype(np.int64)
    near = np.bitwise_count(fps[a] ^ fps[b]) <= radius
    return forest(fps, a[near], b[near])


def forest(fps: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, least node of its part) for every node that a link touches."""
    root = np.arange(len(fps))
    while True:
        ra, rb = root[a], root[b]
        open_ = ra != rb
        if not open_.any():
            break
        a, b, ra, rb = a[open_], b[open_], ra[open_], rb[open_]
        np.minimum.at(root, np.maximum(ra, rb), np.minimum(ra, rb))
        while (root[root] != root).any():
            root = root[root]
    moved = np.flatnonzero(root != np.arange(len(fps)))
    return fps[moved], fps[root[moved]]


def leading_bits(n: int, radius: int = 4, most: int = 26) -> int:
    """Cells so many that one expands to at most about CELL_VARIANTS variants."""
    ball = sum(math.comb(64, k) for k in range(radius // 2 + 1))
    return min(most, max(5, math.ceil(math.log2(max(1.0, n * ball / CELL_VARIANTS)))))


def links(classes: DataFrame, n: int, radius: int = 4) -> DataFrame:
    """(a, b) with b the lesser, spanning every component of fingerprints at `radius` or fewer differing bits.

    classes: one row per distinct fingerprint, column fp; n: how many there are.
    """
    if radius not in (0, 2, 4, 6):
        raise ValueError("radius is 0, 2, 4 or 6")
    lead = leading_bits(n, radius)
    masks = F.array(*[F.lit(int(m)) for m in flips(lead, radius // 2)])
    top = F.shiftrightunsigned("fp", 64 - lead)
    dealt = classes.select("fp", F.explode(F.transform(masks, lambda m: top.bitwiseXOR(m).cast("int"))).alias("cell"))
    ship(classes.sparkSession)

    def run(cell_key, table):
        fps = np.sort(table.column("fp").to_numpy().view(np.uint64))
        a, b = cell_links(fps, cell_key[0].as_py(), lead, radius)
        return pa.table({"a": a.view(np.int64), "b": b.view(np.int64)})

    return dealt.groupBy("cell").applyInArrow(run, "a long, b long")


def components(pairs: DataFrame, rounds: int = 40) -> DataFrame:
    """(node, root) for each node of the link table (a, b); root is the least node of its component.

    Alternating star contraction: each round hangs neighbours on the least neighbour, larger ones first, then all lesser
    ones; a hub's neighbours are reduced by a partial minimum before the shuffle, never gathered.
    """
    spark = pairs.sparkSession
    edges, path = written(pairs.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "links")
    before = None
    for _ in range(rounds):
        # Large star: every node's greater neighbours hang on the least of the node and its neighbours.
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        # Small star: a node and its lesser neighbours hang on the least of them.
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct(F.col("u"), F.col("m").alias("v")))).alias("e"))
        fresh, new_path = written(small.select("e.u", "e.v").where("u <> v").distinct(), "links")
        state = fresh.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        delete(spark, path)
        edges, path = fresh, new_path
        if tuple(state) == before:
            break
        before = tuple(state)
    else:
        raise RuntimeError("components did not settle")
    return edges.groupBy("u").agg(F.min("v").alias("root")).withColumnRenamed("u", "node")


def rooted(classes: DataFrame, radius: int = 4) -> DataFrame:
    """classes (one row per distinct fp) with root, the least fingerprint of the component."""
    of = components(links(classes.select("fp"), classes.count(), radius))
    return classes.join(of, classes.fp == of.node, "left").select(*(classes[c] for c in classes.columns), F.coalesce("root", "fp").alias("root"))


def near_duplicates(docs: DataFrame, radius: int = 4, shingle: int = SHINGLE) -> DataFrame:
    """doc_id, fp and component_id (the least doc_id reachable) for every row of docs."""
    prints, _ = written(fingerprints(docs, shingle), "prints")
    classes, path = written(prints.groupBy("fp").agg(F.min("doc_id").alias("least_id")), "classes")
    placed = rooted(classes, radius)
    named = placed.groupBy("root").agg(F.min("least_id").alias("component_id"))
    by_print = placed.join(named, "root").select("fp", "component_id")
    return prints.join(by_print, "fp").select("doc_id", "fp", "component_id")


def simhash_dedup(docs: DataFrame) -> DataFrame:
    got = near_duplicates(docs)
    return got.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def one_of_each(docs: DataFrame) -> DataFrame:
    """One row of each component of the rows with an id, with the columns of docs; rows with a null id link nothing and all stay.

    The row that stays has the component's least id and, of that id's rows, the least hash of the text. Rows are told
    apart by a surrogate key, so docs is written once: an id that occurs again stays in each component it names.
    """
    spark = docs.sparkSession
    numbered, _ = written(docs.withColumn(ROW, F.monotonically_increasing_id()), "rows")
    named = numbered.where("doc_id is not null")
    thin = named.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("tie"), ROW, "text")
    prints, path = written(prints_of(thin), "prints")
    classes, _ = written(prints.groupBy("fp").agg(F.min(F.struct("doc_id", "tie", ROW)).alias("least")), "classes")
    delete(spark, path)
    stay = rooted(classes).groupBy("root").agg(F.min("least").alias("least")).select(f"least.{ROW}")
    return named.join(stay, ROW, "left_semi").unionByName(numbered.where("doc_id is null")).select(*docs.columns)
