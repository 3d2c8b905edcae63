"""Exact top-k search with MaxScore over integer vectors.

A component x counts as floor(256 * x); a dimension is a term, its postings the rows' values in that dimension, kept per
shard as one column each with their least and greatest value. For a query, a term's contribution is its least possible
value plus a residual between 0 and a bound. Terms are ordered by bound; the longest tail of them whose bounds together
cannot lift a row to the current k-th best score is non-essential. Essential postings are traversed for all rows of the
shard's block, the others are probed, largest bound first, only for rows that can still compete (ties included). Shards
keep k rows a query, and the shards' lists are merged by (score descending, vec_id ascending).

Queries travel in blocks of at most QUERY_BLOCK rows (a few MB), one broadcast and one pass over the rows per block; of
several blocks one at a time is on the driver and in flight, and its lists are written before the next begins.
All arithmetic is exact: float64 while every sum stays below 2^52, int64 while it fits, Python integers beyond.

A query is a row whose id is divisible by `every`; its candidates are the rows of other ids. Defined results: null ids,
null vectors and vectors with null or non-finite components take no part; finite components of any size do, and a score
beyond a long raises OverflowError; a candidate of another dimension is not compared, and the inner product of empty
vectors is 0; repeated rows are separate candidates of each other's queries unless they share the id; equal query rows
count once, and different vectors under one id are queries of their own, each with its ranks from 1; fewer than k
candidates give fewer rows; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from bandloom.runtime import delete, scratch, ship, written

QUERY_BLOCK = 16_384
DOC_BLOCK = 16_384
STRIDE = 8
PART = "qid long, query_id long, vec_id long, score long"


def quantised(vectors: DataFrame) -> DataFrame:
    """vec_id and v (array<double> of whole numbers) of the rows that take part; doubles of 2^52 and more are whole already."""
    scaled = F.transform("embedding", lambda x: F.when(F.abs(x) < 2.0**44, F.floor(F.lit(256.0) * x).cast("double")).otherwise(F.lit(256.0) * x))
    whole = F.transform("embedding", lambda x: x.cast("double"))

    def finite(x: Column) -> Column:
        return F.coalesce(~F.isnan(x) & (F.abs(x) < float("inf")), F.lit(False))

    rows = vectors.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull()).select(F.col("vec_id").cast("long").alias("vec_id"), whole.alias("embedding"))
    return rows.where(F.forall("embedding", finite)).select("vec_id", scaled.alias("v"))


class Best:
    """The k best (score, id) pairs of each query so far. touched: (row, term) pairs that were read."""

    def __init__(self, n: int, k: int):
        self.k, self.score, self.ids = k, [np.zeros(0, np.int64)] * n, [np.zeros(0, np.int64)] * n
        self.touched = 0

    def bar(self, q: int) -> int | None:
        return int(self.score[q][-1]) if len(self.score[q]) == self.k else None

    def offer(self, q: int, score: np.ndarray, ids: np.ndarray) -> None:
        if len(score) > self.k:
            # Rows below the k-th score go; of those that tie with it only the k smallest ids can matter.
            kth = np.partition(score, len(score) - self.k)[len(score) - self.k]
            over, tied = np.flatnonzero(score > kth), np.flatnonzero(score == kth)
            if len(tied) > self.k:
                tied = tied[np.argpartition(ids[tied], self.k - 1)[: self.k]]
            keep = np.concatenate([over, tied])
            score, ids = score[keep], ids[keep]
        score, ids = np.concatenate([self.score[q], score]), np.concatenate([self.ids[q], ids])
        order = np.lexsort((ids, ~score))[: self.k]  # ~ reverses the order of longs and never overflows
        self.score[q], self.ids[q] = score[order], ids[order]


def typed(rows: np.ndarray, queries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Both in the cheapest type in which no product, sum or bound can be inexact."""
    with np.errstate(over="ignore"):
        peak = float(np.abs(rows).max(initial=0)) * float(np.abs(queries).max(initial=0)) * 2 * max(rows.shape[1], 1)
    if peak < 2**52:
        return rows, queries
    if peak < 2**62:
        return rows.astype(np.int64), queries.astype(np.int64)
    if not (np.isfinite(rows).all() and np.isfinite(queries).all()):
        raise OverflowError("256 times a component exceeds a double")
    return tuple(np.array([[int(x) for x in row] for row in part.tolist()], object).reshape(part.shape) for part in (rows, queries))


def longs(score: np.ndarray) -> np.ndarray:
    if score.dtype == object and any(not -(1 << 63) <= x < 1 << 63 for x in score):
        raise OverflowError("a score exceeds a long")
    return score.astype(np.int64)


def search_block(ids: np.ndarray, rows: np.ndarray, query_ids: np.ndarray, queries: np.ndarray, best: Best, numbers: np.ndarray) -> None:
    """Let a block of rows compete for each query. numbers: the queries' places in best."""
    rows, queries = typed(rows, queries)
    postings, least, most = np.ascontiguousarray(rows.T), rows.min(0), rows.max(0)
    for n, own, q in zip(numbers.tolist(), query_ids.tolist(), queries, strict=True):
        ends = np.stack([q * least, q * most])
        low, high = ends.min(0), ends.max(0)
        order = np.argsort(low - high, kind="stable")
        tail = np.concatenate([np.cumsum(high[order][::-1])[::-1], [0]])  # most that terms from j on can add
        floor_ = np.concatenate([[0], np.cumsum(low[order])])
        bar = best.bar(n)
        # Terms from `cut` on are non-essential: a row with no residual before it stays below the bar.
        cut = len(q) if bar is None else int(np.argmax(floor_ + tail < bar)) if (floor_ + tail < bar).any() else len(q)
        if cut == 0 and len(q):
            continue  # no row of this block can compete
        weight = q[order]
        alive = np.flatnonzero(ids != own)
        score = (weight[:cut] @ postings[order[:cut]])[alive] if len(q) else np.zeros(len(alive), np.int64)
        best.touched += cut * len(alive)
        while cut < len(q) and len(alive):
            fit = (score + tail[cut] >= bar).astype(bool)
            alive, score = alive[fit], score[fit]
            upto = min(len(q), cut + STRIDE)
            score = score + weight[cut:upto] @ postings[order[cut:upto]][:, alive]
            best.touched += (upto - cut) * len(alive)
            cut = upto
        score = longs(score)
        if bar is not None:
            fit = score >= bar
            alive, score = alive[fit], score[fit]
        if len(alive):
            best.offer(n, score, ids[alive])


def block_lists(rows: DataFrame, shared, first: int, k: int) -> DataFrame:
    """Every shard's k best rows for each query of one broadcast block; query n of it is numbered first + n."""

    def run(it):
        query_ids, queries = shared.value
        sizes = np.array([len(q) for q in queries])
        by_size = {int(s): np.flatnonzero(sizes == s) for s in np.unique(sizes)}
        best = Best(len(queries), k)
        for batch in it:
            vec_ids = batch.column(0).to_numpy(zero_copy_only=False)
            lists = batch.column(1)
            lengths = lists.value_lengths().to_numpy(zero_copy_only=False)
            flat = lists.flatten().to_numpy(zero_copy_only=False)
            starts = np.concatenate([[0], np.cumsum(lengths)])
            for size, numbers in by_size.items():
                own = np.flatnonzero(lengths == size)
                for at in range(0, len(own), DOC_BLOCK):
                    part = own[at : at + DOC_BLOCK]
                    matrix = flat[starts[part][:, None] + np.arange(size)[None, :]].reshape(len(part), size)
                    search_block(vec_ids[part], matrix, query_ids[numbers], np.stack([queries[i] for i in numbers]), best, numbers)
        for at in range(0, len(queries), 2000):
            upto = range(at, min(at + 2000, len(queries)))
            n = np.concatenate([np.full(len(best.ids[i]), i, np.int64) for i in upto])
            columns = [n + first, query_ids[n], np.concatenate([best.ids[i] for i in upto]), np.concatenate([best.score[i] for i in upto])]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["qid", "query_id", "vec_id", "score"])

    return rows.mapInArrow(run, PART)


def top_k(vectors: DataFrame, k: int = 5, every: int = 50, block: int = QUERY_BLOCK) -> DataFrame:
    """query_id, rank, vec_id, score of the k best rows for each row whose vec_id is divisible by `every`."""
    spark = vectors.sparkSession
    ship(spark)
    rows = quantised(vectors)
    queries = rows.where(F.col("vec_id") % every == 0).distinct()
    n_blocks = -(-queries.count() // block)
    if not n_blocks:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")

    def shared_block(some: DataFrame):
        mine = sorted((r[0], tuple(r[1])) for r in some.collect())  # about `block` rows
        return spark.sparkContext.broadcast((np.array([m[0] for m in mine], np.int64), [np.array(m[1], np.float64) for m in mine]))

    if n_blocks == 1:
        found = block_lists(rows, shared_block(queries), 0, k)
    else:
        number = F.pmod(F.xxhash64("vec_id", "v"), F.lit(n_blocks)).cast("int")
        kept, path = written(queries.withColumn("number", number), "queries")
        lists = scratch(spark, "lists")
        for b in range(n_blocks):
            shared = shared_block(kept.where(F.col("number") == b).select("vec_id", "v"))
            block_lists(rows, shared, b << 32, k).write.mode("append").parquet(lists)
            shared.unpersist()
        delete(spark, path)
        found = spark.read.schema(PART).parquet(lists)
    order = Window.partitionBy("qid").orderBy(F.col("score").desc(), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
