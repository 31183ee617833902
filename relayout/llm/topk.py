"""Exact top-k search by distributed histogram selection.

Every query is scored against every candidate, a block of one against a block of the other (one matrix product). No
block keeps scores: it keeps, for each query, a histogram of them. The histograms are summed; the bin that holds the
k-th highest score becomes the range of the next, finer histogram, until a bin is one score wide. That score is the
query's threshold. A last pass keeps the scores at or above it; ties at the threshold are broken by the smaller id.

A block sends only the bins from its own k-th highest score upwards: the global k-th is never below it, and what lies
above it is counted in full, so a message has at most k bins for each query. Queries travel in batches of a fixed
number of bytes, so what is broadcast does not grow with the data; more queries mean more batches, each written down
before the next.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from relayout.llm.shared import materialise, table

K, QUERY_BYTES, BINS = 5, 16_000_000, 1024
CELLS = 1 << 22  # scores held at once by a task
DIGITS = 10**38 - 1  # what a decimal holds


def quantised(vectors: DataFrame, scale: int = 256) -> DataFrame:
    """(vec_id, v): floor(scale * x) of each component; rows that are null or hold null or non-finite components go."""
    # NaN is above and infinity equal to the bound in Spark's order, so one comparison finds all of them
    finite = F.forall("embedding", lambda x: x.isNotNull() & (F.abs(x.cast("double")) < float("inf")))
    rows = vectors.filter(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull()).filter(F.coalesce(finite, F.lit(False)))
    return rows.select(
        F.col("vec_id").cast("long").alias("vec_id"),
        F.transform("embedding", lambda x: F.floor(x.cast("double") * scale).cast("double")).alias("v"),
    )


def _matrix(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    """Ids and vectors of one length; a shorter vector ends in zeros, which leaves every inner product as it is."""
    ids, lists = batch.column("vec_id").to_numpy(zero_copy_only=False), batch.column("v")
    flat = lists.flatten().to_numpy(zero_copy_only=False)
    size = np.diff(lists.offsets.to_numpy())
    if len(size) and (size == size[0]).all():
        return ids, flat.reshape(len(size), -1)
    out = np.zeros((len(size), int(size.max()) if len(size) else 0))
    out[np.repeat(np.arange(len(size)), size), np.arange(len(flat)) - np.repeat(np.cumsum(size) - size, size)] = flat
    return ids, out


def _product(q: np.ndarray, block: np.ndarray) -> np.ndarray:
    """Inner products as whole numbers, exact whatever their size: in floats while every partial sum stays below 2 ** 53,
    else in 64-bit integers, else in Python's own."""
    wide = min(block.shape[1], q.shape[1])
    q, block = q[:, :wide], block[:, :wide]
    top = float(np.abs(q).sum(axis=1).max(initial=0)) * float(np.abs(block).max(initial=0))
    if top < 2**53:
        return (q @ block.T).astype(np.int64)
    if top < 2**62:
        return q.astype(np.int64) @ block.astype(np.int64).T
    whole = np.frompyfunc(int, 1, 1)
    return whole(q).astype(object) @ whole(block).astype(object).T


def _blocks(batches: Iterator[pa.RecordBatch], ids: np.ndarray, vectors: np.ndarray, floor: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Candidate ids, and scores (queries x candidates) where a query's own row counts as floor, which no score reaches."""
    order = np.argsort(ids, kind="stable")
    known = ids[order]
    for batch in batches:
        own, found = _matrix(batch)
        step = max(1, CELLS // max(1, len(ids)))
        for a in range(0, len(own), step):
            block, names = found[a : a + step], own[a : a + step]
            scores = _product(vectors, block)
            if scores.dtype != object and abs(floor) >= 2**62:
                scores = scores.astype(object)
            first, last = np.searchsorted(known, names, "left"), np.searchsorted(known, names, "right")
            for j in np.flatnonzero(last > first):
                scores[order[first[j] : last[j]], j] = floor
            yield names, scores


def _select(queries: np.ndarray, vectors: np.ndarray, candidates: DataFrame, top: float, k: int, spark: SparkSession) -> DataFrame:
    """The k best of one batch of queries; top: the largest component of a candidate, by size."""
    n = len(queries)
    longest = float(np.abs(vectors).sum(axis=1).max()) if n else 0.0
    bound = int(longest) * int(top) + 1  # no score is beyond it
    kind = np.int64 if bound < 2**61 else object
    low, high = np.full(n, -bound, kind), np.full(n, bound + 1, kind)  # the k-th highest score of each query is in [low, high)
    above = np.zeros(n, np.int64)  # scores known to be at or above high
    span = 2 * bound + 1
    few = np.zeros(n, bool)  # queries with fewer than k candidates: all of them count
    shared = spark.sparkContext.broadcast((queries, vectors))  # QUERY_BYTES at most
    while span > 1:
        width = -(-span // BINS)

        def histogram(batches: Iterator[pa.RecordBatch], low=low, high=high, width=width) -> Iterator[pa.RecordBatch]:
            ids, q = shared.value
            held = np.full((len(ids), 0), -1, np.int64)
            for _, scores in _blocks(batches, ids, q, -bound - 1):
                inside = (scores >= low[:, None]) & (scores < high[:, None])
                bins = np.where(inside, (np.where(inside, scores, low[:, None]) - low[:, None]) // width, -1).astype(np.int64)
                if bins.shape[1] > k:
                    bins = np.partition(bins, bins.shape[1] - k, axis=1)[:, -k:]
                held = np.concatenate([held, bins], axis=1)
                if held.shape[1] > k:
                    held = np.partition(held, held.shape[1] - k, axis=1)[:, -k:]
            row, _ = np.nonzero(held >= 0)
            yield pa.RecordBatch.from_arrays([pa.array(row.astype(np.int32)), pa.array(held[held >= 0].astype(np.int32))], ["q", "bin"])

        counted = candidates.mapInArrow(histogram, "q int, bin int").groupBy("q", "bin").agg(F.count(F.lit(1)).alias("n"))
        # of each query the bin where the count from the top reaches what is missing to k: at most one row a query
        down = F.sum("n").over(Window.partitionBy("q").orderBy(F.desc("bin")))
        counted = counted.withColumn("upto", down)
        need = k - above
        found = np.full(n, -1, np.int64)
        more = np.zeros(n, np.int64)
        for q, b, c, upto in counted.filter(F.col("upto") - F.col("n") < k).toPandas()[["q", "bin", "n", "upto"]].itertuples(index=False):  # at most k bins a query
            if upto >= need[q] and upto - c < need[q]:
                found[q], more[q] = b, upto - c
        few |= found < 0
        low = np.where(few, -bound, low + np.maximum(found, 0).astype(kind) * width)
        high = np.where(few, low, np.minimum(high, low + width))  # the last bin may reach past its range
        above = above + more
        span = width

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q = shared.value
        held = [np.zeros(0, np.int64), np.zeros(0, kind), np.zeros(0, np.int64)]  # query, score, candidate: the k first of this task
        for names, scores in _blocks(batches, ids, q, -bound - 1):
            i, j = np.nonzero(scores >= low[:, None])
            held = [np.concatenate(x) for x in zip(held, (i, scores[i, j].astype(kind), names[j]), strict=True)]
            order = np.array(sorted(range(len(held[0])), key=lambda r: (held[0][r], -held[1][r], held[2][r])), np.int64) if kind is object else np.lexsort((held[2], -held[1], held[0]))
            held = [x[order] for x in held]
            nth = np.arange(len(order)) - np.searchsorted(held[0], held[0], "left")
            held = [x[nth < k] for x in held]
        # a score is a decimal of 38 digits on its way, so that ranks are right beyond 64 bits too
        yield pa.RecordBatch.from_arrays([pa.array(ids[held[0]]), pa.array(held[2]), pa.array([str(max(-DIGITS, min(DIGITS, x))) for x in held[1].tolist()], pa.string())], ["query_id", "vec_id", "score"])

    found = candidates.mapInArrow(keep, "query_id long, vec_id long, score string")
    return found.select("query_id", "vec_id", F.col("score").cast("decimal(38,0)").alias("score"))


def top_k(queries: DataFrame, candidates: DataFrame, k: int = K, batch: int | None = None) -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k highest inner products, ties to the smaller id.

    queries and candidates: (vec_id, v) of whole numbers, as quantised() gives them. A candidate with the query's own
    vec_id is left out. Fewer than k candidates: all. Repeated rows: a vector (id and components alike) counts once; a
    query id that stands for several vectors is searched with each, and the best scores are kept. No queries: no rows.
    Products are exact and ranked by their true value up to 38 digits (larger ones count as equal); the score column is a
    long, so one beyond 2 ** 63 shows as the nearest long.

    batch: queries that travel together (by default as many as fit QUERY_BYTES). Each batch's results are written down
    before the next one starts, so neither the plan nor what is broadcast grows with the number of queries.
    """
    spark = candidates.sparkSession
    candidates = materialise(candidates.select("vec_id", "v").distinct(), "vectors")
    queries = materialise(queries.select("vec_id", "v").distinct(), "queries")
    n, width = queries.agg(F.count(F.lit(1)), F.max(F.size("v"))).first()
    if not n:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    top = candidates.agg(F.max(F.array_max(F.transform("v", F.abs)))).first()[0] or 0.0
    batch = batch or max(1, QUERY_BYTES // (8 * max(width, 1)))
    groups = -(-n // batch)
    found = None
    for g in range(groups):
        part = queries if groups == 1 else queries.filter(F.pmod(F.xxhash64("vec_id"), F.lit(groups)) == g)
        rows = part.toArrow()  # about batch rows
        if rows.num_rows:
            ids, vectors = _matrix(rows.combine_chunks().to_batches()[0])
            one = _select(ids, vectors, candidates, top, k, spark)
            found = one if groups == 1 else materialise(one, "best", found)
    both = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")).alias("rank")
    ends = [F.lit(str(x)).cast("decimal(38,0)") for x in (2**63 - 1, -(2**63))]
    score = F.greatest(F.least("score", ends[0]), ends[1]).cast("long").alias("score")
    return both.select("query_id", rank, "vec_id", score).filter(F.col("rank") <= k)


def is_query(vec_id: Column, every: int = 50) -> Column:
    return vec_id % every == 0


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = quantised(table(spark, sf_dir, "embeddings"))
    return top_k(vectors.filter(is_query(F.col("vec_id"))), vectors)


ORACLE = """
WITH whole AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(CAST(x AS DOUBLE) * 256)) AS v FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0
), scored AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(q.v, c.v) AS BIGINT) AS score
  FROM whole q JOIN whole c ON q.vec_id % 50 = 0 AND q.vec_id <> c.vec_id
), ranked AS (
  SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM scored
)
SELECT query_id, rank, vec_id, score FROM ranked WHERE rank <= 5
"""
