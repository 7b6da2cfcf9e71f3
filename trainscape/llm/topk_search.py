"""Exact top-k inner-product search, a block of candidates at a time."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from trainscape.llm._common import checkpointed, table

#: Vectors of a block, and those that a task holds at a time.
BLOCK, CHUNK = 256, 65_536
#: Queries scored together, and the numbers of all queries that are broadcast at a time (8 bytes each).
QUERIES, BROADCAST_NUMBERS = 512, 4_000_000
#: Vectors of smallest hash whose kth score is each query's first threshold.
SEEDS = 2048
_EXACT = 2**52
_LIMIT = 2**63 - 1
#: Score and id of an empty place; no real score is as low.
_NONE, _NO_ID = np.int64(-(2**63)), np.int64(_LIMIT)


def _quantised(batch: pa.RecordBatch | pa.Table) -> np.ndarray:
    values = batch.column("v")
    values = values.combine_chunks() if isinstance(values, pa.ChunkedArray) else values
    return np.asarray(values.flatten().to_numpy(zero_copy_only=False), float).reshape(len(values), -1)


def _is_exact(q: np.ndarray, x: np.ndarray) -> bool:
    return not q.size or not x.size or np.abs(q).max() * np.abs(x).max() * q.shape[1] < _EXACT


def _dot(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Integer inner products; by Python's integers, held to 64 bits, where floats would not be exact."""
    if _is_exact(q, x):
        return (q @ x.T).astype(np.int64)
    big = np.array([[int(a) for a in r] for r in q], object) @ np.array([[int(a) for a in r] for r in x], object).T
    return np.vectorize(lambda s: max(-_LIMIT, min(_LIMIT, s)), otypes=[np.int64])(big)


class TopK:
    """The k best (score, id) of each query so far; ties to the smaller id."""

    def __init__(self, queries: int, k: int):
        self.scores, self.ids, self.k = np.full((queries, k), _NONE), np.full((queries, k), _NO_ID), k

    def add(self, rows: np.ndarray, scores: np.ndarray, ids: np.ndarray) -> None:
        """Offers the same candidates to some queries: one row of scores each."""
        new = (scores >= self.scores[rows, -1:]).any(axis=1)
        rows, scores = rows[new], scores[new]
        s = np.concatenate([self.scores[rows], scores], axis=1)
        i = np.concatenate([self.ids[rows], np.broadcast_to(ids, scores.shape)], axis=1)
        i = np.where(s == _NONE, _NO_ID, i)
        first = np.lexsort((i, ~s))[:, : self.k]
        self.scores[rows], self.ids[rows] = np.take_along_axis(s, first, 1), np.take_along_axis(i, first, 1)


def search_blocks(queries: np.ndarray, query_ids: np.ndarray, vectors: np.ndarray, ids: np.ndarray, best: TopK, least: np.ndarray, block: int = BLOCK) -> tuple[int, int]:
    """Adds to best each query's best vectors but its own id; (block visits made, visits without bounds).

    ids are ascending. Each block keeps the largest and smallest value of every
    dimension; the sum of a query's greatest terms bounds the block. A query
    meets its blocks from the highest bound down and stops when bounds fall
    below its kth score, that of best or `least` (a score that k other vectors
    are known to reach); a block whose bound equals it is still met, as it may
    hold a smaller id.
    """
    starts = np.arange(0, len(ids), block)
    top = np.maximum.reduceat(vectors, starts)
    low = np.minimum.reduceat(vectors, starts)
    bounds = np.maximum(queries, 0) @ top.T + np.minimum(queries, 0) @ low.T
    if not _is_exact(queries, vectors):
        bounds += np.abs(queries) @ np.maximum(np.abs(top), np.abs(low)).T * 1e-9
    bounds = np.clip(bounds, float(-_LIMIT), float(_LIMIT))
    order = np.argsort(-bounds, axis=1, kind="stable")
    open_, made = np.arange(len(queries)), 0
    for turn in range(len(starts)):
        at = order[open_, turn]
        alive = bounds[open_, at] >= np.maximum(best.scores[open_, -1], least[open_])
        open_, at = open_[alive], at[alive]
        if not len(open_):
            break
        made += len(open_)
        for b in np.unique(at):
            rows, part = open_[at == b], slice(starts[b], starts[b] + block)
            scores = _dot(queries[rows], vectors[part])
            scores[ids[part] == query_ids[rows][:, None]] = _NONE
            best.add(rows, scores, ids[part])
    return made, len(queries) * len(starts)


def first_thresholds(queries: np.ndarray, query_ids: np.ndarray, seeds: np.ndarray, seed_ids: np.ndarray, k: int) -> np.ndarray:
    """The kth score of each query among the seeds but its own id; the lowest number if there are fewer."""
    best = TopK(len(queries), k)
    for i in range(0, len(queries) if len(seeds) else 0, QUERIES):
        rows = np.arange(i, min(i + QUERIES, len(queries)))
        scores = _dot(queries[rows], seeds)
        scores[seed_ids == query_ids[rows][:, None]] = _NONE
        best.add(rows, scores, seed_ids)
    return best.scores[:, -1]


def _by_length(part: pa.Table) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """(vec_id, v) of each length of vectors."""
    lengths = part.column("dims").to_numpy()
    found = {}
    for dims in np.unique(lengths):
        own = part.filter(pa.array(lengths == dims))
        found[int(dims)] = (own.column("vec_id").to_numpy(), _quantised(own))
    return found


def _search(shared, k: int, block: int, chunk: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        queries = shared.value
        best = {dims: TopK(len(ids), k) for dims, (ids, _, _) in queries.items()}

        def visit(held: list[pa.RecordBatch]) -> None:
            for dims, (ids, vectors) in _by_length(pa.Table.from_batches(held)).items():
                if dims in queries:
                    order = np.argsort(ids, kind="stable")
                    ids, vectors = ids[order], vectors[order]
                    query_ids, q, least = queries[dims]
                    for i in range(0, len(query_ids), QUERIES):
                        rows, part = slice(i, i + QUERIES), TopK(0, k)
                        part.scores, part.ids = best[dims].scores[rows], best[dims].ids[rows]
                        search_blocks(q[rows], query_ids[rows], vectors, ids, part, least[rows], block)

        held, n = [], 0
        for batch in batches:
            held.append(batch)
            n += batch.num_rows
            if n >= chunk:
                visit(held)
                held, n = [], 0
        if held:
            visit(held)
        for dims, (query_ids, _, _) in queries.items():
            scores, ids = best[dims].scores.ravel(), best[dims].ids.ravel()
            real = scores != _NONE
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(query_ids, k)[real]), pa.array(ids[real]), pa.array(scores[real])], ["query_id", "vec_id", "score"])

    return run


def exact_top_k(vectors: DataFrame, is_query, k: int = 5, scale: int = 256, block: int = BLOCK, chunk: int = CHUNK, numbers: int = BROADCAST_NUMBERS) -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k vectors of greatest integer inner product.

    Components become floor(scale * x). The vectors are dealt out by ranges of
    vec_id. Queries are broadcast in parts of about `numbers` components; for
    each part every task streams its range past it, `chunk` vectors at a time,
    cut into blocks. A query's kth score is carried from chunk to chunk and
    starts at its kth score among a few vectors of smallest hash. A task
    returns at most k rows a query, of which the k best are kept. Ties go to
    the smaller vec_id.

    Vectors that are null, empty or hold null or non-finite components, and
    rows without vec_id, take no part. Queries meet vectors of their own length
    only. Scores beyond 64 bits are held at its limits. A repeated row is a
    candidate each time but never its own query's; a repeated query is answered
    once, and query rows that share an id but not the vector are answered
    together. With fewer than k candidates all are returned, of an empty table
    none. Other columns are ignored.
    """
    spark = vectors.sparkSession
    x = F.col("embedding").cast("array<double>")
    sound = F.coalesce(F.forall(x, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < F.lit(float("inf")))), F.lit(False))
    rows = vectors.withColumn("embedding", x).withColumn("vec_id", F.col("vec_id").cast("long")).where(sound & (F.size("embedding") > 0) & F.col("vec_id").isNotNull())
    rows = rows.select("vec_id", F.size("embedding").alias("dims"), F.transform("embedding", lambda c: F.floor(c * scale).cast("double")).alias("v"), F.coalesce(is_query, F.lit(False)).alias("asked"))
    queries = checkpointed(rows.where("asked").select("vec_id", "dims", "v").distinct())
    parts = -(-(queries.agg(F.sum(F.col("dims").cast("long"))).first()[0] or 0) // numbers)
    total = rows.count() if parts else 0
    dealt = rows.select("vec_id", "dims", "v").repartitionByRange(max(1, min(max(spark.sparkContext.defaultParallelism, -(-total // chunk)), -(-total // block))), "vec_id", F.xxhash64("v"))
    dealt = checkpointed(dealt) if parts > 1 else dealt
    seeds = _by_length(rows.select("vec_id", "dims", "v").orderBy(F.xxhash64("vec_id"), "vec_id").limit(SEEDS).toArrow()) if parts else {}
    found = spark.createDataFrame([], "query_id long, vec_id long, score long")
    for part in range(parts):
        asked = _by_length(queries.where(F.pmod(F.xxhash64("vec_id"), F.lit(parts)) == part).orderBy("vec_id", "v").toArrow())
        none = (np.empty(0, np.int64), np.empty((0, 1)))
        shared = spark.sparkContext.broadcast({dims: (ids, q, first_thresholds(q, ids, *seeds.get(dims, none)[::-1], k)) for dims, (ids, q) in asked.items()})
        met = dealt.mapInArrow(_search(shared, k, block, chunk), found.schema)
        found = found.unionByName(checkpointed(met)) if parts > 1 else met
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id"))
    return found.withColumn("rank", rank.cast("int")).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op9_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


OP9_SQL = r"""
with v as (select vec_id, list_transform(embedding, lambda x: floor(256 * x::double)) as v from embeddings
           where embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0),
 s as (select q.vec_id as query_id, c.vec_id, list_inner_product(q.v, c.v)::bigint as score from v q join v c on q.vec_id % 50 = 0 and q.vec_id <> c.vec_id),
 r as (select *, row_number() over (partition by query_id order by score desc, vec_id)::integer as rank from s)
select query_id, rank, vec_id, score from r where rank <= 5"""
