"""Helpers shared by the corpus operators: shared-folder checkpoints, bounded
broadcasts, text chunking and distributed connected components."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.sources.tables import cut_lineage as checkpointed
from trainscape.sources.tables import forget
from trainscape.sources.tables import load as table  # noqa: F401
from trainscape.sources.tables import shared_folder as shared_dir  # noqa: F401

#: Rows of ids or thresholds that may be broadcast (16 to 60 bytes each).
BROADCAST_ROWS = 500_000
#: A key is hot if its rows are over one in this many of a table, and over HOT_ROWS.
HOT_SHARE, HOT_ROWS = 1000, 100
#: Parts that the rows of one key are dealt into where its value is copied to each part.
SALTS = 256
#: Characters of text that a Python kernel holds decoded at a time.
CHUNK_CHARS = 2_000_000
#: Java and RE2 pattern of a word: anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"


def small_side(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """A computed df, marked for broadcast only if it has few rows; beyond that a shuffled join."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def skew_join(left: DataFrame, right: DataFrame, keys: list[str], weight: str, total: int, computed: bool = True) -> DataFrame:
    """The inner join with right, which has one row for each key and in `weight` the number of left's rows with it.

    A computed right of few rows is broadcast. Else the hot keys of a left
    table of about `total` rows are few by their definition, so their rows of
    right are broadcast; the others are shuffled.
    """
    if computed and right.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS:
        return left.join(F.broadcast(right), keys)
    bar = max(HOT_ROWS, total // HOT_SHARE)
    hot = right.where(F.col(weight) > bar)
    cold = left.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(right.where(F.col(weight) <= bar), keys)
    return left.join(F.broadcast(hot), keys).unionByName(cold)


def salted_join(left: DataFrame, right: DataFrame, keys: list[str], spread: str, among: DataFrame) -> DataFrame:
    """The inner join with right, which has few rows for each key: left's rows of one key are dealt out by the column
    `spread`, and right's go once to each part that there is. For values too large to broadcast; `among` is a computed
    frame with left's keys and spread."""
    salt = F.pmod(F.xxhash64(spread), F.lit(SALTS)).alias("salt")
    parts = small_side(among.select(*keys, salt).distinct())
    return left.select("*", salt).join(right.join(parts, keys), [*keys, "salt"]).drop("salt")


def words_count(text: Column) -> Column:
    """Number of words of a text; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def crc_mod(key: Column, n: int) -> Column:
    return F.pmod(F.crc32(key.cast("string").cast("binary")), F.lit(n)).cast("int")


def text_chunks(batch: pa.RecordBatch, column: str = "text", limit: int = CHUNK_CHARS) -> Iterator[pa.RecordBatch]:
    """Slices of a batch whose texts hold about limit bytes; a longer text stands alone."""
    lengths = np.nan_to_num(np.asarray(pc.binary_length(batch.column(column)).to_numpy(zero_copy_only=False), dtype=float))
    total = np.cumsum(lengths)
    start = 0
    while start < batch.num_rows:
        before = total[start - 1] if start else 0.0
        end = max(start + 1, int(np.searchsorted(total, before + limit, side="right")))
        yield batch.slice(start, end - start)
        start = end


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit integers."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def connected_components(links: DataFrame) -> DataFrame:
    """(node, component) of every node of links (a, b): component is the smallest node reachable.

    Alternates two steps until nothing changes: each node's larger neighbours
    move to its smallest neighbour, then its smaller ones do. Minima are
    partially aggregated and those of nodes with very many links are broadcast,
    so a hub costs no single task.
    """

    def seen(edges: DataFrame) -> tuple:
        return tuple(edges.agg(F.count("*"), F.sum(F.hash("u", "v").cast("long")), F.bit_xor(F.xxhash64("u", "v"))).first())

    edges = checkpointed(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    last, state = None, seen(edges)
    while state != last and state[0]:
        last = state
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).select("u", F.least("u", "m").alias("m"), "n")
        large = skew_join(both.where("v > u"), low, ["u"], "n", 2 * state[0], computed=False).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.*").where("u <> v").distinct()
        before, edges = edges, checkpointed(small)
        forget(before)
        state = seen(edges)
    found = edges.select(F.col("u").alias("node"), F.col("v").alias("component"))
    found.step_path = edges.step_path
    return found
