"""Views over events, traces and metrics: ranks, shapes, sets, sketches, correlated and cogrouped joins."""

from __future__ import annotations

import math

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def ranks(df: DataFrame, keys: list[str], order: list, tiles: int = 4) -> DataFrame:
    """Adds the rank family within keys: row_no, rank, dense, tile, percent and cume."""
    by = Window.partitionBy(*keys).orderBy(*order)
    return df.withColumns({"row_no": F.row_number().over(by), "rank": F.rank().over(by), "dense": F.dense_rank().over(by), "tile": F.ntile(tiles).over(by), "percent": F.percent_rank().over(by), "cume": F.cume_dist().over(by)})


def cube_counts(df: DataFrame, dims: list[str], value: str) -> DataFrame:
    """(dims, level, n, total) over all subsets of dims; level tells which dims are summed over."""
    return df.cube(*dims).agg(F.grouping_id().cast("int").alias("level"), F.count("*").alias("n"), F.sum(value).alias("total"))


def set_counts(df: DataFrame, dims: list[list[str]]) -> DataFrame:
    """(kind, key, n) of chosen grouping sets of one column each, by one scan."""
    names = [d for group in dims for d in group]
    cube = df.groupingSets([[F.col(c) for c in g] for g in dims], *names).agg(F.count("*").alias("n"), F.grouping_id().alias("g"))
    kind, key = F.lit(None).cast("string"), F.lit(None).cast("string")
    for i, n in enumerate(names):
        open_ = (F.shiftright("g", len(names) - 1 - i) % 2) == 0
        kind, key = F.when(open_, F.lit(n)).otherwise(kind), F.when(open_, F.col(n).cast("string")).otherwise(key)
    return cube.select(kind.alias("kind"), key.alias("key"), "n")


def widen(df: DataFrame, key: str, column: str, names: list[str], value: str | None = None) -> DataFrame:
    """One row per key, one column per name; the names are given, so nothing is scanned for them."""
    grouped = df.groupBy(key).pivot(column, names)
    return grouped.agg(F.sum(value) if value else F.count(F.lit(1))).na.fill(0)


def lengthen(df: DataFrame, key: str, names: list[str], variable: str = "name", value: str = "value") -> DataFrame:
    return df.unpivot([key], names, variable, value)


def latest_each(keys: DataFrame, rows: DataFrame, key: str, order: list, k: int, cols: list[str]) -> DataFrame:
    """For each key its first k rows by a lateral subquery; keys without rows give none. Spark turns it into one join and a limit per key."""
    own = rows.select(F.col(key).alias("_own"), *cols).where(F.col("_own") == F.col("_key").outer()).orderBy(*order).limit(k)
    left = keys.select(F.col(key).alias("_key")).distinct()
    return left.lateralJoin(own.select(*(F.col(c).alias(c) for c in cols))).withColumnRenamed("_key", key)


def compare_groups(before: DataFrame, after: DataFrame, key: str, value: str, parts: int = 64) -> DataFrame:
    """(key, n_before, n_after, change): both frames' groups of a key side by side in one cogrouped Arrow kernel; change is that of the mean.

    Each side comes in at most `parts` partial sums, so a hot key costs no task more than that.
    """

    def summed(df: DataFrame) -> DataFrame:
        return df.groupBy(key, F.pmod(F.xxhash64(value), F.lit(parts)).alias("part")).agg(F.count("*").alias("n"), F.sum(value).alias("total"))

    def run(k, left: pa.Table, right: pa.Table) -> pa.Table:
        n = [pc.sum(t.column("n")).as_py() or 0 for t in (left, right)]
        means = [math.fsum(x for x in t.column("total").to_pylist() if x is not None) / c if c else None for t, c in zip((left, right), n)]
        change = means[1] - means[0] if None not in means else None
        return pa.table({key: [k[0].as_py()], "n_before": pa.array([n[0]], pa.int64()), "n_after": pa.array([n[1]], pa.int64()), "change": pa.array([change], pa.float64())})

    kind = dict(before.dtypes)[key]
    return summed(before).groupBy(key).cogroup(summed(after).groupBy(key)).applyInArrow(run, f"{key} {kind}, n_before long, n_after long, change double")


def sketches(df: DataFrame, key: str, distinct: str, value: str, error: float = 0.02, bins: int = 16) -> DataFrame:
    """(key, distinct, median, bars): approximate distinct count, median and histogram of each key, in one aggregate."""
    return df.groupBy(key).agg(F.approx_count_distinct(distinct, error).alias("distinct"), F.percentile_approx(value, 0.5, 10_000).alias("median"), F.histogram_numeric(value, F.lit(bins)).alias("bars"))


def hinted(left: DataFrame, right: DataFrame, key: str, way: str) -> DataFrame:
    """A join by a chosen strategy: broadcast, merge, shuffle_hash or shuffle_replicate_nl."""
    return left.join(right.hint(way), key)


def list_partitions(df: DataFrame) -> DataFrame:
    """(worker, path, size, attempt): one first start for each file that a scan would read, from the files' own metadata."""
    files = df.select(F.col("_metadata.file_path").alias("path"), F.col("_metadata.file_size").alias("size")).groupBy("path").agg(F.first("size").alias("size"))
    return files.withColumn("worker", F.row_number().over(Window.orderBy("path")) - 1).select("worker", "path", "size", F.lit(0).alias("attempt"))
