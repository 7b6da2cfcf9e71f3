"""Reduction patterns over statistics in coordinate form (worker, coord, value, weight)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PATTERNS = ("all_reduce", "scatter_reduce", "tree_reduce")


def _finish(df: DataFrame, op: str) -> DataFrame:
    value = F.col("s") / F.col("w") if op == "mean" else F.col("s")
    return df.select("coord", value.alias("value"))


def gather(stats: DataFrame, limit: int = 10_000_000) -> DataFrame:
    """All statistics in one partition; refuses more rows than the limit."""
    if stats.limit(limit + 1).count() > limit:
        raise ValueError(f"more than {limit} statistics for one worker; use scatter_reduce")
    return stats.coalesce(1)


def all_reduce(stats: DataFrame, op: str = "mean") -> DataFrame:
    """(coord, value): reduced by one task, the leader, after partial sums in every task; for small models."""
    partial = stats.groupBy("coord").agg(F.sum(F.col("value") * F.col("weight")).alias("s"), F.sum("weight").alias("w"))
    return _finish(partial.coalesce(1), op)


def scatter_reduce(stats: DataFrame, op: str = "mean") -> DataFrame:
    """(coord, value): every task sums what it holds, one exchange deals the coordinates out, and each task reduces its slice; the model stays distributed."""
    return _finish(stats.groupBy("coord").agg(F.sum(F.col("value") * F.col("weight")).alias("s"), F.sum("weight").alias("w")), op)


def tree_reduce(stats: DataFrame, fan_in: int, op: str = "mean") -> DataFrame:
    """(coord, value): groups of fan_in workers first, then the groups."""
    first = stats.groupBy("coord", F.floor(F.col("worker") / fan_in).alias("g")).agg(F.sum(F.col("value") * F.col("weight")).alias("s"), F.sum("weight").alias("w"))
    return _finish(first.groupBy("coord").agg(F.sum("s").alias("s"), F.sum("w").alias("w")), op)


def leader_merge(stats: DataFrame, folder: str, op: str = "mean") -> DataFrame:
    """(worker, coord, value): aggregation through storage. Each worker's part is written to the shared folder, the leader
    reads and merges the parts and writes the merged state, and every worker reads it."""
    spark = stats.sparkSession
    stats.write.mode("overwrite").partitionBy("worker").parquet(f"{folder}/parts")
    parts = spark.read.parquet(f"{folder}/parts")
    all_reduce(parts, op).write.mode("overwrite").parquet(f"{folder}/merged")
    return parts.select("worker").distinct().crossJoin(spark.read.parquet(f"{folder}/merged"))  # one copy of the model for each worker


def ps_merge(model: DataFrame, stats: DataFrame, lr: float) -> DataFrame:
    """(coord, value): a parameter server's step; pushed gradients are averaged by weight and applied to its model."""
    grad = _finish(stats.groupBy("coord").agg(F.sum(F.col("value") * F.col("weight")).alias("s"), F.sum("weight").alias("w")), "mean").withColumnRenamed("value", "g")
    return model.join(grad, "coord", "full_outer").select("coord", (F.coalesce("value", F.lit(0.0)) - lr * F.coalesce("g", F.lit(0.0))).alias("value"))


def payload(spark, n_bytes: int, workers: int) -> DataFrame:
    """Statistics of a model of n_bytes on each worker, made without reading anything: coordinate c of worker j is c + j."""
    coords = -(-n_bytes // 8)
    rows = spark.range(coords * workers).select((F.col("id") % workers).cast("int").alias("worker"), F.floor(F.col("id") / workers).cast("int").alias("coord"))
    return rows.select("worker", "coord", (F.col("coord") + F.col("worker")).cast("double").alias("value"), F.lit(1.0).alias("weight"))


def reduce_with(pattern: str, stats: DataFrame, workers: int, op: str = "mean") -> DataFrame:
    if pattern == "all_reduce":
        return all_reduce(stats, op)
    return tree_reduce(stats, max(2, round(workers**0.5)), op) if pattern == "tree_reduce" else scatter_reduce(stats, op)


def broadcast_model(model: DataFrame, rows: DataFrame, coords: int, limit: int = 5_000_000) -> DataFrame:
    """Rows joined with a model by coord; the model is broadcast up to the limit of coordinates, shuffled beyond."""
    return rows.join(F.broadcast(model) if coords <= limit else model, "coord")


def transfers(pattern: str, channel: str, workers: int) -> tuple[int, int]:
    """(transfers on a worker's path, parts that a statistic is cut into).

    Through a store: slices w - 1 up, w - 1 down, 1 up, w - 1 down; the leader's
    path is its own write, w - 1 reads, the merged write and a read. Direct
    collectives move 2w - 2 slices, a parameter server takes a push and a pull.
    """
    if channel == "vm_ps":
        return 2, 1
    if channel == "direct":
        return (2 * workers - 2, workers) if pattern == "scatter_reduce" else (2 * workers - 2, 1)
    return (3 * workers - 2, workers) if pattern == "scatter_reduce" else (workers + 2, 1)


def choose_pattern(model_bytes: float, workers: int, bandwidth: float, latency: float) -> str:
    """The pattern of the smaller time on a worker's path through a store."""
    cost = {}
    for p in ("all_reduce", "scatter_reduce"):
        n, parts = transfers(p, "object_store", workers)
        cost[p] = n * (model_bytes / parts / bandwidth + latency)
    return min(cost, key=cost.get)


def ledger(stats: DataFrame, pattern: str, channel: str, workers: int, value_bytes: int = 8) -> DataFrame:
    """(worker, n_msgs, n_bytes) of one reduction of the statistics each worker holds."""
    n, parts = transfers(pattern, channel, workers)
    own = stats.groupBy("worker").agg((F.count("*") * value_bytes).alias("m"))
    return own.select("worker", F.lit(n).cast("long").alias("n_msgs"), F.ceil(F.col("m") / parts * n).alias("n_bytes"))


def missing_workers(listing: DataFrame, workers: DataFrame) -> DataFrame:
    """(epoch, iteration, worker) whose file a merge still waits for: workers of each round without a listed file."""
    rounds = listing.select("epoch", "iteration").distinct()
    expected = rounds.crossJoin(F.broadcast(workers.select("worker").distinct()))  # rounds under way times workers
    return expected.join(listing.select("epoch", "iteration", F.col("partition").alias("worker")), ["epoch", "iteration", "worker"], "left_anti")
