"""Splits, workers, batches and samples by portable hashes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trainscape.functions.hashing import SPAN, portable_hash


def split(df: DataFrame, keys: list[str], train: float = 0.9, seed: str = "") -> DataFrame:
    """Adds split: 'validation' for the tenth of hashes from 0, 'train' for the rest."""
    return df.withColumn("split", F.when(F.pmod(portable_hash(f"split{seed}", *keys), F.lit(10)) >= round(10 * (1 - train)), "train").otherwise("validation"))


def assign_workers(df: DataFrame, keys: list[str], workers: int, balance: str = "hash") -> DataFrame:
    """Adds worker. 'hash' is uniform and needs no exchange; 'exact' deals equal shares in hash order.

    'exact' ranks inside 4,096 hash ranges and adds the ranges' offsets, so no
    task sorts more than its ranges.
    """
    h = portable_hash("worker", *keys)
    if balance == "hash":
        return df.withColumn("worker", F.pmod(h, F.lit(workers)).cast("int"))
    ranged = df.withColumn("_h", h).withColumn("_r", F.shiftright("_h", 20))
    counts = ranged.groupBy("_r").agg(F.count("*").alias("_n"))
    ahead = Window.orderBy("_r").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("_r", F.coalesce(F.sum("_n").over(ahead), F.lit(0)).alias("_o"), F.sum("_n").over(Window.partitionBy(F.lit(1))).alias("_t"))
    rank = F.row_number().over(Window.partitionBy("_r").orderBy("_h", *keys)) - 1
    placed = ranged.withColumn("_k", rank).join(F.broadcast(offsets), "_r")  # at most 4,096 rows
    return placed.withColumn("worker", F.floor((F.col("_k") + F.col("_o")) * workers / F.col("_t")).cast("int")).drop("_h", "_r", "_k", "_o", "_t")


def assign_batches(df: DataFrame, keys: list[str], batches: int, epoch: int | None = None) -> DataFrame:
    """Adds batch in [0, batches); a new order for each epoch if one is named."""
    salt = "batch" if epoch is None else f"batch{epoch}"
    return df.withColumn("batch", F.pmod(portable_hash(salt, *keys), F.lit(batches)).cast("int"))


def batches_of(rows: int, batch_size: int) -> int:
    return max(1, -(-rows // batch_size))


def sample_hash(df: DataFrame, keys: list[str], fraction: float) -> DataFrame:
    """The rows whose sample hash is in the first `fraction` of its range; the same rows every time."""
    return df.where(portable_hash("sample", *keys) < int(fraction * SPAN))


def sample_stratified(df: DataFrame, keys: list[str], stratum: str, fractions: dict, default: float = 0.0) -> DataFrame:
    """The rows whose sample hash is in the first part of its range that their stratum names; a null stratum takes the default."""
    limit = F.lit(int(default * SPAN))
    for value, fraction in fractions.items():
        limit = F.when(F.col(stratum) == F.lit(value), F.lit(int(fraction * SPAN))).otherwise(limit)
    return df.where(portable_hash("sample", *keys) < limit)


def class_balance(df: DataFrame, label: str) -> DataFrame:
    """(label, n, share) of each class."""
    counts = df.groupBy(F.col(label).alias("label")).agg(F.count("*").alias("n"))
    return counts.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy(F.lit(1))))


def plan_invocations(spark, paths: list[str]) -> DataFrame:
    """(worker, path, attempt): one first start per partition file."""
    return spark.createDataFrame([(i, p, 0) for i, p in enumerate(sorted(paths))], "worker int, path string, attempt int")
