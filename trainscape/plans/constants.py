"""Measured constants and prices of the infrastructures; all results that use them are simulated."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# Published constants (symbol, configuration, workers, value, spread, unit).
CONSTANTS = [
    ("startup", "fs", 10, 1.2, 0.1, "s"), ("startup", "fs", 50, 11.0, 1.0, "s"), ("startup", "fs", 100, 18.0, 1.0, "s"), ("startup", "fs", 200, 35.0, 3.0, "s"),
    ("startup", "vc", 10, 132.0, 6.0, "s"), ("startup", "vc", 50, 160.0, 5.0, "s"), ("startup", "vc", 100, 292.0, 8.0, "s"), ("startup", "vc", 200, 606.0, 12.0, "s"),
    ("bandwidth", "object_store", None, 65.0, 7.0, "MB/s"), ("bandwidth", "block_volume", None, 1950.0, 50.0, "MB/s"),
    ("bandwidth", "net_t2_medium", None, 120.0, 6.0, "MB/s"), ("bandwidth", "net_c5_large", None, 225.0, 8.0, "MB/s"),
    ("bandwidth", "cache_t3_medium", None, 630.0, 25.0, "MB/s"), ("bandwidth", "cache_m5_large", None, 1260.0, 35.0, "MB/s"),
    ("latency", "object_store", None, 8e-2, 2e-2, "s"), ("latency", "block_volume", None, 3e-5, 5e-6, "s"),
    ("latency", "net_t2_medium", None, 5e-4, 1e-4, "s"), ("latency", "net_c5_large", None, 1.5e-4, 2e-5, "s"), ("latency", "cache_t3_medium", None, 1e-2, 2e-3, "s"),
]
# Published 75 MB parameter-server trials (workers, function GB, server, transfer s and update s of each RPC framework).
RPC_TRIALS = [
    (1, 3, "t2.2xlarge", 2.62, 2.9, 21.8, 0.5), (1, 1, "t2.2xlarge", 3.02, 2.9, 34.4, 0.5), (1, 3, "c5.4xlarge", 1.85, 2.3, 19.7, 0.4), (1, 1, "c5.4xlarge", 2.36, 2.3, 32.0, 0.4),
    (10, 3, "t2.2xlarge", 5.7, 33.0, 68.5, 13.0), (10, 1, "t2.2xlarge", 8.2, 34.0, 82.0, 13.0), (10, 3, "c5.4xlarge", 3.7, 27.0, 52.0, 6.0), (10, 1, "c5.4xlarge", 5.6, 25.0, 84.0, 6.0),
]
# Published slowdown and relative cost against the object store (run, channel, slowdown, cost); null where the channel cannot hold the model.
PUBLISHED_CHANNELS = [
    ("lr_w10", "cache_mt", 4.17, 5.0), ("lr_w10", "kv_db", 0.83, 0.95), ("lr_w10", "vm_ps", 3.85, 4.7), ("lr_w50", "cache_mt", 3.70, 4.5), ("lr_w50", "kv_db", 0.81, 0.92), ("lr_w50", "vm_ps", 3.70, 4.47),
    ("km10_w50", "cache_mt", 1.32, 1.58), ("km10_w50", "kv_db", 0.93, 1.13), ("km10_w50", "vm_ps", 1.23, 1.48), ("km1000_w50", "cache_mt", 1.19, 1.43), ("km1000_w50", "kv_db", 0.90, 1.03), ("km1000_w50", "vm_ps", 1.27, 1.52),
    ("conv_w10", "cache_mt", 0.77, 0.9), ("conv_w10", "kv_db", None, None), ("conv_w10", "vm_ps", 4.01, 4.8), ("conv_w50", "cache_mt", 0.75, 0.89), ("conv_w50", "kv_db", None, None), ("conv_w50", "vm_ps", 4.03, 4.85),
]
# Published seconds of both patterns through the object store (model, all_reduce, scatter_reduce), and pipeline runs (infra, model, seconds, accuracy %, dollars).
PUBLISHED_PATTERNS = [("lr", 9.2, 9.8), ("conv", 3.3, 3.1), ("residual", 17.3, 8.5)]
PUBLISHED_PIPELINES = [("fs", "lr", 96.0, 62.2, 0.47), ("vc", "lr", 233.0, 62.1, 0.31), ("fs", "conv", 1712.0, 80.45, 8.37), ("vc", "conv", 1350.0, 80.52, 1.74)]
#: Unit prices per worker second implied by the published pipeline runs (means of both runs), and hourly prices of a cache node and a GPU machine.
PRICE_FS, PRICE_VC, CACHE_HOUR, GPU_HOUR = 4.89e-5, 1.31e-5, 0.034, 0.75
#: A managed key-value database refuses larger items; it communicates in this share of the object store's time.
KV_ITEM_BYTES, KV_SHARE = 400_000, 0.8
CACHE_STARTUP_S, LIFETIME_S, FUNCTION_LINK_MB = 120.0, 900.0, 70.0


def constants(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(CONSTANTS, "symbol string, config string, workers int, value double, spread double, unit string")


def constant(symbol: str, config: str, bound: int = 0) -> float:
    """A constant, or its value less (-1) or plus (1) its spread."""
    return next(v + bound * s for n, c, _, v, s, _ in CONSTANTS if (n, c) == (symbol, config))


def startup(workers: Column, infra: str, bound: int = 0) -> Column:
    """Start-up seconds: linear between the measured points, level before the first, along the last slope beyond."""
    points = [(w, v + bound * s) for n, c, w, v, s, _ in CONSTANTS if (n, c) == ("startup", infra)]
    out = F.when(workers <= points[0][0], F.lit(points[0][1]))
    for (w0, v0), (w1, v1) in zip(points, points[1:]):
        line = F.lit(v0) + (workers - w0) * F.lit((v1 - v0) / (w1 - w0))
        out = out.when(workers <= w1, line) if w1 != points[-1][0] else out.otherwise(line)
    return out


def extrapolated(workers: Column) -> Column:
    return (workers < 10) | (workers > 200)
