"""Communication channels: profiles for replay, the file protocol for real, and their limits."""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.plans import constants as K
from trainscape.plans.job import ItemTooLarge


@dataclass(frozen=True)
class Channel:
    """Bandwidth in MB/s, latency and start-up in seconds, price an hour, item limit, whether transfers queue at one thread."""

    name: str
    bandwidth: float
    latency: float
    startup_s: float = 0.0
    hour: float = 0.0
    item_cap: int | None = None
    single_thread: bool = False
    share: float = 1.0


CHANNELS = {
    c.name: c
    for c in (
        Channel("object_store", K.constant("bandwidth", "object_store"), K.constant("latency", "object_store")),
        Channel("cache_mt", K.constant("bandwidth", "cache_t3_medium"), K.constant("latency", "cache_t3_medium"), K.CACHE_STARTUP_S, K.CACHE_HOUR),
        Channel("cache_st", K.constant("bandwidth", "cache_t3_medium"), K.constant("latency", "cache_t3_medium"), K.CACHE_STARTUP_S, K.CACHE_HOUR, single_thread=True),
        Channel("kv_db", K.constant("bandwidth", "object_store"), K.constant("latency", "object_store"), item_cap=K.KV_ITEM_BYTES, share=K.KV_SHARE),
        Channel("vm_ps", K.FUNCTION_LINK_MB, K.constant("latency", "net_t2_medium"), K.CONSTANTS[4][3], 0.68),
    )
}


def check_item(channel: str, n_bytes: int) -> None:
    cap = CHANNELS[channel].item_cap
    if cap is not None and n_bytes > cap:
        raise ItemTooLarge(f"{n_bytes} bytes; {channel} takes items of up to {cap}")


def round_seconds(channel: Channel, m_mb: Column, w: Column) -> Column:
    """Seconds of one scatter-reduce round; null where an item is over the channel's limit.

    A single-threaded store serves the workers' bytes one after the other. A
    parameter server takes a push and a pull of all workers over its own link,
    and the measured server update.
    """
    from trainscape.plans.analytic import rpc_update

    if channel.name == "vm_ps":
        return 2 * (m_mb * w / F.lit(channel.bandwidth) + F.lit(channel.latency)) + rpc_update(w, m_mb)
    bandwidth = F.lit(channel.bandwidth) / (w if channel.single_thread else F.lit(1.0))
    seconds = (3 * w - 2) * (m_mb / w / bandwidth + F.lit(channel.latency)) * F.lit(channel.share)
    return seconds if channel.item_cap is None else F.when(m_mb * 1e6 <= channel.item_cap, seconds)


def replay(runs: DataFrame, names: list[str] | None = None) -> DataFrame:
    """Runs (run, w, m_mb, rounds, base_s) on each channel: adds channel, comm_s, time_s, dollars; base_s is what does not communicate."""
    out = None
    for name in names or ["object_store", "cache_mt", "kv_db", "vm_ps"]:
        c = CHANNELS[name]
        one = runs.withColumn("channel", F.lit(name)).withColumn("comm_s", F.col("rounds") * round_seconds(c, F.col("m_mb"), F.col("w")))
        one = one.withColumn("time_s", F.lit(c.startup_s) + F.col("base_s") + F.col("comm_s"))
        one = one.withColumn("dollars", K.PRICE_FS * F.col("w") * F.col("time_s") + F.col("time_s") * (c.hour / 3600))
        out = one if out is None else out.unionByName(one)
    return out.withColumn("simulated", F.lit(True))


def relative(replayed: DataFrame, base: str = "object_store") -> DataFrame:
    """Adds slowdown and relative_cost against the base channel of the same run; over 1 the base is better."""
    b = replayed.where(F.col("channel") == base).select("run", F.col("time_s").alias("_t"), F.col("dollars").alias("_d"))
    return replayed.join(b, "run").withColumn("slowdown", F.col("time_s") / F.col("_t")).withColumn("relative_cost", F.col("dollars") / F.col("_d")).drop("_t", "_d")


class FileChannel:
    """Statistics as Parquet files named by epoch, iteration and worker under a shared folder.

    send() writes a worker's part, await_count() polls the listing until the
    parts of all workers are there, merge() reads them, publish() writes the
    merged state and fetch() polls for it: the two phases of a synchronous round.
    """

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")
        self._fs = spark._jvm.org.apache.hadoop.fs.Path(self.root).getFileSystem(spark._jsc.hadoopConfiguration())

    def _exists(self, path: str) -> bool:
        return self._fs.exists(self.spark._jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS"))

    def _round(self, epoch: int, iteration: int) -> str:
        return f"{self.root}/epoch={epoch}/iteration={iteration}"

    def send(self, stats: DataFrame, epoch: int, iteration: int, worker: int) -> None:
        stats.write.mode("overwrite").parquet(f"{self._round(epoch, iteration)}/partition={worker}")

    def listing(self, epoch: int, iteration: int, workers: int) -> list[int]:
        return [j for j in range(workers) if self._exists(f"{self._round(epoch, iteration)}/partition={j}")]

    def _poll(self, ready, what: str, poll_s: float, timeout_s: float) -> None:
        until = time.monotonic() + timeout_s
        while not ready():
            if time.monotonic() > until:
                raise TimeoutError(what)
            time.sleep(poll_s)

    def await_count(self, epoch: int, iteration: int, workers: int, poll_s: float = 0.05, timeout_s: float = 10.0) -> None:
        self._poll(lambda: len(self.listing(epoch, iteration, workers)) == workers, f"round {epoch}.{iteration}: {workers} parts", poll_s, timeout_s)

    def merge(self, epoch: int, iteration: int, workers: int) -> DataFrame:
        return self.spark.read.parquet(*(f"{self._round(epoch, iteration)}/partition={j}" for j in range(workers)))

    def publish(self, model: DataFrame, epoch: int, iteration: int) -> None:
        model.write.mode("overwrite").parquet(f"{self._round(epoch, iteration)}/merged")

    def fetch(self, epoch: int, iteration: int, poll_s: float = 0.05, timeout_s: float = 10.0) -> DataFrame:
        path = f"{self._round(epoch, iteration)}/merged"
        self._poll(lambda: self._exists(path), f"merged state of round {epoch}.{iteration}", poll_s, timeout_s)
        return self.spark.read.parquet(path)
