"""Replay of real traces on infrastructure profiles: seconds and dollars, always simulated."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trainscape.plans import constants as K


@dataclass(frozen=True)
class Profile:
    """Where a trace is replayed: start-up curve, load and link speeds in MB/s, latency, relative speed, price a worker second, price an hour of a node."""

    name: str
    startup: str
    bandwidth: float
    latency: float
    speed: float = 1.0
    price: float = K.PRICE_FS
    node_hour: float = 0.0
    extra_startup_s: float = 0.0
    bill_startup: bool = False
    load_mb: float = K.constant("bandwidth", "object_store")

    @classmethod
    def fs(cls, channel: str = "object_store", mem_gb: float = 3.0) -> Profile:
        """Function workers; a function's speed goes with its memory (3 GB: 1.8 virtual CPUs)."""
        from trainscape.plans.channels import CHANNELS

        c = CHANNELS[channel]
        return cls(f"fs_{channel}", "fs", c.bandwidth, c.latency, mem_gb / 3.0, node_hour=c.hour, extra_startup_s=c.startup_s)

    @classmethod
    def vc(cls, net: str = "net_t2_medium") -> Profile:
        return cls(f"vc_{net}", "vc", K.constant("bandwidth", net), K.constant("latency", net), price=K.PRICE_VC, bill_startup=True)

    @classmethod
    def vc_gpu(cls, kind: str = "newer") -> Profile:
        """Two GPU generations: the newer one is 15 % faster and 30 % cheaper."""
        old = replace(cls.vc("net_c5_large"), name="vc_gpu_older", speed=8.0 / 1.15, price=K.GPU_HOUR / 3600)
        return old if kind == "older" else replace(old, name="vc_gpu_newer", speed=8.0, price=0.7 * K.GPU_HOUR / 3600)

    @classmethod
    def hadoop_ps(cls, slowdown: float, startup_s: float) -> Profile:
        """A parameter-server system on a Hadoop stack; no numbers are published, so both are the caller's."""
        return replace(cls.vc(), name="hadoop_ps", speed=1.0 / slowdown, extra_startup_s=startup_s)

    @classmethod
    def hybrid(cls, n_servers: int = 1) -> Profile:
        """Functions around parameter servers; the link grows with the servers, (de)serialisation does not."""
        return cls("hp", "fs", K.FUNCTION_LINK_MB, K.constant("latency", "net_t2_medium"), node_hour=0.68 * n_servers, extra_startup_s=K.CONSTANTS[4][3])


def replay(trace: DataFrame, profile: Profile, workers: int, row_s: float, data_mb: float) -> DataFrame:
    """The timeline (infra, round, worker, phase, sim_start, sim_end, simulated) of a trace on a profile.

    Loading takes a worker's share of the data, computing row_s a row, sending
    its messages and bytes. Rounds are synchronous: the next starts when the
    slowest worker has ended.
    """
    total = trace.where("phase = 'load'").agg(F.sum("rows").alias("_all"))
    share = data_mb / profile.load_mb
    timed = trace.crossJoin(F.broadcast(total))  # one row
    seconds = (
        F.when(F.col("phase") == "load", F.col("rows") / F.greatest(F.col("_all"), F.lit(1)) * share)
        .when(F.col("phase") == "compute", F.col("rows") * (row_s / profile.speed))
        .otherwise(F.col("n_msgs") * profile.latency + F.col("n_bytes") / 1e6 / profile.bandwidth)
    )
    phases = timed.groupBy("round", "worker", "phase").agg(F.sum(seconds).alias("s"))
    start = trace.sparkSession.range(1).select(F.lit(0).alias("round"), F.explode(F.sequence(F.lit(0), F.lit(workers - 1))).alias("worker"), F.lit("startup").alias("phase"), F.greatest(K.startup(F.lit(workers), profile.startup), F.lit(profile.extra_startup_s)).alias("s"))
    phases = phases.unionByName(start).withColumn("k", F.array_position(F.array(*map(F.lit, ("startup", "load", "compute", "communicate"))), F.col("phase")))
    lengths = phases.groupBy("round", "worker").agg(F.sum("s").alias("s")).groupBy("round").agg(F.max("s").alias("len"))
    ahead = F.coalesce(F.sum("len").over(Window.orderBy("round").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    until = F.sum("s").over(Window.partitionBy("round", "worker").orderBy("k").rowsBetween(Window.unboundedPreceding, 0))
    placed = phases.withColumn("until", until).join(lengths.select("round", ahead.alias("at")), "round")
    return placed.select(F.lit(profile.name).alias("infra"), "round", "worker", "phase", (F.col("at") + F.col("until") - F.col("s")).alias("sim_start"), (F.col("at") + F.col("until")).alias("sim_end"), F.lit(True).alias("simulated"))


def dollar_cost(timeline: DataFrame, profile: Profile, workers: int) -> DataFrame:
    """(infra, seconds, billed_s, dollars) of a timeline."""
    t = timeline.groupBy("infra").agg(F.max("sim_end").alias("seconds"), F.max(F.when(F.col("phase") == "startup", F.col("sim_end"))).alias("_start"))
    billed = F.col("seconds") - (F.lit(0.0) if profile.bill_startup else F.coalesce("_start", F.lit(0.0)))
    return t.select("infra", "seconds", billed.alias("billed_s"), (billed * workers * profile.price + F.col("seconds") * (profile.node_hour / 3600)).alias("dollars"))
