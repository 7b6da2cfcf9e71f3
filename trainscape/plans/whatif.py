"""What-if studies over the analytic model: a faster link, hot data, peaky arrivals."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trainscape.plans import analytic as A
from trainscape.plans import constants as K

#: A GPU multiplies the speed of an epoch by this on deep models.
GPU_SPEEDUP = 8.0


def whatif_fast_link(params: DataFrame, link_mb: float = 10_000.0) -> DataFrame:
    """(task, algo, w, design, runtime_s, dollars): today's designs beside functions and server over a fast link, without and with GPUs in the functions."""
    mode = {"load_mode": "per_worker"}
    gpu = K.GPU_HOUR / 3600
    designs = {
        "fs": A.cost_fs(A.runtime_fs(params, **mode)), "vc": A.cost_vc(A.runtime_vc(params, **mode)),
        "vc_gpu": A.cost_vc(A.runtime_vc(params.withColumn("compute_s", F.col("compute_s") / GPU_SPEEDUP), **mode), gpu),
        "hp": A.cost_hp(A.runtime_hp(params, **mode)), "hp_fast": A.cost_hp(A.runtime_hp(params, link_mb, update=False, **mode)),
        "hp_fast_gpu": A.cost_hp(A.runtime_hp(params, link_mb, update=False, speedup=GPU_SPEEDUP, **mode), gpu),
    }
    return reduce(DataFrame.unionByName, (d.select("task", "algo", "w", F.lit(n).alias("design"), "runtime_s", "dollars") for n, d in designs.items()))


def whatif_hot_data(params: DataFrame, vm_mb: float = 1250.0, link_mb: float = K.FUNCTION_LINK_MB) -> DataFrame:
    """(task, algo, w, design, load_s, runtime_s): the data sits in a machine; machines read it over their network, functions over the slow link."""
    designs = {"vc": (A.runtime_vc(params), vm_mb), "fs": (A.runtime_fs(params), link_mb), "hp": (A.runtime_hp(params), link_mb)}
    hot = lambda d, b: d.withColumn("load_s", F.col("s_mb") / b).withColumn("runtime_s", F.col("startup_s") + F.col("load_s") + F.col("comm_s") + F.col("comp_s"))
    return reduce(DataFrame.unionByName, (hot(d, b).select("task", "algo", "w", F.lit(n).alias("design"), "load_s", "runtime_s") for n, (d, b) in designs.items()))


def concurrency(jobs: DataFrame, start: str, end: str, weight: str) -> DataFrame:
    """(at, running): the running sum of weights at each change; ends count before starts of the same second.

    Sums run inside days and are offset by the days before, so that no task sorts all jobs.
    """
    moves = jobs.select(F.col(start).alias("at"), F.col(weight).cast("long").alias("d")).unionByName(jobs.select(F.col(end).alias("at"), (-F.col(weight)).cast("long").alias("d")))
    moves = moves.groupBy("at").agg(F.sum("d").alias("d")).withColumn("day", F.floor(F.col("at") / 86_400))
    ahead = Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)
    before = moves.groupBy("day").agg(F.sum("d").alias("d")).select("day", F.coalesce(F.sum("d").over(ahead), F.lit(0)).alias("before"))
    inside = F.sum("d").over(Window.partitionBy("day").orderBy("at").rowsBetween(Window.unboundedPreceding, 0))
    return moves.withColumn("inside", inside).join(before, "day").select("at", (F.col("inside") + F.col("before")).alias("running"))


def provision(jobs: DataFrame, policy: str, workers: int = 10) -> DataFrame:
    """One row for a policy over jobs (job_id, at seconds, work_s): (policy, jobs, mean_latency_s, peak_workers, dollars, utilisation).

    'fs' starts functions on demand, 'vm' machines on demand, 'reserved' holds as
    many machines as the peak needs for the whole horizon.
    """
    w = F.lit(workers)
    wait = {"fs": K.startup(w, "fs"), "vm": K.startup(w, "vc"), "reserved": F.lit(0.0)}[policy]
    run = jobs.withColumn("wait", wait).withColumn("finish", F.col("at") + F.col("wait") + F.col("work_s")).withColumn("workers", w)
    peak = concurrency(run, "at", "finish", "workers").agg(F.max("running").alias("peak_workers"))
    totals = run.agg(F.count("*").alias("jobs"), F.avg(F.col("wait") + F.col("work_s")).alias("mean_latency_s"), F.sum("work_s").alias("work"), F.sum(F.col("work_s") + F.col("wait")).alias("held"), (F.max("finish") - F.min("at")).alias("horizon"))
    both = totals.crossJoin(F.broadcast(peak))  # one row each
    busy = F.col("work") * workers
    dollars = {"fs": busy * K.PRICE_FS, "vm": F.col("held") * workers * K.PRICE_VC, "reserved": F.col("peak_workers") * F.col("horizon") * K.PRICE_VC}[policy]
    share = {"fs": F.lit(1.0), "vm": F.col("work") / F.col("held"), "reserved": busy / (F.col("peak_workers") * F.col("horizon"))}[policy]
    return both.select(F.lit(policy).alias("policy"), "jobs", "mean_latency_s", "peak_workers", dollars.alias("dollars"), share.alias("utilisation"))


def peaks(events: DataFrame) -> DataFrame:
    """(kind, hours, mean_jobs, max_jobs, peakiness) of arrivals per hour and kind; hours without arrivals are not counted."""
    hourly = events.groupBy("event_type", F.date_trunc("hour", F.col("ts").cast("timestamp")).alias("h")).agg(F.count("*").alias("n"))
    out = hourly.groupBy(F.col("event_type").alias("kind")).agg(F.count("*").alias("hours"), F.avg("n").alias("mean_jobs"), F.max("n").alias("max_jobs"))
    return out.withColumn("peakiness", F.col("max_jobs") / F.col("mean_jobs"))
