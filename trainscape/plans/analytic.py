"""The closed-form model of run time and cost, as columns over a parameter frame.

A parameter row has task, algo, w workers, s_mb data, m_mb model, rounds (epochs
of one worker), f_w (epochs at w over epochs at one), compute_s (a worker alone,
one epoch) and syncs (communications per epoch).
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from trainscape.plans import constants as K

#: Tasks with sizes in MB: data, model, rounds, seconds of one epoch on one worker, growth of epochs by worker.
TASKS = [("lr_dense", "admm", 8000.0, 0.000224, 10.0, 90.0, 0.0), ("lr_dense", "ga", 8000.0, 0.000224, 10.0, 90.0, 0.002), ("conv_image", "ga", 220.0, 12.0, 60.0, 300.0, 0.01), ("residual_image", "ga", 220.0, 89.0, 40.0, 2400.0, 0.01), ("lr_wide", "admm", 110_000.0, 0.032768, 10.0, 2000.0, 0.0), ("lr_ctr", "admm", 30_000.0, 8.0, 10.0, 600.0, 0.0)]
WORKERS = [1, 5, 10, 20, 50, 100, 150, 200, 300]


def parameter_grid(spark: SparkSession, tasks: list[tuple] | DataFrame = TASKS, workers: list[int] = WORKERS) -> DataFrame:
    t = tasks if isinstance(tasks, DataFrame) else spark.createDataFrame(tasks, "task string, algo string, s_mb double, m_mb double, rounds double, compute_s double, growth double")
    w = spark.createDataFrame([(x,) for x in workers], "w int")
    grid = t.crossJoin(w).withColumn("f_w", 1 + F.col("growth") * (F.col("w") - 1))
    return grid.withColumn("syncs", F.lit(1.0))


def _load(df_s: Column, load_mode: str, bandwidth: float) -> Column:
    whole = df_s / F.lit(bandwidth)
    return whole if load_mode == "aggregate" else whole / F.col("w")


def slices_seconds(legs: Column, bandwidth: float, latency: float) -> Column:
    return legs * (F.col("m_mb") / F.col("w") / F.lit(bandwidth) + F.lit(latency))


def runtime_fs(params: DataFrame, channel: str = "object_store", load_mode: str = "aggregate", bound: int = 0) -> DataFrame:
    """Adds startup_s, load_s, comm_s and comp_s (whole run) and runtime_s of function workers over a storage channel: 3w - 2 legs a round, as storage cannot compute."""
    b, l = K.constant("bandwidth", channel, -bound), K.constant("latency", channel, bound)
    epochs = F.col("rounds") * F.col("f_w")
    out = params.withColumns({"startup_s": K.startup(F.col("w"), "fs", bound), "load_s": _load(F.col("s_mb"), load_mode, K.constant("bandwidth", "object_store", -bound)), "comm_s": epochs * F.col("syncs") * slices_seconds(3.0 * F.col("w") - 2, b, l), "comp_s": epochs * F.col("compute_s") / F.col("w")})
    return _sum_terms(out)


def runtime_vc(params: DataFrame, net: str = "net_t2_medium", load_mode: str = "aggregate", bound: int = 0) -> DataFrame:
    """The same terms for a cluster of virtual machines with direct collectives: 2w - 2 legs a round."""
    b, l = K.constant("bandwidth", net, -bound), K.constant("latency", net, bound)
    epochs = F.col("rounds") * F.col("f_w")
    out = params.withColumns({"startup_s": K.startup(F.col("w"), "vc", bound), "load_s": _load(F.col("s_mb"), load_mode, K.constant("bandwidth", "object_store", -bound)), "comm_s": epochs * F.col("syncs") * slices_seconds(2.0 * F.col("w") - 2, b, l), "comp_s": epochs * F.col("compute_s") / F.col("w")})
    return _sum_terms(out)


def rpc_update(workers: Column, model_mb: Column, framework: int = 2, server: str = "c5.4xlarge", gb: int = 3) -> Column:
    """Server update seconds: linear in workers through the 75 MB trials of 1 and 10 workers, in proportion to the model."""
    one, ten = (next(t[4 + 2 * (framework - 1)] for t in K.RPC_TRIALS if t[:3] == (n, gb, server)) for n in (1, 10))
    return (F.lit(one) + (workers - 1) * F.lit((ten - one) / 9.0)) * model_mb / 75.0


def runtime_hp(params: DataFrame, link_mb: float = K.FUNCTION_LINK_MB, latency: float = 5e-4, update: bool = True, load_mode: str = "aggregate", speedup: float = 1.0) -> DataFrame:
    """Function workers around one parameter server: both start side by side, the server's link is shared, each round is a push, an update and a pull."""
    epochs = F.col("rounds") * F.col("f_w")
    each = 2.0 * (F.col("m_mb") * F.col("w") / F.lit(link_mb) + F.lit(latency)) + (rpc_update(F.col("w"), F.col("m_mb")) if update else F.lit(0.0))
    out = params.withColumns({"startup_s": F.greatest(K.startup(F.col("w"), "fs"), K.startup(F.lit(1), "vc")), "load_s": _load(F.col("s_mb"), load_mode, K.constant("bandwidth", "object_store")), "comm_s": epochs * F.col("syncs") * each, "comp_s": epochs * F.col("compute_s") / F.col("w") / F.lit(speedup)})
    return _sum_terms(out)


def _sum_terms(df: DataFrame) -> DataFrame:
    return df.withColumn("runtime_s", F.col("startup_s") + F.col("load_s") + F.col("comm_s") + F.col("comp_s"))


def cost_fs(df: DataFrame, channel_hour: float = 0.0, bill_startup: bool = False, price: float = K.PRICE_FS) -> DataFrame:
    """Adds dollars: workers billed while they run, and a channel node by the hour."""
    billed = F.col("runtime_s") - (F.lit(0.0) if bill_startup else F.col("startup_s"))
    return df.withColumn("dollars", price * F.col("w") * billed + F.col("runtime_s") * channel_hour / 3600)


def cost_vc(df: DataFrame, price: float = K.PRICE_VC) -> DataFrame:
    """Adds dollars: machines are billed from their start."""
    return df.withColumn("dollars", price * F.col("w") * F.col("runtime_s"))


def cost_hp(df: DataFrame, price: float = K.PRICE_FS, server_hour: float = 0.68) -> DataFrame:
    return df.withColumn("dollars", price * F.col("w") * (F.col("runtime_s") - F.col("startup_s")) + F.col("runtime_s") * server_hour / 3600)


def all_designs(params: DataFrame, load_mode: str = "per_worker") -> DataFrame:
    """The parameters priced on each infrastructure: adds infra, the terms, runtime_s, dollars and simulated."""
    frames = {
        "fs": cost_fs(runtime_fs(params, load_mode=load_mode)), "fs_cache": cost_fs(runtime_fs(params, "cache_t3_medium", load_mode).withColumn("startup_s", F.greatest("startup_s", F.lit(K.CACHE_STARTUP_S))).withColumn("runtime_s", F.col("startup_s") + F.col("load_s") + F.col("comm_s") + F.col("comp_s")), K.CACHE_HOUR),
        "vc": cost_vc(runtime_vc(params, load_mode=load_mode)), "hp": cost_hp(runtime_hp(params, load_mode=load_mode)),
    }
    return reduce(DataFrame.unionByName, (f.withColumn("infra", F.lit(n)) for n, f in frames.items())).withColumn("simulated", F.lit(True))


def runtime_bounds(params: DataFrame, infra: str = "fs", **options) -> DataFrame:
    """Adds low_s and high_s: the run time with every constant at its favourable and unfavourable end."""
    run = {"fs": runtime_fs, "vc": runtime_vc}[infra]
    keys = ["task", "algo", "w"]
    low = run(params, bound=-1, **options).select(*keys, F.col("runtime_s").alias("low_s"))
    high = run(params, bound=1, **options).select(*keys, F.col("runtime_s").alias("high_s"))
    return run(params, **options).join(low, keys).join(high, keys)


def regime(params: DataFrame, load_mode: str = "per_worker") -> DataFrame:
    """(task, algo, w, fs_s, vc_s, winner, cheaper, crossover, comm_share): which of the two wins, and where that changes."""
    f = cost_fs(runtime_fs(params, load_mode=load_mode)).select("task", "algo", "w", F.col("runtime_s").alias("fs_s"), F.col("dollars").alias("fs_d"), (F.col("comm_s") / F.col("runtime_s")).alias("comm_share"))
    v = cost_vc(runtime_vc(params, load_mode=load_mode)).select("task", "algo", "w", F.col("runtime_s").alias("vc_s"), F.col("dollars").alias("vc_d"))
    both = f.join(v, ["task", "algo", "w"])
    by = Window.partitionBy("task", "algo").orderBy("w")
    winner = F.when(F.col("fs_s") <= F.col("vc_s"), "fs").otherwise("vc")
    both = both.withColumn("winner", winner).withColumn("cheaper", F.when(F.col("fs_d") <= F.col("vc_d"), "fs").otherwise("vc"))
    return both.withColumn("crossover", F.coalesce(F.lag("winner").over(by) != F.col("winner"), F.lit(False))).select("task", "algo", "w", "fs_s", "vc_s", "winner", "cheaper", "crossover", "comm_share")


def pareto(df: DataFrame, keys: list[str], time: str = "runtime_s", cost: str = "dollars") -> DataFrame:
    """The rows that no other row of their keys beats on time and cost; equal rows stay together.

    In the order of time, a row stays if its cost is under all costs of smaller
    times, and least among those of its own time.
    """
    by = Window.partitionBy(*keys).orderBy(time)
    earlier = F.min(cost).over(Window.partitionBy(*keys).orderBy("_t").rangeBetween(Window.unboundedPreceding, -1))
    ranked = df.withColumn("_t", F.dense_rank().over(by))
    least = F.min(cost).over(Window.partitionBy(*keys, "_t"))
    return ranked.withColumn("_e", earlier).withColumn("_m", least).where((F.col(cost) == F.col("_m")) & (F.col("_e").isNull() | (F.col(cost) < F.col("_e")))).drop("_t", "_e", "_m")


def fit_scaling(epochs: DataFrame) -> DataFrame:
    """(task, algo, w, f_w): epochs at w over epochs at the smallest w of a task."""
    by = Window.partitionBy("task", "algo").orderBy("w").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return epochs.withColumn("f_w", F.col("epochs") / F.first("epochs").over(by)).select("task", "algo", "w", "f_w")


def prediction_error(df: DataFrame, predicted: str, actual: str) -> DataFrame:
    return df.withColumn("abs_error", F.abs(F.col(predicted) - F.col(actual))).withColumn("rel_error", F.col("abs_error") / F.abs(F.col(actual)))
