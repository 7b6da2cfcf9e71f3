"""Cost and accuracy measures over predictions, histories and traces."""

from __future__ import annotations

import math

from pyspark.ml.feature import Bucketizer
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def class_metrics(pred: DataFrame, label: str = "y", hat: str = "label_hat", positive: float = 1.0) -> DataFrame:
    """One row: n, accuracy, precision, recall, f1 (0 where undefined)."""
    is_, said = F.col(label) == positive, F.col(hat) == positive
    c = pred.agg(F.count("*").alias("n"), F.avg((F.col(label) == F.col(hat)).cast("double")).alias("accuracy"), F.sum((is_ & said).cast("long")).alias("tp"), F.sum((~is_ & said).cast("long")).alias("fp"), F.sum((is_ & ~said).cast("long")).alias("fn"))
    ratio = lambda a, b: F.when(b > 0, a / b).otherwise(0.0)
    c = c.withColumn("precision", ratio(F.col("tp"), F.col("tp") + F.col("fp"))).withColumn("recall", ratio(F.col("tp"), F.col("tp") + F.col("fn")))
    return c.withColumn("f1", ratio(2.0 * F.col("tp"), 2.0 * F.col("tp") + F.col("fp") + F.col("fn"))).select("n", "accuracy", "precision", "recall", "f1")


def auc(pred: DataFrame, label: str, score: str, positive=1) -> DataFrame:
    """One row: n_pos, n_neg, auc. Counts per distinct score are enough, ties count half; null without both classes.

    Ranks run over scores rounded into counts, partially aggregated; the running
    sum is taken within 1,024 ranges of about equally many distinct scores, and
    offset by the ranges before. Rows without a score are left out.
    """
    is_ = (F.col(label) == positive).cast("long")
    counts = pred.select(F.col(score).cast("double").alias("s"), is_.alias("is")).where("s is not null").groupBy("s").agg(F.sum("is").alias("p"), F.sum(1 - F.col("is")).alias("q"))
    edges = sorted({e for e in counts.approxQuantile("s", [i / 1024 for i in range(1, 1024)], 1e-4) if math.isfinite(e)})
    ranged = Bucketizer(splits=[-math.inf, *edges, math.inf], inputCol="s", outputCol="r", handleInvalid="keep").transform(counts)
    ahead = Window.orderBy("r").rowsBetween(Window.unboundedPreceding, -1)
    offsets = ranged.groupBy("r").agg(F.sum("q").alias("q")).select("r", F.coalesce(F.sum("q").over(ahead), F.lit(0)).alias("o"))
    inside = F.sum("q").over(Window.partitionBy("r").orderBy("s").rowsBetween(Window.unboundedPreceding, -1))
    below = ranged.withColumn("b", F.coalesce(inside, F.lit(0))).join(F.broadcast(offsets), "r")  # at most 1,024 rows
    total = below.agg(F.sum("p").alias("n_pos"), F.sum("q").alias("n_neg"), F.sum(F.col("p") * (F.col("b") + F.col("o") + F.col("q") / 2.0)).alias("u"))
    return total.select("n_pos", "n_neg", F.when((F.col("n_pos") > 0) & (F.col("n_neg") > 0), F.col("u") / (F.col("n_pos") * F.col("n_neg"))).alias("auc"))


def rounds_to(metrics: DataFrame, threshold: float) -> DataFrame:
    return metrics.agg(F.min(F.when(F.col("loss") <= threshold, F.col("round"))).alias("rounds"))


def time_to(metrics: DataFrame, timeline: DataFrame, threshold: float) -> DataFrame:
    """The end of the first round at the threshold: (round, seconds); no row if never."""
    first = metrics.where(F.col("loss") <= threshold).agg(F.min("round").alias("round"))
    return first.join(timeline.groupBy("round").agg(F.max("sim_end").alias("seconds")), "round")


def breakdown(timeline: DataFrame) -> DataFrame:
    """(infra, phase, seconds) with totals by rollup; a phase lasts as long as its slowest worker in each round."""
    longest = timeline.groupBy("infra", "round", "phase").agg(F.max(F.col("sim_end") - F.col("sim_start")).alias("s"))
    return longest.rollup("infra", "phase").agg(F.sum("s").alias("seconds")).where("infra is not null").select("infra", F.coalesce("phase", F.lit("total")).alias("phase"), "seconds")


def time_per(timeline: DataFrame, unit: str = "round") -> DataFrame:
    return timeline.groupBy("infra", unit).agg((F.max("sim_end") - F.min("sim_start")).alias("seconds"))


def speedup(times: DataFrame) -> DataFrame:
    """Adds speedup against the single worker of the same model and infrastructure."""
    one = times.where("w = 1").select("model", "infra", F.col("seconds").alias("_one"))
    return times.join(one, ["model", "infra"]).withColumn("speedup", F.col("_one") / F.col("seconds")).drop("_one")


def stability(metrics: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, rises, mean_change, variance) of the loss from round to round."""
    change = F.col("loss") - F.lag("loss").over(Window.partitionBy(*keys).orderBy("round"))
    return metrics.withColumn("change", change).groupBy(*keys).agg(F.sum((F.col("change") > 0).cast("int")).alias("rises"), F.avg("change").alias("mean_change"), F.var_pop("change").alias("variance"))


def rpc_breakdown(spark) -> DataFrame:
    """The parameter-server trials, one row per framework: (workers, gb, server, framework, transfer_s, update_s, update_share)."""
    from trainscape.plans.constants import RPC_TRIALS

    t = spark.createDataFrame(RPC_TRIALS, "workers int, gb int, server string, t1 double, u1 double, t2 double, u2 double")
    long = t.select("workers", "gb", "server", F.expr("stack(2, 1, t1, u1, 2, t2, u2) as (framework, transfer_s, update_s)"))
    return long.withColumn("update_share", F.col("update_s") / (F.col("update_s") + F.col("transfer_s")))
