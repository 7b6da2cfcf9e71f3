"""Asynchronous training as a deterministic simulation of reads and writes."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from trainscape.operators.linear import score


def async_schedule(spark: SparkSession, delays: dict[int, float] | DataFrame, steps: int) -> DataFrame:
    """(worker, step, read_at, write_at, version_read, version_written, staleness): every worker reads, works for its delay, writes, and repeats.

    Writes are numbered by (write_at, worker). A read sees the latest write no
    later than it, found by carrying the last version along the union of reads
    and writes, a worker's own write first. Staleness counts the writes of others
    between read and write.
    """
    workers = delays if isinstance(delays, DataFrame) else spark.createDataFrame(sorted(delays.items()), "worker int, delay double")
    events = workers.select("worker", "delay", F.explode(F.sequence(F.lit(0), F.lit(steps - 1))).alias("step"))
    events = events.select("worker", "step", (F.col("step") * F.col("delay")).alias("read_at"), ((F.col("step") + 1) * F.col("delay")).alias("write_at"))
    numbered = events.withColumn("version_written", F.row_number().over(Window.partitionBy(F.lit(1)).orderBy("write_at", "worker")))
    writes = numbered.select(F.col("write_at").alias("at"), F.lit(0).alias("kind"), "worker", "step", F.col("version_written").alias("v"))
    reads = numbered.select(F.col("read_at").alias("at"), F.lit(1).alias("kind"), "worker", "step", F.lit(None).cast("int").alias("v"))
    latest = F.max("v").over(Window.partitionBy(F.lit(1)).orderBy("at", "kind", "worker").rowsBetween(Window.unboundedPreceding, 0))
    seen = writes.unionByName(reads).withColumn("seen", F.coalesce(latest, F.lit(0))).where("kind = 1").select("worker", "step", F.col("seen").alias("version_read"))
    return numbered.join(seen, ["worker", "step"]).select("worker", "step", "read_at", "write_at", "version_read", "version_written", (F.col("version_written") - F.col("version_read") - 1).alias("staleness"))


def async_train(examples: DataFrame, feats: list[str], loss, lr: float, schedule: DataFrame, batches: int, overwrite: bool = True, decay: bool = True) -> tuple[np.ndarray, list[dict]]:
    """(model, events) of asynchronous steps.

    Each event computes the gradient of its worker's next batch at the version
    it read. With overwrite the stored model becomes that version's step, so
    work of others in between is lost; without, the step is added to the
    latest. Events whose versions are known are computed together, one scan a
    wave. The step size falls with the root of the worker's epoch.
    """
    order = [r.asDict() for r in schedule.orderBy("version_written").collect()]
    kept = examples.select("split", "worker", "batch", "y", *feats).persist()
    rows, held = kept.where("split = 'train'"), kept.where("split = 'validation'")
    versions: dict[int, np.ndarray] = {0: np.zeros(len(feats) + 1)}
    done: list[dict] = []
    while len(done) < len(order):
        wave = []
        for e in order[len(done) :]:
            if e["version_read"] not in versions:
                break
            wave.append(e)
        slope = None
        match = None
        for e in wave:
            here = (F.col("worker") == e["worker"]) & (F.col("batch") == e["step"] % batches)
            c = loss.slope(F.col("y") * score(versions[e["version_read"]], feats)) * F.col("y")
            slope = F.when(here, c) if slope is None else slope.when(here, c)
            match = F.when(here, F.lit(e["version_written"])) if match is None else match.when(here, F.lit(e["version_written"]))
        hit = rows.select(match.alias("_e"), slope.alias("_c"), *feats).where("_e is not null")
        sums = {r["_e"]: r for r in hit.groupBy("_e").agg(F.count("*").alias("_n"), *(F.sum(F.col("_c") * F.col(f)).alias(f) for f in feats), F.sum("_c").alias("_b")).collect()}
        for e in wave:
            r = sums.get(e["version_written"])
            g = np.array([r[f] for f in feats] + [r["_b"]]) / r["_n"] if r else np.zeros(len(feats) + 1)
            rate = lr / np.sqrt(e["step"] // batches + 1) if decay else lr
            base = versions[e["version_read"]] if overwrite else versions[e["version_written"] - 1]
            versions[e["version_written"]] = base - rate * g
            done.append(e)
    last = versions[len(order)] if order else versions[0]
    for e in done:
        e["w"] = versions[e["version_written"]]
    losses = held.agg(*(F.avg(loss.value(F.col("y") * score(e["w"], feats))).alias(f"l{i}") for i, e in enumerate(done))).first() if done else {}
    for i, e in enumerate(done):
        e["loss"] = losses[f"l{i}"]
    kept.unpersist()
    return last, done


def staleness_summary(schedule: DataFrame) -> DataFrame:
    """(worker, writes, mean_staleness, lost): a write with other writes in between loses them."""
    return schedule.groupBy("worker").agg(F.count("*").alias("writes"), F.avg("staleness").alias("mean_staleness"), F.sum((F.col("staleness") > 0).cast("int")).alias("lost"))
