"""Registered queries: one per method, variant, measure, workload or operator."""

from __future__ import annotations

import math
import uuid
from collections.abc import Callable
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from trainscape.functions import arrow
from trainscape.functions.hashing import portable_hash
from trainscape.functions.losses import HingeLoss, LogisticLoss
from trainscape.operators import asynchronous, clustering, features, joins, linear, metrics, nets, partition, patterns, views
from trainscape.plans import analytic, channels, constants, designs, estimator, experiments, lifetime, pipeline, tasks, whatif
from trainscape.plans.job import JobSpec, LrSchedule, StopRule
from trainscape.sources.tables import cut_lineage, load, shared_folder
from trainscape.streaming import retrain

KEYS, DENSE = tasks.KEYS, tasks.DENSE
#: A channel study: run, workers, model MB, rounds, seconds without communication.
RUNS = [("lr_w10", 10, 0.000224, 10.0, 30.0), ("lr_w50", 50, 0.000224, 10.0, 20.0), ("km10_w50", 50, 0.00224, 40.0, 60.0), ("km1000_w50", 50, 0.224, 40.0, 180.0), ("conv_w10", 10, 12.0, 600.0, 900.0), ("conv_w50", 50, 12.0, 600.0, 400.0)]
DELAYS, ASYNC_STEPS = {0: 1.0, 1: 1.5, 2: 2.25, 3: 4.0}, 3
#: The event type whose mean value is the seconds that one worker computes in a round of a run.
RUN_TYPES = {"lr": "view", "km10": "click", "km1000": "purchase", "conv": "signup"}
GRID_RATES = [0.1, 0.5, 1.0]


def rounded(df: DataFrame, *cols: str, digits: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(c, digits) + F.lit(0.0) for c in cols})


def model_frame(spark: SparkSession, w: np.ndarray) -> DataFrame:
    return rounded(spark.createDataFrame([(i, float(v)) for i, v in enumerate(w)], "coord int, value double"), "value")


def dense28_features(spark, sf_dir):
    df, _ = tasks.task_dense28(spark, sf_dir)
    return df.select(*KEYS, *DENSE, "y", "split", "worker", "batch")


def split_balance(spark, sf_dir):
    df, _ = tasks.task_dense28(spark, sf_dir)
    return df.groupBy("split", "worker").agg(F.count("*").alias("n"), F.sum((F.col("y") > 0).cast("long")).alias("positive"))


def exact_partition(spark, sf_dir):
    e = load(spark, sf_dir, "events", ["event_id"])
    return partition.assign_workers(e, ["event_id"], 7, "exact").groupBy("worker").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))


def minmax_scale(spark, sf_dir):
    cols = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
    l = load(spark, sf_dir, "lineitem", KEYS + cols)
    return rounded(features.minmax_apply(l, features.minmax_fit(l, cols), cols), *cols)


def tfidf_text(spark, sf_dir):
    x, _, _ = tasks.task_text(spark, sf_dir)
    return rounded(x, "value")


def ctr_crosses(spark, sf_dir):
    x, y, _ = tasks.task_ctr(spark, sf_dir)
    return x.groupBy("coord").agg(F.count("*").alias("n")).select("coord", "n")


def wide_outer_stats(spark, sf_dir):
    x, _ = tasks.task_wide4096(spark, sf_dir)
    return rounded(x.select(F.posexplode("x").alias("coord", "v")).groupBy("coord").agg(F.avg("v").alias("mean"), F.count("*").alias("n")), "mean")


def grid_classes(spark, sf_dir):
    df, _ = tasks.task_grid10(spark, sf_dir)
    return df.groupBy("y", "split").agg(F.count("*").alias("n"))


def _fit(spark, sf_dir, job: JobSpec) -> DataFrame:
    df, _ = tasks.task_dense28(spark, sf_dir, job.workers, job.batches)
    return model_frame(spark, linear.train(df, DENSE, [*KEYS, "l_shipdate"], job).w)


def lr_gd(spark, sf_dir):
    return _fit(spark, sf_dir, JobSpec("ga", lr=LrSchedule(0.5), workers=1, batches=1, stop=StopRule(max_rounds=4)))


def lr_ga_sgd(spark, sf_dir):
    return _fit(spark, sf_dir, JobSpec("ga", lr=LrSchedule(0.3), workers=4, batches=4, stop=StopRule(max_rounds=1)))


def svm_ga_sgd(spark, sf_dir):
    return _fit(spark, sf_dir, JobSpec("ga", HingeLoss(l2=0.01), LrSchedule(0.2), 4, 4, stop=StopRule(max_rounds=1)))


def lr_ma_sgd(spark, sf_dir):
    return _fit(spark, sf_dir, JobSpec("ma", lr=LrSchedule(0.3), workers=4, batches=3, stop=StopRule(max_rounds=2)))


def lr_ma_sync2(spark, sf_dir):
    return _fit(spark, sf_dir, JobSpec("ma", lr=LrSchedule(0.3), workers=4, batches=4, sync_every=2, weighted=False, stop=StopRule(max_rounds=1)))


def lr_admm(spark, sf_dir):
    return _fit(spark, sf_dir, JobSpec("admm", lr=LrSchedule(0.3), workers=3, batches=1, rho=0.1, inner_epochs=2, stop=StopRule(max_rounds=2)))


def kmeans_em(spark, sf_dir):
    df, _ = tasks.task_dense28(spark, sf_dir)
    feats = DENSE[:4]
    c, losses = clustering.em_kmeans(df.select(*KEYS, "l_shipdate", *feats), feats, 3, [*KEYS, "l_shipdate"], iters=3)
    rows = [(i, j, float(v), float(losses[-1])) for i, r in enumerate(c) for j, v in enumerate(r)]
    return rounded(spark.createDataFrame(rows, "cluster int, coord int, value double, loss double"), "value", "loss")


def _embedding_stats(spark, sf_dir, workers=8):
    e = partition.assign_workers(load(spark, sf_dir, "embeddings", ["vec_id", "embedding"]), ["vec_id"], workers)
    return e.select("worker", F.posexplode(F.col("embedding").cast("array<double>")).alias("coord", "value"), F.lit(1.0).alias("weight"))


def allreduce_mean(spark, sf_dir):
    return rounded(patterns.all_reduce(_embedding_stats(spark, sf_dir)), "value")


def scatter_reduce_mean(spark, sf_dir):
    return rounded(patterns.scatter_reduce(_embedding_stats(spark, sf_dir)), "value")


def tree_reduce_mean(spark, sf_dir):
    return rounded(patterns.tree_reduce(_embedding_stats(spark, sf_dir), 3), "value")


def two_phase_missing(spark, sf_dir):
    """Days are rounds, users mod 8 the workers: who has not delivered on a day?"""
    e = load(spark, sf_dir, "events", ["ts", "user_id", "event_type"]).where("event_type = 'error'")
    hourly = e.select(F.day("ts").alias("epoch"), F.hour("ts").alias("iteration"), F.pmod("user_id", F.lit(8)).alias("partition")).distinct()
    return patterns.missing_workers(hourly, spark.range(8).select(F.col("id").alias("worker")))


def grid_search_lr(spark, sf_dir):
    df, _ = tasks.task_dense28(spark, sf_dir, 1, 2)
    return rounded(linear.tune_lr(df, DENSE, LogisticLoss(), GRID_RATES, 1, 2).select("lr", "loss"), "loss")


def pipeline_end_to_end(spark, sf_dir):
    examples = pipeline.preprocess(spark, sf_dir, batches=2)
    _, measured = pipeline.run_pipeline(examples, GRID_RATES, 1, 2)
    return rounded(measured.select("n", "accuracy"), "accuracy")


def tag_imbalance(spark, sf_dir):
    d = load(spark, sf_dir, "documents", ["doc_id", "lang", "source"]).withColumn("tags", F.array("lang", "source"))
    parts = [partition.class_balance(features.binarize_tag(d, "tags", t), "target").select(F.lit(t).alias("tag"), "label", "n", "share") for t in ("de", "src0", "fr")]
    return rounded(reduce(DataFrame.unionByName, parts), "share")


def auc_toxic(spark, sf_dir):
    d = load(spark, sf_dir, "documents", ["doc_id", "n_chars"]).join(load(spark, sf_dir, "labels", ["doc_id", "toxic"]), "doc_id")
    return rounded(metrics.auc(d, "toxic", "n_chars"), "auc")


def class_metrics(spark, sf_dir):
    df, _ = tasks.task_dense28(spark, sf_dir)
    w = np.array([math.cos(j + 1) for j in range(28)] + [0.39])
    return rounded(metrics.class_metrics(linear.predict(df.where("split = 'validation'"), w, DENSE, KEYS)), "accuracy", "precision", "recall", "f1")


def stability_lag(spark, sf_dir):
    daily = load(spark, sf_dir, "events").groupBy("event_type", F.day("ts").alias("round")).agg(F.avg("value").alias("loss"))
    return rounded(metrics.stability(daily, ["event_type"]), "mean_change", "variance")


def table_constants(spark, sf_dir):
    return constants.constants(spark)


def rpc_table(spark, sf_dir):
    return rounded(metrics.rpc_breakdown(spark), "update_share")


def startup_curve(spark, sf_dir):
    w = spark.createDataFrame([(x,) for x in (1, 10, 30, 50, 75, 100, 150, 200, 300)], "w int")
    both = [w.select("w", F.lit(i).alias("infra"), constants.startup(F.col("w"), i).alias("seconds"), constants.extrapolated(F.col("w")).alias("extrapolated")) for i in ("fs", "vc")]
    return rounded(both[0].unionByName(both[1]), "seconds")


_TERMS = ["startup_s", "load_s", "comm_s", "comp_s", "runtime_s"]


def runtime_fs_grid(spark, sf_dir):
    p = analytic.parameter_grid(spark)
    return rounded(analytic.cost_fs(analytic.runtime_fs(p)).select("task", "algo", "w", *_TERMS, "dollars"), *_TERMS, "dollars")


def runtime_vc_grid(spark, sf_dir):
    p = analytic.parameter_grid(spark)
    return rounded(analytic.cost_vc(analytic.runtime_vc(p, load_mode="per_worker")).select("task", "algo", "w", *_TERMS, "dollars"), *_TERMS, "dollars")


def runtime_hp_grid(spark, sf_dir):
    p = analytic.parameter_grid(spark)
    return rounded(analytic.cost_hp(analytic.runtime_hp(p)).select("task", "algo", "w", *_TERMS, "dollars"), *_TERMS, "dollars")


def runtime_bounds(spark, sf_dir):
    return rounded(analytic.runtime_bounds(analytic.parameter_grid(spark)).select("task", "algo", "w", "low_s", "runtime_s", "high_s"), "low_s", "runtime_s", "high_s")


def cost_grid_pareto(spark, sf_dir):
    d = analytic.all_designs(analytic.parameter_grid(spark, tasks.event_grid(spark, sf_dir))).select("task", "algo", "infra", "w", F.round("runtime_s", 6).alias("runtime_s"), F.round("dollars", 6).alias("dollars"))
    return analytic.pareto(d, ["task"])


def regime_crossover(spark, sf_dir):
    return rounded(analytic.regime(analytic.parameter_grid(spark)), "fs_s", "vc_s", "comm_share")


def whatif_fast_link(spark, sf_dir):
    return rounded(whatif.whatif_fast_link(analytic.parameter_grid(spark)), "runtime_s", "dollars")


def whatif_hot_data(spark, sf_dir):
    return rounded(whatif.whatif_hot_data(analytic.parameter_grid(spark)), "load_s", "runtime_s")


def multitenant_peaks(spark, sf_dir):
    return rounded(whatif.peaks(load(spark, sf_dir, "events")), "mean_jobs", "peakiness")


def multitenant_policies(spark, sf_dir):
    e = load(spark, sf_dir, "events")
    jobs = e.select(F.col("event_id").alias("job_id"), F.unix_timestamp(F.col("ts").cast("timestamp")).cast("double").alias("at"), F.col("value").alias("work_s"))
    return rounded(reduce(DataFrame.unionByName, (whatif.provision(jobs, p) for p in ("fs", "vm", "reserved"))), "mean_latency_s", "dollars", "utilisation")


def design_space(spark, sf_dir):
    users = load(spark, sf_dir, "events", ["user_id"]).agg(F.count_distinct("user_id").alias("users"))
    each = spark.createDataFrame([(m, a, b, designs.NUMBERS[m]) for m, a, b, _ in designs.MODELS], "model string, convex boolean, clusters boolean, numbers long")
    return designs.enumerate_designs(spark, models=each.crossJoin(users).select("model", "convex", "clusters", (F.col("users") * F.col("numbers") * 8).alias("m_bytes")))


def _timeline(spark, sf_dir, w=10, rounds=3):
    """A timeline of w workers by infrastructure: the model's terms, and a millisecond of computing for each unit of the events' values; users are dealt to workers, days to rounds."""
    p = analytic.parameter_grid(spark, [("lr_dense", "admm", 8000.0, 0.000224, float(rounds), 90.0, 0.0)], [w])
    both = analytic.runtime_fs(p, load_mode="per_worker").withColumn("infra", F.lit("fs")).unionByName(analytic.runtime_vc(p, load_mode="per_worker").withColumn("infra", F.lit("vc")))
    long = both.selectExpr("infra", "stack(3, 'startup', startup_s, 'load', load_s, 'communicate', comm_s) as (phase, s)")
    each = long.crossJoin(spark.range(w).withColumnRenamed("id", "worker")).crossJoin(spark.range(rounds).select(F.col("id").cast("int").alias("round")))
    once = F.col("phase").isin("startup", "load")
    seconds = F.when(once & (F.col("round") > 0), 0.0).otherwise(F.when(once, F.col("s")).otherwise(F.col("s") / rounds))
    fixed = each.select("infra", "round", "worker", "phase", F.lit(0.0).alias("sim_start"), seconds.alias("sim_end"))
    e = load(spark, sf_dir, "events", ["ts", "user_id", "value"])
    computed = e.groupBy(F.pmod(F.day("ts"), F.lit(rounds)).alias("round"), F.pmod("user_id", F.lit(w)).alias("worker")).agg((F.sum("value") / 1000.0).alias("sim_end"))
    computed = computed.select(F.explode(F.array(F.lit("fs"), F.lit("vc"))).alias("infra"), "round", "worker", F.lit("compute").alias("phase"), F.lit(0.0).alias("sim_start"), "sim_end")
    return fixed.unionByName(computed)


def breakdown_phases(spark, sf_dir):
    return rounded(metrics.breakdown(_timeline(spark, sf_dir)), "seconds")


def speedup_sanity(spark, sf_dir):
    p = analytic.parameter_grid(spark, workers=[1, 10])
    t = analytic.all_designs(p).where("infra in ('fs', 'vc') and algo = 'admm'").select(F.col("task").alias("model"), "infra", "w", (F.col("runtime_s") - F.col("startup_s")).alias("seconds"))
    return rounded(metrics.speedup(t), "seconds", "speedup")


def channel_relative(spark, sf_dir):
    """A run for each event type and 10 or 50 workers."""
    sized = tasks.event_work(spark, sf_dir).crossJoin(spark.createDataFrame([(10,), (50,)], "w int"))
    runs = sized.select(F.concat("task", F.lit("_w"), "w").alias("run"), "w", (F.col("users") * 8.0 / 1e6).alias("m_mb"), F.lit(10.0).alias("rounds"), F.col("mean_s").alias("base_s"))
    cols = ["comm_s", "time_s", "dollars", "slowdown", "relative_cost"]
    return rounded(channels.relative(channels.replay(runs, ["object_store", "cache_mt", "cache_st", "kv_db", "vm_ps"])).select("run", "channel", *cols), *cols)


def pattern_ledger(spark, sf_dir):
    stats = _embedding_stats(spark, sf_dir, 8).groupBy("worker", "coord").agg(F.avg("value").alias("value"))
    combos = [("all_reduce", "object_store"), ("scatter_reduce", "object_store"), ("scatter_reduce", "direct"), ("all_reduce", "vm_ps")]
    return reduce(DataFrame.unionByName, (patterns.ledger(stats, p, c, 8).select(F.lit(p).alias("pattern"), F.lit(c).alias("channel"), "worker", "n_msgs", "n_bytes") for p, c in combos))


def async_schedule(spark, sf_dir):
    """Four workers share the users; a worker's delay is the mean value of their events."""
    e = load(spark, sf_dir, "events", ["user_id", "value"]).where("user_id is not null and value is not null")
    delays = e.groupBy(F.pmod("user_id", F.lit(4)).cast("int").alias("worker")).agg(F.round(F.avg("value"), 6).alias("delay"))
    return asynchronous.async_schedule(spark, delays, ASYNC_STEPS)


def lr_async(spark, sf_dir):
    df, _ = tasks.task_dense28(spark, sf_dir, len(DELAYS), 2)
    w, _ = asynchronous.async_train(df, DENSE, LogisticLoss(), 0.5, asynchronous.async_schedule(spark, DELAYS, ASYNC_STEPS), 2)
    return model_frame(spark, w)


def lr_async_add(spark, sf_dir):
    df, _ = tasks.task_dense28(spark, sf_dir, len(DELAYS), 2)
    w, _ = asynchronous.async_train(df, DENSE, LogisticLoss(), 0.5, asynchronous.async_schedule(spark, DELAYS, ASYNC_STEPS), 2, overwrite=False)
    return model_frame(spark, w)


def lifetime_restarts(spark, sf_dir):
    """Orders of a customer stand for steps of a worker; the price gives the seconds."""
    o = load(spark, sf_dir, "orders", ["o_custkey", "o_orderkey", "o_totalprice"])
    trace = o.select(F.col("o_custkey").alias("worker"), F.col("o_orderkey").alias("step"), (F.col("o_totalprice") / 1000.0).alias("seconds"))
    return rounded(lifetime.apply_lifetime(trace, 900.0, 60.0), "seconds", "until_s")


def epoch_estimate(spark, sf_dir):
    df, _ = tasks.task_dense28(spark, sf_dir, 4, 4)
    job = JobSpec("ma", lr=LrSchedule(0.3), workers=4, batches=4, stop=StopRule(0.665, 8))
    epochs, result = estimator.estimate_epochs(df, DENSE, [*KEYS, "l_shipdate"], job, 0.5)
    return spark.createDataFrame([(epochs, h["round"], float(h["loss"])) for h in result.history], "estimate int, round int, loss double")


def _net_steps(spark, sf_dir, net):
    df, _ = tasks.task_grid10(spark, sf_dir)
    _, losses = nets.net_ga(df.where("split = 'train'").persist(), net, 0.5, 3)
    return rounded(spark.createDataFrame(list(enumerate(losses)), "step int, loss double"), "loss")


def conv_net_steps(spark, sf_dir):
    return _net_steps(spark, sf_dir, nets.SeparableConvNet(width=4, blocks=1))


def residual_net_steps(spark, sf_dir):
    return _net_steps(spark, sf_dir, nets.ResidualNet(width=4, blocks=1))


def conv_net_ma(spark, sf_dir):
    df, _ = tasks.task_grid10(spark, sf_dir, 4)
    _, losses = nets.net_ma(df.where("split = 'train'"), nets.SeparableConvNet(width=4, blocks=1), 0.1, 2, 4)
    return rounded(spark.createDataFrame(list(enumerate(losses)), "step int, loss double"), "loss")


def sparse_lr_step(spark, sf_dir):
    """Two steps of logistic regression on hashed text weights, the model in coordinate form."""
    x, y, meta = tasks.task_text(spark, sf_dir)
    x = x.persist()
    model = spark.createDataFrame([], "coord int, value double")
    for _ in range(2):
        model = linear.sparse_step(model, linear.sparse_gradient(x, y, model, LogisticLoss(), "doc_id", meta.dims), 1.0)
    return rounded(model, "value")


def _two_sparse_steps(x, y, dims, loss, key):
    x = x.persist()
    model = x.sparkSession.createDataFrame([], "coord int, value double")
    for _ in range(2):
        model = cut_lineage(linear.sparse_step(model, linear.sparse_gradient(x, y, model, loss, key, dims), 1.0))
    x.unpersist()
    return rounded(model, "value")


def sparse_svm_step(spark, sf_dir):
    x, y, meta = tasks.task_text(spark, sf_dir)
    return _two_sparse_steps(x, y, meta.dims, HingeLoss(), "doc_id")


def ctr_lr_step(spark, sf_dir):
    x, y, meta = tasks.task_ctr(spark, sf_dir)
    return _two_sparse_steps(x, y, meta.dims, LogisticLoss(), "event_id")


def sparse_kmeans(spark, sf_dir):
    """One step of three clusters on text weights, from the first three documents."""
    x, _, _ = tasks.task_text(spark, sf_dir)
    x = x.persist()
    first = x.select("doc_id").distinct().orderBy("doc_id").limit(3).select("doc_id", (F.row_number().over(Window.orderBy("doc_id")) - 1).alias("cluster"))
    start = x.join(F.broadcast(first), "doc_id").select("cluster", "coord", "value").persist()
    _, at = clustering.sparse_em_step(x, start, "doc_id")
    return at.groupBy("cluster").agg(F.count("*").alias("n"), (F.round(F.sum("d"), 6) + F.lit(0.0)).alias("loss"))


def wide_lr_steps(spark, sf_dir):
    df, meta = tasks.task_wide4096(spark, sf_dir)
    w, _ = linear.block_train(df.where("split = 'train'").persist(), LogisticLoss(), 1.0, 2, meta.dims)
    return model_frame(spark, w)


def wide_svm_steps(spark, sf_dir):
    df, meta = tasks.task_wide4096(spark, sf_dir)
    _, losses = linear.block_train(df.where("split = 'train'").persist(), HingeLoss(), 1.0, 3, meta.dims)
    return rounded(spark.createDataFrame(list(enumerate(losses)), "step int, loss double"), "loss")


def wide_kmeans(spark, sf_dir):
    df, _ = tasks.task_wide4096(spark, sf_dir)
    df = df.persist()
    c = np.array([r["x"] for r in df.orderBy("vec_id").limit(10).collect()])
    losses = []
    for _ in range(2):
        c, loss, _ = clustering.block_em_step(df, c)
        losses.append(loss)
    return rounded(spark.createDataFrame(list(enumerate(losses)), "step int, loss double"), "loss")


def algorithm_comparison(spark, sf_dir):
    return experiments.compare_algorithms(spark, sf_dir)


def sync_protocols(spark, sf_dir):
    return experiments.sync_against_async(spark, sf_dir, DELAYS, ASYNC_STEPS, 2)


def systems_end_to_end(spark, sf_dir):
    return experiments.end_to_end(spark, sf_dir, rounds=1)


def presets_end_to_end(spark, sf_dir):
    return rounded(experiments.presets_end_to_end(spark, sf_dir), "first_loss", "last_loss", "seconds", "dollars")


def sync_protocols_net(spark, sf_dir):
    return rounded(experiments.sync_against_async_net(spark, sf_dir, {0: 1.0, 1: 1.5, 2: 4.0}, 2), "loss")


def model_validation(spark, sf_dir):
    e = partition.assign_workers(load(spark, sf_dir, "events", ["event_id"]), ["event_id"], 10)
    held = {r["worker"]: r["count"] for r in e.groupBy("worker").count().collect()}  # one row a worker
    return rounded(experiments.validate_model(spark, (1, 10), held=held), "predicted_s", "replayed_s", "abs_error", "rel_error")


def pattern_table(spark, sf_dir):
    sizes = [(r["task"], 10, r["users"] * 8.0 / 1e6) for r in tasks.event_work(spark, sf_dir).collect()]  # one row an event type
    return rounded(experiments.pattern_table(spark, sizes), "all_reduce_s", "scatter_reduce_s")


def cache_threads(spark, sf_dir):
    sizes = tasks.event_work(spark, sf_dir).select("task", (F.col("users") * 8.0 / 1e6).alias("m_mb"))
    return rounded(experiments.single_against_multi_thread(spark, sizes), "ratio")


def rpc_servers(spark, sf_dir):
    return rounded(experiments.rpc_servers(spark), "seconds")


def memory_failures(spark, sf_dir):
    """Activations take 400 bytes for each character of the longest text."""
    longest = load(spark, sf_dir, "documents", ["text"]).agg(F.max(F.length("text"))).first()[0] or 0
    return experiments.memory_failures(spark, activation_bytes=400 * longest)


def workers_sweep(spark, sf_dir):
    return rounded(experiments.workers_sweep(spark).select("task", "algo", "infra", "w", "runtime_s", "dollars"), "runtime_s", "dollars")


def instance_scatter(spark, sf_dir):
    return rounded(experiments.instance_scatter(spark, base=tasks.event_grid(spark, sf_dir)), "runtime_s", "dollars")


def payload_reduce(spark, sf_dir):
    """The mean quantity of each part, suppliers dealt to ten workers, per thousand parts."""
    l = load(spark, sf_dir, "lineitem", ["l_partkey", "l_suppkey", "l_quantity"])
    m = patterns.scatter_reduce(l.select(F.pmod("l_suppkey", F.lit(10)).alias("worker"), F.col("l_partkey").alias("coord"), F.col("l_quantity").alias("value"), F.lit(1.0).alias("weight")))
    return rounded(m.groupBy(F.floor(F.col("coord") / 1000).alias("block")).agg(F.sum("value").alias("value"), F.count("*").alias("n")), "value")


def retrain_stream(spark, sf_dir):
    folder = f"{shared_folder(spark).rstrip('/')}/retrain-{uuid.uuid4().hex}"
    trainer = retrain.Retrainer(steps=2, spark=spark, folder=f"{folder}/model")
    trainer.run(retrain.event_stream(spark, f"{sf_dir}/events.parque*", 10_000), f"{folder}/stream")
    rows = [(n, i, v) for _, n, w in trainer.history[-1:] for i, v in enumerate(w)]
    return rounded(spark.createDataFrame(rows, "n long, coord int, value double"), "value")


def session_arrivals(spark, sf_dir):
    s = retrain.sessions(load(spark, sf_dir, "events"), "6 hours")
    return rounded(s.select("user_id", F.unix_micros("start").alias("start_us"), F.unix_micros("end").alias("end_us"), "n", "value"), "value", digits=4)


def price_as_of(spark, sf_dir):
    """Purchases with the user's latest view value before them."""
    e = load(spark, sf_dir, "events", ["event_id", "user_id", "ts", "event_type", "value"])
    views = e.where("event_type = 'view'").select("user_id", F.col("ts").alias("seen"), F.col("value").alias("last_view"))
    return joins.as_of(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), views, ["user_id"], "ts", "seen", "last_view").select("event_id", "user_id", "last_view")


def job_overlaps(spark, sf_dir):
    """How many other runs overlap each signup's run of its value in minutes."""
    at = F.unix_micros(F.col("ts").cast("timestamp")) / 1e6
    j = load(spark, sf_dir, "events").where("event_type = 'signup'").select("event_id", at.alias("a"), (at + F.col("value") * 60).alias("b"))
    other = j.select(F.col("event_id").alias("other"), F.col("a").alias("c"), F.col("b").alias("d"))
    pairs = joins.overlaps(j, other, ("a", "b"), ("c", "d"), 3600.0).where("event_id <> other")
    return pairs.groupBy("event_id").agg(F.count("*").alias("n"))


def estimate_sample(spark, sf_dir):
    o = load(spark, sf_dir, "orders", ["o_orderkey"])
    return partition.sample_hash(o, ["o_orderkey"], 0.1)


def hash_buckets(spark, sf_dir):
    o = load(spark, sf_dir, "orders", ["o_orderkey"])
    return o.groupBy(F.pmod(portable_hash("worker", "o_orderkey"), F.lit(16)).alias("bucket")).agg(F.count("*").alias("n"))


def estimator_study(spark, sf_dir):
    return rounded(experiments.estimator_study(spark, sf_dir, most=9), "threshold", "predicted_s", "actual_s", "rel_error")


def scaling_study(spark, sf_dir):
    return rounded(experiments.scaling_study(spark, sf_dir, most=6), "f_w")


def model_against_spark(spark, sf_dir):
    return experiments.model_against_spark(spark, sf_dir)


def workers_in_training(spark, sf_dir):
    return rounded(experiments.workers_in_training(spark, sf_dir, (8, 300)), "loss")


def averaging_on_networks(spark, sf_dir):
    return rounded(experiments.averaging_on_networks(spark, sf_dir), "loss")


def published_channels(spark, sf_dir):
    cols = ["slowdown", "slowdown_error", "relative_cost", "cost_error"]
    named = spark.createDataFrame([(*r[:4], RUN_TYPES[r[0].split("_")[0]]) for r in RUNS], "run string, w int, m_mb double, rounds double, task string")
    runs = named.join(tasks.event_work(spark, sf_dir), "task").select("run", "w", "m_mb", "rounds", (F.col("rounds") * F.col("mean_s") / F.col("w")).alias("base_s"))
    return rounded(experiments.published_channels(spark, runs), *cols)


def published_patterns(spark, sf_dir):
    return rounded(experiments.published_patterns(spark), "ratio", "published_ratio", "all_reduce_error", "scatter_reduce_error")


def published_pipelines(spark, sf_dir):
    return rounded(experiments.published_pipelines(spark), "dollars", "error")


def time_to_loss(spark, sf_dir):
    """Days are rounds, the daily mean value the loss: rounds and seconds until it is under its mean over all days."""
    e = load(spark, sf_dir, "events", ["ts", "value"])
    daily = e.groupBy(F.dayofyear("ts").alias("round")).agg(F.avg("value").alias("loss"), F.sum("value").alias("sim_end"))
    threshold = daily.agg(F.avg("loss")).first()[0]
    rounds = metrics.rounds_to(daily, threshold or 0.0)
    return rounded(metrics.time_to(daily, daily, threshold or 0.0).crossJoin(rounds), "seconds", digits=4)


def event_ranks(spark, sf_dir):
    e = load(spark, sf_dir, "events", ["event_id", "event_type", "value"])
    return rounded(views.ranks(e.where("event_type = 'purchase'"), ["event_type"], [F.col("value").desc(), F.col("event_id")]).select("event_id", "row_no", "rank", "dense", "tile", "percent", "cume"), "percent", "cume")


def event_cube(spark, sf_dir):
    e = load(spark, sf_dir, "events", ["ts", "event_type", "value"]).withColumn("hour", F.hour("ts"))
    return rounded(views.cube_counts(e, ["event_type", "hour"], "value"), "total", digits=2)


def event_sets(spark, sf_dir):
    e = load(spark, sf_dir, "events", ["ts", "event_type"]).withColumn("hour", F.hour("ts"))
    return views.set_counts(e, [["event_type"], ["hour"]])


def daily_types(spark, sf_dir):
    """Counts by day and type, made wide and long again."""
    e = load(spark, sf_dir, "events", ["ts", "event_type"]).withColumn("day", F.day("ts"))
    names = ["click", "error", "purchase", "signup", "view"]
    return views.lengthen(views.widen(e, "day", "event_type", names), "day", names, "event_type", "n")


def user_sets(spark, sf_dir):
    """How many users buy, click, do both, only click, or either."""
    e = load(spark, sf_dir, "events", ["user_id", "event_type"])
    buy, click = (e.where(F.col("event_type") == t).select("user_id") for t in ("purchase", "click"))
    parts = {"both": buy.intersect(click), "only_click": click.exceptAll(buy).distinct().subtract(buy), "either": buy.union(click).distinct()}
    return reduce(DataFrame.unionByName, (df.agg(F.count("*").alias("n")).select(F.lit(k).alias("kind"), "n") for k, df in parts.items()))


def user_balance(spark, sf_dir):
    """Clicks and purchases of each user by a full outer join."""
    e = load(spark, sf_dir, "events", ["user_id", "event_type"])
    clicks, buys = (e.where(F.col("event_type") == t).groupBy("user_id").agg(F.count("*").alias(t)) for t in ("click", "purchase"))
    return clicks.join(buys, "user_id", "full_outer").na.fill(0)


def dearest_purchases(spark, sf_dir):
    e = load(spark, sf_dir, "events", ["event_id", "user_id", "event_type", "value"])
    return views.latest_each(e, e.where("event_type = 'purchase'"), "user_id", [F.col("value").desc(), F.col("event_id")], 2, ["event_id", "value"])


def value_change(spark, sf_dir):
    e = load(spark, sf_dir, "events", ["ts", "event_type", "value"])
    return rounded(views.compare_groups(e.where("day(ts) % 2 = 0"), e.where("day(ts) % 2 = 1"), "event_type", "value"), "change")


def sketch_errors(spark, sf_dir):
    """Whether approximate distinct counts, medians and histograms keep their bounds against exact ones."""
    e = load(spark, sf_dir, "events", ["user_id", "event_type", "value"])
    exact = e.groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count("*").alias("n"), F.percentile("value", 0.49).alias("low"), F.percentile("value", 0.51).alias("high"))
    both = views.sketches(e, "event_type", "user_id", "value").join(exact, "event_type")
    heights = F.aggregate("bars", F.lit(0.0), lambda a, b: a + b["y"])
    return both.select("event_type", "users", (F.abs(F.col("distinct") - F.col("users")) <= 0.1 * F.col("users") + 1).alias("distinct_ok"), F.col("median").between(F.col("low"), F.col("high")).alias("median_ok"), (F.abs(heights - F.col("n")) < 0.5).alias("bars_ok"))


def join_ways(spark, sf_dir):
    """Rows of one join by each hinted strategy."""
    o, c = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]), load(spark, sf_dir, "customer", ["c_custkey"]).withColumnRenamed("c_custkey", "o_custkey")
    return reduce(DataFrame.unionByName, (views.hinted(o, c, "o_custkey", way).agg(F.count("*").alias("n")).select(F.lit(way).alias("way"), "n") for way in ("broadcast", "merge", "shuffle_hash")))


def vector_products(spark, sf_dir):
    """x.x and the sum of 2x + x of each embedding by Arrow functions."""
    e = load(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    x = F.col("embedding").cast("array<double>")
    total = F.aggregate(arrow.vec_axpy(2.0, x, x), F.lit(0.0), lambda a, b: a + b)
    return rounded(e.select("vec_id", arrow.vec_dot(x, x).alias("dot"), total.alias("total")), "dot", "total", digits=5)


def label_means(spark, sf_dir):
    e = load(spark, sf_dir, "embeddings", ["label", "embedding"])
    return rounded(e.groupBy("label").agg(arrow.vec_avg(F.col("embedding").cast("array<double>")).alias("v")).select("label", F.posexplode("v").alias("coord", "value")), "value", digits=5)


def rate_stream(spark, sf_dir):
    """One micro-batch of the deterministic rate source through a stateless stream: (residue, n)."""
    folder, out = f"{shared_folder(spark).rstrip('/')}/rate-{uuid.uuid4().hex}", []
    stream = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", 100).option("numPartitions", 2).load().select((F.col("value") % 7).alias("residue"))

    def take(batch: DataFrame, _: int) -> None:
        out.extend((r["residue"], r["n"]) for r in batch.groupBy("residue").agg(F.count("*").alias("n")).collect())

    stream.writeStream.foreachBatch(take).option("checkpointLocation", folder).trigger(availableNow=True).start().awaitTermination()
    return spark.createDataFrame(out, "residue long, n long")


def invocation_plan(spark, sf_dir):
    """One worker per file of events, from the scan's own metadata; names without folders."""
    files = views.list_partitions(spark.read.parquet(f"{sf_dir}/events.parquet"))
    return files.select(F.col("worker").cast("int").alias("worker"), F.element_at(F.split("path", "/"), -1).alias("name"), "attempt")


_NAMES = """dense28_features split_balance exact_partition minmax_scale tfidf_text ctr_crosses wide_outer_stats grid_classes lr_gd lr_ga_sgd svm_ga_sgd lr_ma_sgd lr_ma_sync2
lr_admm kmeans_em allreduce_mean scatter_reduce_mean tree_reduce_mean two_phase_missing grid_search_lr pipeline_end_to_end tag_imbalance auc_toxic class_metrics stability_lag
table_constants rpc_table startup_curve runtime_fs_grid runtime_vc_grid runtime_hp_grid runtime_bounds cost_grid_pareto regime_crossover whatif_fast_link whatif_hot_data
multitenant_peaks multitenant_policies design_space breakdown_phases speedup_sanity channel_relative pattern_ledger async_schedule lr_async lr_async_add lifetime_restarts
epoch_estimate conv_net_steps residual_net_steps conv_net_ma sparse_lr_step sparse_svm_step ctr_lr_step sparse_kmeans wide_lr_steps wide_svm_steps wide_kmeans
algorithm_comparison sync_protocols systems_end_to_end model_validation pattern_table cache_threads rpc_servers memory_failures workers_sweep instance_scatter payload_reduce retrain_stream session_arrivals price_as_of job_overlaps estimate_sample hash_buckets
estimator_study scaling_study model_against_spark workers_in_training averaging_on_networks published_channels published_patterns published_pipelines time_to_loss event_ranks event_cube event_sets
daily_types user_sets user_balance dearest_purchases value_change sketch_errors join_ways vector_products label_means rate_stream invocation_plan presets_end_to_end sync_protocols_net""".split()

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {n: globals()[n] for n in _NAMES}
