"""The experiment workloads on the given tables, one function each; cloud seconds and dollars in them are simulated."""

from __future__ import annotations

import time
from dataclasses import replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.functions.losses import HingeLoss, LogisticLoss
from trainscape.operators import asynchronous, clustering, linear, metrics, nets, patterns
from trainscape.operators.partition import assign_batches, assign_workers, sample_hash
from trainscape.plans import analytic, channels, constants, estimator, pricing, tasks
from trainscape.plans.job import TRACE, JobSpec, LrSchedule, NonConvexModelError, OutOfWorkerMemory, StopRule, check_memory
from trainscape.sources.tables import forget, settings

FIT_KEYS = [*tasks.KEYS, "l_shipdate"]
TRACE_NAMES = [c.split()[0] for c in TRACE.split(", ")]


#: Losses of the comparisons and the validation loss that ends their runs.
MODELS = {"lr": (LogisticLoss(), 0.66), "svm": (HingeLoss(l2=0.001), 0.86)}
#: Rounds after which a comparison ends a run that does not come to its loss.
MOST_ROUNDS = 1000


def compare_algorithms(spark: SparkSession, sf_dir: str, workers: int = 10, batches: int = 10, rates: tuple[float, ...] = (0.05,), limits: dict[str, int] | None = None, models: tuple[str, ...] = ("lr", "svm")) -> DataFrame:
    """(model, algorithm, w, lr, status, syncs, scans, loss): synchronisations and data scans of GA, MA and ADMM until a validation loss.

    Without limits only a run that does not come to its loss in MOST_ROUNDS is ended.
    """
    base = tasks.dense28_kept(spark, sf_dir)
    df = linear.pack(tasks.task_dense28(spark, sf_dir, workers, batches, kept=base)[0], tasks.DENSE)
    rows = []
    for model in models:
        loss, threshold = MODELS[model]
        for algorithm, most in (limits or dict.fromkeys(("ga", "ma", "admm"), MOST_ROUNDS)).items():
            for lr in rates:
                r = linear.train(df, tasks.DENSE, FIT_KEYS, JobSpec(algorithm, loss, LrSchedule(lr), workers, batches, stop=StopRule(threshold, most)))
                n = r.history[-1]["round"]
                rows.append((model, algorithm, workers, lr, r.status, n * (batches if algorithm == "ga" else 1), n * (10 if algorithm == "admm" else 1), float(r.history[-1]["loss"])))
    df.unpersist()
    forget(base)
    return spark.createDataFrame(rows, "model string, algorithm string, w int, lr double, status string, syncs int, scans int, loss double")


def workers_in_training(spark: SparkSession, sf_dir: str, workers: tuple[int, ...] = (8, 30, 100, 300), lr: float = 0.3) -> DataFrame:
    """(algorithm, w, loss, n_bytes): one real pass of model averaging and ADMM by the number of logical workers; what they send grows with it."""
    rows, base = [], tasks.dense28_kept(spark, sf_dir)
    for w in workers:
        df = linear.pack(tasks.task_dense28(spark, sf_dir, w, 4, kept=base)[0], tasks.DENSE)
        for algorithm in ("ma", "admm"):
            r = linear.train(df, tasks.DENSE, FIT_KEYS, JobSpec(algorithm, lr=LrSchedule(lr), workers=w, batches=4, inner_epochs=2, stop=StopRule(max_rounds=1)))
            rows.append((algorithm, w, float(r.history[-1]["loss"]), sum(t[8] for t in r.trace_rows if t[5] == "communicate")))
        df.unpersist()
    forget(base)
    return spark.createDataFrame(rows, "algorithm string, w int, loss double, n_bytes long")


def averaging_on_networks(spark: SparkSession, sf_dir: str, workers: int = 4, rounds: int = 4, lr: float = 0.3) -> DataFrame:
    """(algorithm, round, loss, rises): gradient against model averaging of the convolutional net; rises counts the rounds in which the loss grew."""
    df, _ = tasks.task_grid10(spark, sf_dir, workers)
    net, rows = nets.SeparableConvNet(width=4, blocks=1), []
    fit = df.where("split = 'train'").persist()
    for name, losses in (("ga", nets.net_ga(fit, net, lr, rounds)[1]), ("ma", nets.net_ma(fit, net, lr, rounds, workers, 4)[1])):
        rows += [(name, i, float(v), sum(b > a for a, b in zip(losses[:i], losses[1 : i + 1]))) for i, v in enumerate(losses)]
    fit.unpersist()
    return spark.createDataFrame(rows, "algorithm string, round int, loss double, rises int")


def published_channels(spark: SparkSession, runs: list[tuple] | DataFrame) -> DataFrame:
    """The channel replay beside the published table: (run, channel, slowdown, published_slowdown, slowdown_error, relative_cost, published_cost, cost_error); errors are relative."""
    ours = channel_table(spark, runs).select("run", "channel", F.round("slowdown", 6).alias("slowdown"), F.round("relative_cost", 6).alias("relative_cost"))
    theirs = spark.createDataFrame(constants.PUBLISHED_CHANNELS, "run string, channel string, published_slowdown double, published_cost double")
    both = theirs.join(ours, ["run", "channel"])
    return both.withColumn("slowdown_error", F.col("slowdown") / F.col("published_slowdown") - 1).withColumn("cost_error", F.col("relative_cost") / F.col("published_cost") - 1)


def published_patterns(spark: SparkSession) -> DataFrame:
    """(model, ratio, published_ratio, all_reduce_error, scatter_reduce_error): one round of our formula beside the published seconds."""
    theirs = spark.createDataFrame(constants.PUBLISHED_PATTERNS, "model string, a double, s double")
    both = pattern_table(spark).join(theirs, "model")
    return both.select("model", (F.col("all_reduce_s") / F.col("scatter_reduce_s")).alias("ratio"), (F.col("a") / F.col("s")).alias("published_ratio"), (F.col("all_reduce_s") / F.col("a") - 1).alias("all_reduce_error"), (F.col("scatter_reduce_s") / F.col("s") - 1).alias("scatter_reduce_error"))


def published_pipelines(spark: SparkSession) -> DataFrame:
    """(infra, model, dollars, published_dollars, error): the published seconds at the implied unit prices."""
    t = spark.createDataFrame(constants.PUBLISHED_PIPELINES, "infra string, model string, seconds double, accuracy double, published_dollars double")
    dollars = F.col("seconds") * 100.0 * F.when(F.col("infra") == "fs", constants.PRICE_FS).otherwise(constants.PRICE_VC)
    return t.select("infra", "model", dollars.alias("dollars"), "published_dollars", (dollars / F.col("published_dollars") - 1).alias("error"))


def estimator_study(spark: SparkSession, sf_dir: str, fraction: float = 0.1, most: int = 30, workers: int = 4, batches: int = 4) -> DataFrame:
    """(task, model, algorithm, threshold, estimated, actual, predicted_s, actual_s, rel_error): epochs to a loss from a hashed
    sample and from all rows, and the function workers' run time that the analytic model gives for each.

    The dense task runs model averaging and ADMM, the wide one mini-batch descent on whole vectors (ADMM of its blocks is not
    built). The threshold is the loss of the whole data after a third of `most` rounds, so that it can be reached.
    """
    rows, base = [], tasks.dense28_kept(spark, sf_dir)
    df, _ = tasks.task_dense28(spark, sf_dir, workers, batches, kept=base)
    sample, df = (linear.pack(part, tasks.DENSE) for part in (sample_hash(df, FIT_KEYS, fraction), df))
    for model, (loss, _) in MODELS.items():
        for algorithm, rounds in (("ma", most), ("admm", max(3, most // 5))):
            job = JobSpec(algorithm, loss, LrSchedule(0.2), workers, batches, inner_epochs=2, stop=StopRule(max_rounds=rounds))
            losses = [h["loss"] for h in linear.train(df, tasks.DENSE, FIT_KEYS, job).history]
            threshold = losses[len(losses) // 3]
            estimated, _ = estimator.sample_epochs(sample, tasks.DENSE, FIT_KEYS, replace(job, stop=StopRule(threshold, rounds)))
            actual = next(i + 1 for i, v in enumerate(losses) if v <= threshold)
            rows.append(("dense28", model, algorithm, float(threshold), estimated, actual, 8000.0, 0.000224, 90.0))
    df.unpersist()
    sample.unpersist()
    forget(base)
    wide, meta = tasks.task_wide4096(spark, sf_dir)
    wide = assign_batches(wide.where("split = 'train'"), ["vec_id"], batches).persist()
    for model, (loss, _) in MODELS.items():
        _, losses = linear.block_train(wide, loss, 0.5, most, meta.dims, batches)
        smooth = [float(np.mean(losses[i : i + batches])) for i in range(0, len(losses) - batches + 1, batches)]
        threshold = smooth[len(smooth) // 2]
        _, sampled = linear.block_train(sample_hash(wide, ["vec_id"], fraction), loss, 0.5, most, meta.dims, batches)
        epochs = [float(np.mean(sampled[i : i + batches])) for i in range(0, len(sampled) - batches + 1, batches)]
        estimated = next((i + 1 for i, v in enumerate(epochs) if v <= threshold), None)
        actual = next(i + 1 for i, v in enumerate(smooth) if v <= threshold)
        rows.append(("wide4096", model, "sgd", threshold, estimated, actual, 110_000.0, 0.032768, 2000.0))
    wide.unpersist()
    out = []
    for task, model, algorithm, threshold, estimated, actual, s_mb, m_mb, compute in rows:
        seconds = [estimator.predict_runtime(spark, n, 10, s_mb, m_mb, compute).first()["runtime_s"] if n else None for n in (estimated, actual)]
        out.append((task, model, algorithm, threshold, estimated, actual, *seconds))
    frame = spark.createDataFrame(out, "task string, model string, algorithm string, threshold double, estimated int, actual int, predicted_s double, actual_s double")
    return analytic.prediction_error(frame, "predicted_s", "actual_s").drop("abs_error")


def scaling_study(spark: SparkSession, sf_dir: str, workers: tuple[int, ...] = (1, 4, 8), lr: float = 0.3, most: int = 12) -> DataFrame:
    """(task, algo, w, f_w): how the epochs of model averaging to one loss grow with the number of workers, from real runs."""
    rows, threshold, base = [], None, tasks.dense28_kept(spark, sf_dir)
    for w in workers:
        df = linear.pack(tasks.task_dense28(spark, sf_dir, w, 4, kept=base)[0], tasks.DENSE)
        losses = [h["loss"] for h in linear.train(df, tasks.DENSE, FIT_KEYS, JobSpec("ma", lr=LrSchedule(lr), workers=w, batches=4, stop=StopRule(max_rounds=most))).history]
        df.unpersist()
        threshold = threshold or losses[most // 3]
        rows.append(("dense28", "ma", w, next((i + 1 for i, v in enumerate(losses) if v <= threshold), most)))
    forget(base)
    return analytic.fit_scaling(spark.createDataFrame(rows, "task string, algo string, w int, epochs int"))


def model_against_spark(spark: SparkSession, sf_dir: str, epochs: tuple[int, ...] = (1, 2, 3, 6), workers: int = 4) -> DataFrame:
    """(epochs, fitted, predicted_s, real_s, abs_error, rel_error): start-up and seconds an epoch are fitted to the shortest and the
    longest of this machine's real runs, and tell the others. Real times differ between runs."""
    base = tasks.dense28_kept(spark, sf_dir)
    df = linear.pack(tasks.task_dense28(spark, sf_dir, workers, 4, kept=base)[0], tasks.DENSE)
    real = []
    linear.train(df, tasks.DENSE, FIT_KEYS, JobSpec("ma", lr=LrSchedule(0.3), workers=workers, batches=4, stop=StopRule(max_rounds=1)))
    for e in epochs:
        began = time.monotonic()
        linear.train(df, tasks.DENSE, FIT_KEYS, JobSpec("ma", lr=LrSchedule(0.3), workers=workers, batches=4, stop=StopRule(max_rounds=e)))
        real.append(time.monotonic() - began)
    df.unpersist()
    forget(base)
    each = (real[-1] - real[0]) / (epochs[-1] - epochs[0])
    rows = [(e, e in (epochs[0], epochs[-1]), float(real[0] + each * (e - epochs[0])), float(t)) for e, t in zip(epochs, real)]
    return analytic.prediction_error(spark.createDataFrame(rows, "epochs int, fitted boolean, predicted_s double, real_s double"), "predicted_s", "real_s")


def admm_on_network_is_refused() -> bool:
    try:
        JobSpec("admm", nets.SeparableConvNet()).validate()
    except NonConvexModelError:
        return True
    return False


def channel_table(spark: SparkSession, runs: list[tuple] | DataFrame) -> DataFrame:
    """Slowdown and relative cost of each channel against the object store, for runs (run, w, m_mb, rounds, base_s)."""
    return channels.relative(channels.replay(runs if isinstance(runs, DataFrame) else spark.createDataFrame(runs, "run string, w int, m_mb double, rounds double, base_s double")))


def single_against_multi_thread(spark: SparkSession, sizes: DataFrame | None = None) -> DataFrame:
    """(m_mb, w, ratio), or the columns of sizes with w and ratio, of a single-threaded cache's round to a multi-threaded one's."""
    grid = spark.createDataFrame([(m, w) for m in (0.000224, 12.0, 89.0) for w in (2, 10, 50)], "m_mb double, w int")
    if sizes is not None:
        grid = sizes.crossJoin(spark.createDataFrame([(2,), (10,), (50,)], "w int"))
    st, mt = (channels.round_seconds(channels.CHANNELS[c], F.col("m_mb"), F.col("w")) for c in ("cache_st", "cache_mt"))
    return grid.withColumn("ratio", st / mt)


def rpc_servers(spark: SparkSession, servers: tuple[int, ...] = (1, 2, 3, 4, 5)) -> DataFrame:
    """(servers, seconds): 75 MB from ten functions; more servers share the wire (10 Gb/s), not the (de)serialisation and update."""
    transfer, update = next((t, u) for n, gb, s, t, u, _, _ in constants.RPC_TRIALS if (n, gb, s) == (10, 3, "c5.4xlarge"))
    wire = 10 * 75.0 / 1250.0
    return spark.createDataFrame([(k, transfer - wire + wire / k + update) for k in servers], "servers int, seconds double")


def pattern_table(spark: SparkSession, sizes: list[tuple] | None = None) -> DataFrame:
    """(model, w, m_mb, all_reduce_s, scatter_reduce_s): seconds a round through the object store."""
    b, l = constants.constant("bandwidth", "object_store"), constants.constant("latency", "object_store")
    rows = []
    for model, w, m in sizes or [("lr", 50, 0.000224), ("conv", 10, 12.0), ("residual", 10, 89.0)]:
        cost = {}
        for p in ("all_reduce", "scatter_reduce"):
            n, parts = patterns.transfers(p, "object_store", w)
            cost[p] = n * (m / parts / b + l)
        rows.append((model, w, m, cost["all_reduce"], cost["scatter_reduce"]))
    return spark.createDataFrame(rows, "model string, w int, m_mb double, all_reduce_s double, scatter_reduce_s double")


def pattern_timings(spark: SparkSession, n_bytes: int = 12_000_000, workers: int = 10) -> DataFrame:
    """(pattern, seconds): real seconds of this machine's Spark for one reduction of a made payload."""
    stats = patterns.payload(spark, n_bytes, workers).persist()
    stats.count()
    rows = []
    for p in patterns.PATTERNS:
        began = time.monotonic()
        patterns.reduce_with(p, stats, workers).write.format("noop").mode("overwrite").save()
        rows.append((p, time.monotonic() - began))
    stats.unpersist()
    return spark.createDataFrame(rows, "pattern string, seconds double")


def sync_against_async(spark: SparkSession, sf_dir: str, delays: dict[int, float], steps: int, batches: int = 4, lr: float = 0.5) -> DataFrame:
    """(protocol, step, sim_s, loss): synchronous rounds last as long as the slowest worker, asynchronous writes come as they end."""
    df, _ = tasks.task_dense28(spark, sf_dir, len(delays), batches)
    df = df.persist()
    w, events = asynchronous.async_train(df, tasks.DENSE, LogisticLoss(), lr, asynchronous.async_schedule(spark, delays, steps), batches)
    rows = [("async", i, float(e["write_at"]), float(e["loss"])) for i, e in enumerate(events)]
    v = np.zeros(len(tasks.DENSE) + 1)
    fit, held = df.where("split = 'train'"), df.where("split = 'validation'")
    for s in range(steps):
        g, _ = linear.gradient(fit.where(F.col("batch") == s % batches), v, tasks.DENSE, LogisticLoss())
        v = v - lr / np.sqrt(s // batches + 1) * g
        rows.append(("bsp", s, (s + 1) * max(delays.values()), float(linear.eval_loss(held, v, tasks.DENSE, LogisticLoss()))))
    df.unpersist()
    return spark.createDataFrame(rows, "protocol string, step int, sim_s double, loss double")


def end_to_end(spark: SparkSession, sf_dir: str, row_s: float = 2e-5, data_mb: float = 8000.0, workers: int = 10, rounds: int = 3) -> DataFrame:
    """(infra, phase, seconds) with totals: one real ADMM run replayed on each system."""
    df, _ = tasks.task_dense28(spark, sf_dir, workers, 10)
    trace = linear.train(df, tasks.DENSE, FIT_KEYS, JobSpec("admm", lr=LrSchedule(0.1), workers=workers, inner_epochs=2, stop=StopRule(max_rounds=rounds))).trace(spark).persist()
    systems = [pricing.Profile.fs(), pricing.Profile.fs("cache_mt"), pricing.Profile.vc(), pricing.Profile.hybrid()]
    timeline = reduce(DataFrame.unionByName, (pricing.replay(trace, p, workers, row_s, data_mb) for p in systems))
    return metrics.breakdown(timeline)


def counted_trace(rows: DataFrame, run_id: str, keys: list[str], workers: int, rounds: int, row_bytes: int, model_bytes: int) -> list[tuple]:
    """The trace of `rounds` passes over all rows by hashed workers: their counted rows, and a model's messages and bytes in each round."""
    n_msgs, parts = patterns.transfers("all_reduce", "object_store", workers)
    held = {r["worker"]: r["count"] for r in assign_workers(rows.select(*keys), keys, workers).groupBy("worker").count().collect()}  # one row a worker
    trace = [(run_id, 0, 0, 0, j, "load", n, 1, n * row_bytes) for j, n in sorted(held.items())]
    for r in range(1, rounds + 1):
        trace += [t for j, n in sorted(held.items()) for t in ((run_id, r, r, 0, j, "compute", n, 0, 0), (run_id, r, r, 0, j, "communicate", 0, n_msgs, n_msgs * model_bytes // parts))]
    return trace


def run_presets(spark: SparkSession, sf_dir: str, names: tuple[str, ...], rounds: int) -> dict[str, tuple[list[float], list[tuple]]]:
    """(losses, trace) of each preset's first rounds on all training rows of its task, with the preset's workers and clusters.

    The presets of a task share its rows, which are made once."""
    kinds = {"dense28": _dense_presets, "text47k": _text_presets, "ctr1m": _ctr_presets, "wide4096": _vector_presets, "grid10": _vector_presets}
    out = {}
    for task in dict.fromkeys(tasks.preset(n)["task"] for n in names):
        out |= kinds[task](spark, sf_dir, [n for n in names if tasks.preset(n)["task"] == task], rounds)
    return out


def _loss_of(name: str):
    return {"hinge": HingeLoss()}.get(tasks.preset(name)["model"], LogisticLoss())


def _dense_presets(spark: SparkSession, sf_dir: str, names: list[str], rounds: int) -> dict[str, tuple[list[float], list[tuple]]]:
    out, base = {}, tasks.dense28_kept(spark, sf_dir)
    for workers in dict.fromkeys(tasks.preset(n)["workers"] for n in names):
        df, _ = tasks.task_dense28(spark, sf_dir, workers, 4, kept=base)
        blocks = linear.pack(df, tasks.DENSE)
        for name in (n for n in names if tasks.preset(n)["workers"] == workers):
            if k := tasks.preset(name)["k"]:
                fit = df.where("split = 'train'")
                first = [r[0] for r in fit.select(*FIT_KEYS).orderBy(*FIT_KEYS).limit(k).collect()]  # only the rows of these keys are scaled again
                at = clustering.first_rows(fit.where(F.col(FIT_KEYS[0]).isin(first)), tasks.DENSE, k, FIT_KEYS)
                own, losses = blocks.where("fit"), []
                for _ in range(rounds):
                    at, value, _ = clustering.packed_em_step(own, at)
                    losses.append(float(value))
                out[name] = losses, counted_trace(fit, name, FIT_KEYS, workers, rounds, 8 * 28, 8 * 29 * k)
            else:
                run = linear.train(blocks, tasks.DENSE, FIT_KEYS, JobSpec("ma", _loss_of(name), LrSchedule(0.3), workers, 4, stop=StopRule(max_rounds=rounds)))
                out[name] = [float(h["loss"]) for h in run.history], run.trace_rows
        blocks.unpersist()
    forget(base)
    return out


def _text_presets(spark: SparkSession, sf_dir: str, names: list[str], rounds: int) -> dict[str, tuple[list[float], list[tuple]]]:
    x, y, meta = tasks.task_text(spark, sf_dir)
    x, y, key, out = x.persist(), y.persist(), "doc_id", {}
    fit = y.where("split = 'train'")
    rows = linear.sparse_rows(x, fit, key).persist()
    for name in names:
        _, _, _, workers, _, k = tasks.PRESETS[name]
        if k:
            first, losses = x.select(key).distinct().orderBy(key).limit(k).collect(), []
            of = spark.createDataFrame([(r[key], i) for i, r in enumerate(first)], f"{key} long, cluster int")
            model = x.join(F.broadcast(of), key).select("cluster", "coord", "value")  # k rows
            for _ in range(rounds):
                model, at = clustering.sparse_em_step(x, model, key)
                losses.append(float(at.agg(F.avg("d")).first()[0] or 0.0))
        else:
            losses = linear.sparse_train(rows, _loss_of(name), 1.0, rounds, meta.dims)
        out[name] = losses, counted_trace(y if k else fit, name, [key], workers, rounds, 12 * 64, 8 * meta.dims * (k or 1))
    for df in (rows, x, y):
        df.unpersist()
    return out


def _ctr_presets(spark: SparkSession, sf_dir: str, names: list[str], rounds: int) -> dict[str, tuple[list[float], list[tuple]]]:
    rows, meta = tasks.ctr_rows(spark, sf_dir)
    fit, out = rows.where("split = 'train'").select("event_id", "y", "coords", "vals").persist(), {}
    for name in names:
        losses = linear.sparse_train(fit, _loss_of(name), 1.0, rounds, meta.dims)
        out[name] = losses, counted_trace(fit, name, ["event_id"], tasks.preset(name)["workers"], rounds, 12 * 64, 8 * meta.dims)
    fit.unpersist()
    return out


def _vector_presets(spark: SparkSession, sf_dir: str, names: list[str], rounds: int) -> dict[str, tuple[list[float], list[tuple]]]:
    wide = tasks.preset(names[0])["task"] == "wide4096"
    df, meta = tasks.task_wide4096(spark, sf_dir) if wide else tasks.task_grid10(spark, sf_dir, tasks.preset(names[0])["workers"])
    fit, out = df.where("split = 'train'").persist(), {}
    for name in names:
        _, model, _, workers, _, k = tasks.PRESETS[name]
        if k:
            at, losses = np.array([r["x"] for r in fit.orderBy("vec_id").limit(k).collect()], float), []
            for _ in range(rounds):
                at, value, _ = clustering.block_em_step(fit, at)
                losses.append(float(value))
            size = 8 * at.size
        elif wide:
            losses, size = linear.block_train(fit, _loss_of(name), 0.5, rounds, meta.dims)[1], 8 * meta.dims
        else:
            net = nets.SeparableConvNet(width=4, blocks=1) if model == "separable_conv" else nets.ResidualNet(width=4, blocks=1)
            losses, size = nets.net_ga(fit, net, 0.3, rounds)[1], 8 * net.size
        out[name] = [float(v) for v in losses], counted_trace(fit, name, ["vec_id"], workers, rounds, 8 * meta.dims, size)
    fit.unpersist()
    return out


def presets_end_to_end(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = tuple(tasks.PRESETS), rounds: int = 2, row_s: float = 2e-5, data_mb: float = 8000.0, hadoop: tuple[float, float] = (1.5, 180.0)) -> DataFrame:
    """(preset, infra, rounds, first_loss, last_loss, seconds, dollars): every preset trained for some rounds and its trace replayed on each system.

    Networks run on machines with GPUs of two generations too, the others on
    the parameter-server system of a Hadoop stack, whose slowdown and start-up
    are not published: `hadoop` is our choice of both.
    """
    out = []
    for name, (losses, rows) in run_presets(spark, sf_dir, names, rounds).items():
        trace = spark.createDataFrame(pa.Table.from_pylist([dict(zip(TRACE_NAMES, r)) for r in rows]), TRACE)  # a local table
        w = tasks.preset(name)["workers"]
        deep = tasks.preset(name)["task"] == "grid10"
        more = [pricing.Profile.vc_gpu("older"), pricing.Profile.vc_gpu("newer")] if deep else [pricing.Profile.hadoop_ps(*hadoop)]
        systems = (pricing.Profile.fs(), pricing.Profile.vc(), pricing.Profile.hybrid(), *more)
        with settings(spark, {"spark.sql.shuffle.partitions": "1"}):  # some rows a worker and round
            costs = reduce(DataFrame.unionByName, (pricing.dollar_cost(pricing.replay(trace, system, w, row_s, data_mb), system, w) for system in systems)).collect()
        out += [(name, cost["infra"], len(losses), losses[0], losses[-1], float(cost["seconds"]), float(cost["dollars"])) for cost in costs]
    return spark.createDataFrame(out, "preset string, infra string, rounds int, first_loss double, last_loss double, seconds double, dollars double")


def sync_against_async_net(spark: SparkSession, sf_dir: str, delays: dict[int, float], steps: int, lr: float = 0.3) -> DataFrame:
    """(protocol, step, sim_s, loss) of the convolutional net: rounds of all workers against overwriting writes in the order they end."""
    df, _ = tasks.task_grid10(spark, sf_dir, len(delays))
    fit, net = df.where("split = 'train'").persist(), nets.SeparableConvNet(width=4, blocks=1)
    versions, rows = {0: net.init()}, []
    for e in asynchronous.async_schedule(spark, delays, steps).orderBy("version_written").collect():  # workers times steps
        base = versions[e["version_read"]]
        g, _, _ = nets.net_gradient(fit.where(F.col("worker") == e["worker"]), net, base)
        versions[e["version_written"]] = base - lr / np.sqrt(e["step"] + 1) * g
        rows.append(("async", e["version_written"] - 1, float(e["write_at"]), float(nets.net_gradient(fit, net, versions[e["version_written"]])[1])))
    w = net.init()
    for s in range(steps):
        w = w - lr / np.sqrt(s + 1) * nets.net_gradient(fit, net, w)[0]
        rows.append(("bsp", s, (s + 1) * max(delays.values()), float(nets.net_gradient(fit, net, w)[1])))
    fit.unpersist()
    return spark.createDataFrame(rows, "protocol string, step int, sim_s double, loss double")


def workers_sweep(spark: SparkSession) -> DataFrame:
    """(task, infra, w, runtime_s, dollars, on_front): time and cost over the number of workers, with the best trade-offs marked."""
    d = analytic.all_designs(analytic.parameter_grid(spark)).select("task", "algo", "infra", "w", "runtime_s", "dollars")
    front = analytic.pareto(d, ["task"]).select("task", "algo", "infra", "w", F.lit(True).alias("front"))
    return d.join(front, ["task", "algo", "infra", "w"], "left").withColumn("on_front", F.coalesce("front", F.lit(False))).drop("front")


def instance_scatter(spark: SparkSession, rates: tuple[float, ...] = (0.01, 0.05, 0.1), base: DataFrame | None = None) -> DataFrame:
    """([task,] infra, lr, w, runtime_s, dollars) of the image task by machine kind; smaller rates need more epochs."""
    named = [] if base is None else ["task"]
    base = analytic.parameter_grid(spark, [t for t in analytic.TASKS if t[0] == "conv_image"] if base is None else base, [10])
    kinds = {"fs": analytic.cost_fs(analytic.runtime_fs(base)), "vc": analytic.cost_vc(analytic.runtime_vc(base)), "vc_c5": analytic.cost_vc(analytic.runtime_vc(base, "net_c5_large"), 2 * constants.PRICE_VC), "gpu": analytic.cost_vc(analytic.runtime_vc(base.withColumn("compute_s", F.col("compute_s") / 8), "net_c5_large"), constants.GPU_HOUR / 3600)}
    out = reduce(DataFrame.unionByName, (k.withColumn("infra", F.lit(n)) for n, k in kinds.items()))
    lr = spark.createDataFrame([(r, 0.1 / r) for r in rates], "lr double, more double")
    run = F.col("startup_s") + F.col("load_s") + (F.col("comm_s") + F.col("comp_s")) * F.col("more")
    return out.crossJoin(F.broadcast(lr)).select(*named, "infra", "lr", "w", run.alias("runtime_s"), (F.col("dollars") * run / F.col("runtime_s")).alias("dollars"))


def validate_model(spark: SparkSession, epochs: tuple[int, ...] = (1, 5, 10, 25, 50, 100), workers: int = 10, held: dict[int, int] | None = None) -> DataFrame:
    """(epochs, predicted_s, replayed_s, abs_error, rel_error): the closed form against a replayed trace of the same epochs, load per worker.

    `held` has the rows of each worker, else 1,000; an epoch of all rows takes a worker 90 s.
    """
    held = held or {j: 1000 for j in range(workers)}
    row_s = 90.0 / sum(held.values())
    rows = []
    profile = pricing.Profile.fs()
    n, parts = patterns.transfers("scatter_reduce", "object_store", workers)
    for e in epochs:
        trace = [("v", 0, 0, 0, j, "load", held.get(j, 0), 1, 0) for j in range(workers)]
        trace += [("v", r, r, 0, j, p, k, m, b) for r in range(1, e + 1) for j in range(workers) for p, k, m, b in (("compute", held.get(j, 0), 0, 0), ("communicate", 0, n, int(np.ceil(n * 224 / parts))))]
        t = spark.createDataFrame(trace, "run_id string, round int, epoch int, batch int, worker int, phase string, rows long, n_msgs long, n_bytes long")
        replayed = pricing.replay(t, profile, workers, row_s, 8000.0).agg(F.max("sim_end")).first()[0]
        p = analytic.parameter_grid(spark, [("v", "x", 8000.0, 0.000224, float(e), 90.0, 0.0)], [workers])
        rows.append((e, analytic.runtime_fs(p, load_mode="per_worker").first()["runtime_s"], replayed))
    return analytic.prediction_error(spark.createDataFrame(rows, "epochs int, predicted_s double, replayed_s double"), "predicted_s", "replayed_s")


def batch_sweep(spark: SparkSession, sf_dir: str, batches: tuple[int, ...] = (2, 4, 8), passes: int = 1, lr: float = 0.3) -> DataFrame:
    """(batches, loss) of model averaging with batches of different sizes."""
    rows = []
    for b in batches:
        df, _ = tasks.task_dense28(spark, sf_dir, 4, b)
        r = linear.train(df, tasks.DENSE, FIT_KEYS, JobSpec("ma", lr=LrSchedule(lr), workers=4, batches=b, stop=StopRule(max_rounds=passes)))
        rows.append((b, float(r.history[-1]["loss"])))
    return spark.createDataFrame(rows, "batches int, loss double")


def memory_failures(spark: SparkSession, batches: tuple[int, ...] = (32, 64), activation_bytes: int = 40_000_000) -> DataFrame:
    """(infra, batch, fits) of the 89 MB residual network."""
    rows = []
    for infra, gb in (("fs", 3.0), ("vc", 64.0)):
        for b in batches:
            try:
                check_memory(89_000_000, b, activation_bytes, gb)
                rows.append((infra, b, True))
            except OutOfWorkerMemory:
                rows.append((infra, b, False))
    return spark.createDataFrame(rows, "infra string, batch int, fits boolean")
