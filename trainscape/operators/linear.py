"""Linear models by gradient averaging, model averaging and consensus ADMM."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark import BarrierTaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from trainscape.operators.partition import assign_batches
from trainscape.operators.patterns import reduce_with, transfers
from trainscape.plans.job import JobRefused, JobSpec, TooLargeToCollect, TrainResult
from trainscape.sources.tables import COLLECT_LIMIT, COMPILED, save_checkpoint, settings


def score(w: np.ndarray, feats: list[str]) -> Column:
    """The linear score as one expression; the intercept is the last weight."""
    total = F.lit(float(w[-1]))
    for c, f in zip(w[:-1], feats):
        total = total + F.lit(float(c)) * F.col(f)
    return total


def eval_loss(examples: DataFrame, w: np.ndarray, feats: list[str], loss) -> float | None:
    return examples.agg(F.avg(loss.value(F.col("y") * score(w, feats)))).first()[0]


def predict(examples: DataFrame, w: np.ndarray, feats: list[str], keys: list[str]) -> DataFrame:
    """(keys, y, score, label_hat) of each row."""
    return examples.select(*keys, "y", score(w, feats).alias("score")).withColumn("label_hat", F.when(F.col("score") >= 0, 1.0).otherwise(-1.0))


def gradient(examples: DataFrame, w: np.ndarray, feats: list[str], loss) -> tuple[np.ndarray, int]:
    """The mean gradient over the rows and their number: d + 2 sums in one partially aggregated pass."""
    c = loss.slope(F.col("y") * score(w, feats)) * F.col("y")
    row = examples.select(c.alias("_c"), *feats).agg(F.count("*").alias("n"), *(F.sum(F.col("_c") * F.col(f)).alias(f) for f in feats), F.sum("_c").alias("_b")).first()
    n = row["n"]
    g = np.array([row[f] for f in feats] + [row["_b"]], float) if n else np.zeros(len(w))
    penalty = np.append(w[:-1], 0.0) * loss.l2
    return g / max(n, 1) + penalty * (n > 0), n


#: Rows that a task packs at a time, and bytes of packed rows that a Python worker takes at once.
PACK_ROWS, PACK_BYTES = 131_072, 64 << 20


def _pack_kernel(feats: list[str]):
    """Rows into compressed blocks of one split, worker and batch each; at most PACK_ROWS rows are held."""

    def blocks(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = pa.Table.from_batches(held)
        column = lambda c: part.column(c).to_numpy()
        null = column("_null")
        x = np.vstack([np.where(null, 0.0, column(c)) for c in ("y", *feats)])
        keys = np.array([column("batch"), column("worker"), column("fit")])
        order = np.lexsort(keys[::-1])
        x, keys, null = x[:, order], keys[:, order], null[order]
        cuts = np.flatnonzero((keys[:, 1:] != keys[:, :-1]).any(0)) + 1
        for lo, hi in zip([0, *cuts], [*cuts, len(order)]):
            data = pa.compress(np.ascontiguousarray(x[:, lo:hi]).tobytes(), "zstd", asbytes=True)
            batch, worker, fit = keys[:, lo]
            yield pa.RecordBatch.from_arrays([pa.array([bool(fit)]), pa.array([int(worker)], pa.int32()), pa.array([int(batch)], pa.int32()), pa.array([hi - lo], pa.int64()), pa.array([int(null[lo:hi].sum())], pa.int64()), pa.array([data], pa.binary())], ["fit", "worker", "batch", "n", "nulls", "data"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for part in batches:
            held, n = [*held, part], n + part.num_rows
            if n >= PACK_ROWS:
                yield from blocks(held)
                held, n = [], 0
        if n:
            yield from blocks(held)

    return run


def pack(examples: DataFrame, feats: list[str], table: str | None = None) -> DataFrame:
    """(fit, worker, batch, n, nulls, data): the rows of both splits in compressed blocks, each of one worker and batch, kept for the rounds.

    A block is y and the features as doubles, column after column, so that a
    pass moves bytes instead of single values and no exchange is needed. Rows
    with a null label or feature count in n, but add nothing to a sum; nulls
    says how many they are. With a table name the blocks are written there.
    """
    null = F.lit(False)
    for c in ("y", *feats):
        null = null | F.col(c).isNull()
    rows = examples.where("split in ('train', 'validation')").select((F.col("split") == "train").alias("fit"), "worker", "batch", null.alias("_null"), *(F.col(c).cast("double").alias(c) for c in ("y", *feats)))
    blocks = rows.mapInArrow(_pack_kernel(feats), "fit boolean, worker int, batch int, n long, nulls long, data binary")
    with settings(examples.sparkSession, COMPILED):
        if table:
            blocks.write.mode("overwrite").saveAsTable(table)
            return examples.sparkSession.table(table)
        blocks = blocks.persist()
        blocks.count()
    return blocks


def _sum_kernel(models: dict[int, np.ndarray] | np.ndarray, loss, value: bool):
    """Each task's sums over its blocks: of the gradient by worker for a dict of models, or of all; or of the loss."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals: dict[int, np.ndarray] = {}
        for part in batches:
            for worker, n, nulls, data in zip(*(part.column(c) for c in ("worker", "n", "nulls", "data"))):
                j, n, nulls = worker.as_py() if isinstance(models, dict) else -1, n.as_py(), nulls.as_py()
                w = models[j] if isinstance(models, dict) else models
                rows = np.frombuffer(pa.decompress(data.as_buffer(), n * 8 * len(w), "zstd")).reshape(len(w), n)
                m = rows[0] * (w[:-1] @ rows[1:] + w[-1])
                if value:
                    own = np.array([loss.np_value(m).sum() - nulls * loss.np_value(np.zeros(1))[0], n - nulls])
                else:
                    c = loss.np_slope(m) * rows[0]
                    own = np.array([*(rows[1:] @ c), c.sum(), n])
                totals[j] = totals[j] + own if j in totals else own
        if totals:
            yield pa.RecordBatch.from_arrays([pa.array(list(totals), pa.int32()), pa.array(list(totals.values()), pa.list_(pa.float64()))], ["worker", "sums"])

    return run


def packed_sums(blocks: DataFrame, models: dict[int, np.ndarray] | np.ndarray, loss, value: bool = False) -> dict[int, np.ndarray]:
    """{worker: [gradient sums, rows]} of each worker's own model over packed blocks, or of one model under -1; with value, [loss sum, rows] of that model."""
    with settings(blocks.sparkSession, {"spark.sql.execution.arrow.maxBytesPerBatch": str(PACK_BYTES)}):
        parts = blocks.select("worker", "n", "nulls", "data").mapInArrow(_sum_kernel(models, loss, value), "worker int, sums array<double>")
        sums = parts.select("worker", F.posexplode("sums").alias("i", "v")).groupBy("worker", "i").agg(F.sum("v").alias("v"))
        out: dict[int, dict[int, float]] = {}
        for r in sums.collect():  # workers times dimensions
            out.setdefault(r["worker"], {})[r["i"]] = r["v"]
    return {j: np.array([v[i] for i in range(len(v))]) for j, v in out.items()}


def local_step(blocks: DataFrame, models: dict[int, np.ndarray], loss, lr: float, rho: float = 0.0, anchors: dict | None = None) -> dict[int, int]:
    """Moves every worker's own model, in place, by its gradient over the blocks; returns the rows of each. Workers without rows keep theirs."""
    seen = {}
    for j, s in packed_sums(blocks, models, loss).items():
        g = s[:-1] / s[-1] + loss.l2 * np.append(models[j][:-1], 0.0)
        if rho:
            g = g + rho * (models[j] - anchors[j])
        models[j], seen[j] = models[j] - lr * g, int(s[-1])
    return seen


def _local_kernel(start: dict[int, np.ndarray] | np.ndarray, feats: list[str], loss, lr: float, rho: float, anchors: dict[int, np.ndarray]):
    """SGD over each worker's batches in order; only the open batch's sums and the workers' vectors are held."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state: dict[int, list] = {}
        current, total, count = None, None, 0

        def close() -> None:
            nonlocal total, count
            if current is not None and count:
                own = state[current[0]]
                w = own[0]
                g = total / count + loss.l2 * np.append(w[:-1], 0.0)
                if rho:
                    g = g + rho * (w - anchors[current[0]])
                own[0] = w - lr * g
                own[1] += count
                own[2] += 1
            total, count = None, 0

        for part in batches:
            if not part.num_rows:
                continue
            x = np.column_stack([*(part.column(f).to_numpy(zero_copy_only=False) for f in feats), np.ones(part.num_rows)])
            y = part.column("y").to_numpy(zero_copy_only=False)
            worker, batch = (part.column(c).to_numpy(zero_copy_only=False) for c in ("worker", "batch"))
            cuts = np.flatnonzero((worker[1:] != worker[:-1]) | (batch[1:] != batch[:-1])) + 1
            for lo, hi in zip([0, *cuts], [*cuts, part.num_rows]):
                key = (int(worker[lo]), int(batch[lo]))
                if key != current:
                    close()
                    current = key
                    if key[0] not in state:
                        state[key[0]] = [np.array(start[key[0]] if isinstance(start, dict) else start, float), 0, 0]
                w = state[key[0]][0]
                m = y[lo:hi] * (x[lo:hi] @ w)
                g = (loss.np_slope(m) * y[lo:hi]) @ x[lo:hi]
                total, count = (g if total is None else total + g), count + hi - lo
        close()
        if state:
            yield pa.RecordBatch.from_arrays([pa.array(list(state), pa.int32()), pa.array([s[1] for s in state.values()], pa.int64()), pa.array([s[2] for s in state.values()], pa.int32()), pa.array([s[0] for s in state.values()], pa.list_(pa.float64()))], ["worker", "n", "steps", "w"])

    return run


def barrier_average(rows: DataFrame, w: np.ndarray, feats: list[str], loss, lr: float, tasks: int) -> np.ndarray:
    """One round of model averaging within a single stage: all tasks start together, pass over their workers' rows, exchange
    their weighted models at a barrier and leave with the same mean. The cluster needs `tasks` free cores."""
    kernel = _local_kernel(w, feats, loss, lr, 0.0, {})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros(len(w)), 0
        for out in kernel(batches):
            for own, count in zip(out.column("w").to_pylist(), out.column("n").to_pylist()):
                total, n = total + count * np.array(own), n + count
        context = BarrierTaskContext.get()
        told = [json.loads(m) for m in context.allGather(json.dumps([n, total.tolist()]))]
        if context.partitionId() == 0 and sum(c for c, _ in told):
            mean = np.sum([t for _, t in told], axis=0) / sum(c for c, _ in told)
            yield pa.RecordBatch.from_arrays([pa.array([mean], pa.list_(pa.float64()))], ["w"])

    laid = rows.select("worker", "batch", "y", *feats).repartition(tasks, "worker").sortWithinPartitions("worker", "batch")
    found = laid.mapInArrow(run, "w array<double>", barrier=True).collect()
    return np.array(found[0]["w"]) if found else np.array(w, float)


def statistics(local: DataFrame, weighted: bool = True) -> DataFrame:
    """(worker, coord, value, weight) of local models."""
    weight = F.col("n").cast("double") if weighted else F.lit(1.0)
    return local.where("n > 0").select("worker", weight.alias("weight"), F.posexplode("w").alias("coord", "value"))


def collect_model(model: DataFrame, dims: int) -> np.ndarray:
    if dims > COLLECT_LIMIT:
        raise TooLargeToCollect(f"{dims} coordinates")
    w = np.zeros(dims)
    for r in model.collect():
        w[r["coord"]] = r["value"]
    return w


def soft_threshold(v: np.ndarray, by: float) -> np.ndarray:
    return np.sign(v) * np.maximum(np.abs(v) - by, 0)


def train(examples: DataFrame, feats: list[str], keys: list[str], job: JobSpec, w0: np.ndarray | None = None, checkpoint: str | None = None, resume: dict[int, dict] | None = None, table: str | None = None) -> TrainResult:
    """Runs a job on rows with y, split, worker, batch and features; returns the shared model.

    'ga' steps once per batch of all workers, 'ma' averages local models after
    every pass or every sync_every batches, 'admm' lets each worker solve its
    own part near the consensus by inner_epochs passes. Loss is measured on the
    validation split after each round (for 'ga' each epoch). A worker without
    rows counts for nothing. With a checkpoint path each round saves the shared
    model as worker -1, and x and u of each ADMM worker; `resume` takes them up.
    Rows may come packed, to share blocks between jobs. Each step is one pass
    over the batch's blocks, wherever they lie, that sums by worker. With
    reshuffle each epoch deals the rows into batches anew. The trace has
    the counted rows, the messages and the bytes of every worker and phase.
    """
    job.validate()
    spark, d = examples.sparkSession, len(feats) + 1
    w = np.zeros(d) if w0 is None else np.array(w0, float)
    given = "data" in examples.columns
    if given and job.reshuffle:
        raise JobRefused("packed rows cannot be dealt anew")
    whole = examples.select("split", "worker", *keys, "y", *feats).persist() if job.reshuffle else examples

    def dealt(epoch: int) -> tuple[DataFrame, dict[tuple[int, int], int]]:
        blocks = whole if given else pack(assign_batches(whole, keys, job.batches, epoch) if job.reshuffle else whole, feats, table)
        counts = blocks.where("fit").groupBy("worker", "batch").agg(F.sum("n").alias("n")).collect()  # workers times batches
        return blocks, {(r["worker"], r["batch"]): r["n"] for r in counts}

    laid, held_rows = dealt(1)
    history, trace, status, n_round = [], [], None, 0
    n_msgs, parts = transfers(job.pattern, "object_store", job.workers)
    if resume and -1 in resume:
        w = np.array(resume[-1]["w"])
    resume = {k: v for k, v in (resume or {}).items() if k >= 0}
    sizes_of: dict[int, int] = {}
    for (j, _), n in held_rows.items():
        sizes_of[j] = sizes_of.get(j, 0) + n
    trace += [(job.run_id, 0, 0, 0, j, "load", n, 1, 8 * d * n) for j, n in sorted(sizes_of.items())]

    def told(batch: int, rows_of: dict[int, int], passes: int = 1) -> None:
        """What each worker computed and sent in one synchronisation."""
        for j, n in sorted(sizes_of.items()):
            trace.append((job.run_id, n_round, n_round, batch, j, "compute", rows_of.get(j, 0) * passes, 0, 0))
            trace.append((job.run_id, n_round, n_round, batch, j, "communicate", 0, n_msgs, int(np.ceil(n_msgs * 8 * d / parts))))

    x = {int(k): np.array(v["w"]) for k, v in resume.items()}
    u = {int(k): np.array(v["dual"]) for k, v in resume.items()}
    try:
        while status is None:
            n_round += 1
            before, lr = w.copy(), job.lr.at(n_round)
            if job.reshuffle and n_round > 1:
                laid.unpersist()
                laid, held_rows = dealt(n_round)
            rows, order = laid.where("fit"), sorted({b for _, b in held_rows})
            if job.algorithm == "ga":
                for t in range(job.batches):
                    for s in packed_sums(rows.where(F.col("batch") == t), w, job.loss).values():
                        w = w - lr * (s[:-1] / s[-1] + job.loss.l2 * np.append(w[:-1], 0.0))
                    told(t, {j: held_rows.get((j, t), 0) for j in sizes_of})
            elif job.algorithm == "ma":
                step = job.sync_every or job.batches
                for t in range(0, job.batches, step):
                    own, seen = {j: w.copy() for j in sizes_of}, {}
                    for b in order if step >= job.batches else [b for b in order if t <= b < t + step]:
                        for j, n in local_step(rows.where(F.col("batch") == b), own, job.loss, lr).items():
                            seen[j] = seen.get(j, 0) + n
                    local = spark.createDataFrame([(j, n, [float(v) for v in own[j]]) for j, n in sorted(seen.items())], "worker int, n long, w array<double>")
                    for r in reduce_with(job.pattern, statistics(local, job.weighted), job.workers).collect():
                        w[r["coord"]] = r["value"]
                    told(t, {j: sum(held_rows.get((j, i), 0) for i in range(t, min(t + step, job.batches))) for j in sizes_of})
            else:
                anchors = {j: w - u.get(j, np.zeros(d)) for j in range(job.workers)}
                x = {j: x.get(j, w.copy()) for j in range(job.workers)}
                sizes: dict[int, int] = {}
                for _ in range(job.inner_epochs):
                    start, sizes = dict(x), {}
                    for b in order:
                        for j, n in local_step(rows.where(F.col("batch") == b), x, job.loss, lr, job.rho, anchors).items():
                            sizes[j] = sizes.get(j, 0) + n
                    if job.inner_tol and max((float(np.abs(x[j] - start[j]).max()) for j in sizes), default=0.0) < job.inner_tol:
                        break
                present = sorted(sizes)
                mean = np.mean([x[j] + u.get(j, np.zeros(d)) for j in present], axis=0) if present else w
                w = soft_threshold(mean, job.l1 / (len(present) * job.rho)) if job.l1 else mean
                for j in present:
                    u[j] = u.get(j, np.zeros(d)) + x[j] - w
                told(0, sizes, job.inner_epochs)
            if checkpoint:
                own = [(j, n_round, 0, [float(a) for a in x[j]], [float(a) for a in u[j]]) for j in sorted(u)]
                save_checkpoint(spark, checkpoint, job.run_id, [(-1, n_round, 0, [float(a) for a in w], []), *own])
            found = packed_sums(laid.where("not fit"), w, job.loss, value=True).get(-1)
            loss = float(found[0] / found[1]) if found is not None and found[1] else None
            moved = float(np.abs(w - before).max())
            primal = float(np.sqrt(sum(((x[j] - w) ** 2).sum() for j in x))) if job.algorithm == "admm" else 0.0
            history.append({"round": n_round, "loss": loss, "moved": moved, "primal": primal, "dual": job.rho * np.sqrt(job.workers) * float(np.linalg.norm(w - before))})
            status = job.stop.reason(n_round, loss, moved)
    finally:
        if not given:
            laid.unpersist()
        if job.reshuffle:
            whole.unpersist()
    return TrainResult(w, history, status, trace)


def tune_lr(examples: DataFrame, feats: list[str], loss, rates: list[float], epochs: int, batches: int) -> DataFrame:
    """(lr, loss): gradient averaging for every rate at once; each batch is scanned once for all candidates.

    The candidates' models stand side by side in one aggregate, so a grid costs
    as many scans as a single job.
    """
    d, spark = len(feats) + 1, examples.sparkSession
    w = {i: np.zeros(d) for i in range(len(rates))}
    kept = examples.select("split", "batch", "y", *feats).persist()
    fit, held = kept.where("split = 'train'"), kept.where("split = 'validation'")
    for _ in range(epochs):
        for t in range(batches):
            slopes = fit.where(F.col("batch") == t).select(*feats, *((loss.slope(F.col("y") * score(w[i], feats)) * F.col("y")).alias(f"_c{i}") for i in w))
            row = slopes.agg(F.count("*").alias("n"), *(F.sum(F.col(f"_c{i}") * F.col(f)).alias(f"_{i}_{j}") for i in w for j, f in enumerate(feats)), *(F.sum(f"_c{i}").alias(f"_{i}_b") for i in w)).first()
            for i in w:
                g = np.array([row[f"_{i}_{j}"] or 0.0 for j in range(d - 1)] + [row[f"_{i}_b"] or 0.0]) / max(row["n"], 1)
                w[i] = w[i] - rates[i] * (g + loss.l2 * np.append(w[i][:-1], 0.0))
    losses = held.agg(*(F.avg(loss.value(F.col("y") * score(w[i], feats))).alias(f"l{i}") for i in w)).first()
    kept.unpersist()
    return spark.createDataFrame([(float(r), losses[f"l{i}"], [float(v) for v in w[i]]) for i, r in enumerate(rates)], "lr double, loss double, w array<double>")


def best_rate(tuned: DataFrame) -> float:
    """The rate of the smallest loss; of equal ones the smallest rate."""
    return tuned.orderBy(F.col("loss").asc_nulls_last(), "lr").first()["lr"]


def with_algorithm(job: JobSpec, algorithm: str) -> JobSpec:
    return replace(job, algorithm=algorithm)


# ---- sparse models in coordinate form

#: Coordinates of a model that may be broadcast; as a table of the driver they take some 100 bytes each.
BROADCAST_COORDS = 100_000


def sparse_gradient(features: DataFrame, labels: DataFrame, model: DataFrame, loss, key: str, model_coords: int, limit: int = BROADCAST_COORDS) -> DataFrame:
    """(coord, g): the mean gradient of a model (coord, value) over (key, coord, value) features, never collected.

    Scores meet the features again by key; hot coordinates are summed partially
    before their exchange. The model is broadcast only up to `limit` coordinates,
    as a broadcast table is built in the driver's memory.
    """
    small = F.broadcast(model) if model_coords <= limit else model
    joined = features.join(small.withColumnRenamed("value", "w"), "coord", "left")
    margins = joined.groupBy(key).agg(F.sum(F.col("value") * F.coalesce("w", F.lit(0.0))).alias("s")).join(labels.select(key, "y"), key)
    slopes = margins.select(key, (loss.slope(F.col("y") * F.col("s")) * F.col("y")).alias("c"))
    n = labels.count()
    return features.join(slopes, key).groupBy("coord").agg((F.sum(F.col("c") * F.col("value")) / F.lit(float(max(n, 1)))).alias("g"))


def sparse_step(model: DataFrame, grad: DataFrame, lr: float, l2: float = 0.0) -> DataFrame:
    """The model after one step; coordinates of either side stay."""
    both = model.join(grad, "coord", "full_outer")
    w = F.coalesce("value", F.lit(0.0))
    return both.select("coord", (w - lr * (F.coalesce("g", F.lit(0.0)) + l2 * w)).alias("value"))


def sparse_loss(features: DataFrame, labels: DataFrame, model: DataFrame, loss, key: str) -> float | None:
    s = features.join(model.withColumnRenamed("value", "w"), "coord", "left").groupBy(key).agg(F.sum(F.col("value") * F.coalesce("w", F.lit(0.0))).alias("s"))
    return labels.join(s, key, "left").agg(F.avg(loss.value(F.col("y") * F.coalesce("s", F.lit(0.0))))).first()[0]


# ---- sparse rows with a model that passes through the driver


def sparse_rows(features: DataFrame, labels: DataFrame, key: str) -> DataFrame:
    """(key, y, coords, vals): one row per label with all features of its key; none for a key without features."""
    held = features.groupBy(key).agg(F.collect_list(F.struct("coord", "value")).alias("_f"))
    empty = F.array().cast("array<struct<coord:int,value:double>>")
    rows = labels.join(held, key, "left").select(key, "y", F.coalesce("_f", empty).alias("_f"))
    return rows.select(key, "y", F.col("_f.coord").alias("coords"), F.col("_f.value").alias("vals"))


def sparse_pass(rows: DataFrame, w: np.ndarray, loss, value_only: bool = False) -> tuple[float, int, np.ndarray]:
    """(loss sum, rows, gradient sums) of a model over (y, coords, vals) rows; each task leaves only the coordinates that it met."""
    shared, d = rows.sparkSession.sparkContext.broadcast(w), len(w)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, total, value, n = shared.value, np.zeros(d), 0.0, 0
        for part in batches:
            y, coords, vals = part.column("y").to_numpy(), part.column("coords"), part.column("vals").flatten().to_numpy()
            owner = np.repeat(np.arange(len(y)), np.asarray(coords.value_lengths()))
            coords = coords.flatten().to_numpy()
            m = y * np.bincount(owner, w[coords] * vals, len(y))
            value, n = value + float(loss.np_value(m).sum()), n + len(y)
            if not value_only:
                total += np.bincount(coords, (loss.np_slope(m) * y)[owner] * vals, d)
        met = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array([-2, -1, *met], pa.int32()), pa.array([value, n, *total[met]], pa.float64())], ["coord", "g"])

    sums = rows.select("y", "coords", "vals").mapInArrow(run, "coord int, g double").groupBy("coord").agg(F.sum("g").alias("g")).toArrow()
    shared.unpersist()
    coords, g = sums["coord"].to_numpy(), sums["g"].to_numpy()
    out = np.zeros(d)
    out[coords[coords >= 0]] = g[coords >= 0]
    return float(g[coords == -2].sum()), int(g[coords == -1].sum()), out


def sparse_train(rows: DataFrame, loss, lr: float, steps: int, dims: int) -> list[float]:
    """The mean loss before each step of gradient descent from zero over (y, coords, vals) rows: one pass a step and no exchange of features."""
    if dims > COLLECT_LIMIT:
        raise TooLargeToCollect(f"{dims} coordinates")
    w, losses = np.zeros(dims), []
    for s in range(steps):
        value, n, g = sparse_pass(rows, w, loss, value_only=s == steps - 1)
        losses.append(value / n if n else 0.0)
        w = w - lr * g / max(n, 1)
    return losses


# ---- long dense vectors in Arrow blocks


def block_gradient(rows: DataFrame, w: np.ndarray, loss, limit: int = COLLECT_LIMIT) -> tuple[np.ndarray, float, int]:
    """(mean gradient, mean loss, rows) over (x array, y) rows; w has no intercept. One vector leaves each task and is summed by coordinate."""
    d = len(w)
    if d > limit:
        raise TooLargeToCollect(f"{d} coordinates")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, value, n = np.zeros(d), 0.0, 0
        for batch in batches:
            for lo in range(0, batch.num_rows, 1024):
                part = batch.slice(lo, 1024)
                x = part.column("x").flatten().to_numpy(zero_copy_only=False).reshape(part.num_rows, -1)
                y = part.column("y").to_numpy(zero_copy_only=False)
                m = y * (x @ w)
                total, value, n = total + (loss.np_slope(m) * y) @ x, value + float(loss.np_value(m).sum()), n + len(y)
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([value]), pa.array([total], pa.list_(pa.float64()))], ["n", "value", "g"])

    parts = rows.select("x", "y").mapInArrow(run, "n long, value double, g array<double>")
    sums = parts.select("n", "value", F.posexplode("g").alias("i", "v"))
    g, n, value = np.zeros(d), 0, 0.0
    for r in sums.groupBy("i").agg(F.sum("v").alias("v"), F.sum("n").alias("n"), F.sum("value").alias("value")).collect():
        g[r["i"]], n, value = r["v"], r["n"], r["value"]
    return g / max(n, 1) + loss.l2 * w * (n > 0), value / max(n, 1), n


def block_train(rows: DataFrame, loss, lr: float, steps: int, dims: int, batches: int = 1) -> tuple[np.ndarray, list[float]]:
    """Gradient averaging over (x, y[, batch]) rows of long vectors; the loss is that before each step."""
    w, losses = np.zeros(dims), []
    for s in range(steps):
        g, value, _ = block_gradient(rows if batches == 1 else rows.where(F.col("batch") == s % batches), w, loss)
        losses.append(value)
        w = w - lr * g
    return w, losses
