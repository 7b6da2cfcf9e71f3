"""k-means by expectation and maximisation."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from trainscape.functions.hashing import portable_hash
from trainscape.operators.linear import PACK_BYTES
from trainscape.sources.tables import settings

#: Centroids times dimensions up to which distances are one generated expression.
NATIVE_TERMS = 512


def first_rows(rows: DataFrame, feats: list[str], k: int, keys: list[str]) -> np.ndarray:
    """The k first rows by key as centroids; fewer if there are fewer rows."""
    return np.array([[float(r[f]) for f in feats] for r in rows.select(*keys, *feats).orderBy(*keys).limit(k).collect()]).reshape(-1, len(feats))


def random_rows(rows: DataFrame, feats: list[str], k: int, keys: list[str], seed: str = "") -> np.ndarray:
    """The k rows of smallest hash as centroids; the same rows for a seed however the data lie."""
    h = portable_hash(f"init{seed}", *keys)
    return np.array([[float(r[f]) for f in feats] for r in rows.select(h.alias("_h"), *keys, *feats).orderBy("_h", *keys).limit(k).collect()]).reshape(-1, len(feats))


def spread_rows(rows: DataFrame, feats: list[str], k: int, keys: list[str], rounds: int = 4, seed: str = "") -> np.ndarray:
    """Centroids by oversampling: each round keeps rows by hash with a chance that grows with their distance; then the most weighty k are chosen greedily."""
    chosen = first_rows(rows, feats, 1, keys)
    for turn in range(rounds):
        near = rows.withColumn("_d", nearest(chosen, feats)["d"])
        cost = near.agg(F.sum("_d")).first()[0] or 0.0
        if cost <= 0:
            break
        more = near.where(portable_hash(f"init{seed}{turn}", *keys) / 2.0**32 < F.lit(2.0 * k / cost) * F.col("_d")).select(*feats).limit(10 * k).collect()
        chosen = np.vstack([chosen, *([[[float(r[f]) for f in feats] for r in more]] if more else [])])
    weights = {r["c"]: r["n"] for r in rows.select(nearest(chosen, feats)["c"].alias("c")).groupBy("c").agg(F.count("*").alias("n")).collect()}
    picked = [max(weights, key=lambda c: (weights[c], -c))] if weights else []
    while len(picked) < min(k, len(chosen)):
        gap = ((chosen[:, None] - chosen[picked][None]) ** 2).sum(-1).min(1)
        picked.append(int(np.argmax([gap[c] * weights.get(c, 0) + 1e-12 * gap[c] for c in range(len(chosen))])))
    return chosen[picked]


def nearest(centroids: np.ndarray, feats: list[str]) -> Column:
    """struct(d, c): squared distance and number of the nearest centroid, of equal ones the smallest."""
    def distance(c: np.ndarray) -> Column:
        total = None
        for v, f in zip(c, feats):
            term = (F.col(f) - float(v)) * (F.col(f) - float(v))
            total = term if total is None else total + term
        return total

    return F.array_min(F.array(*(F.struct(distance(c).alias("d"), F.lit(i).alias("c")) for i, c in enumerate(centroids))))


def _block_kernel(centroids: np.ndarray, feats: list[str]):
    """Sums, counts and loss per centroid of a partition, by blocks of distances."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        k, d = centroids.shape
        sums, counts, losses = np.zeros((k, d)), np.zeros(k, np.int64), np.zeros(k)
        half = (centroids**2).sum(1)
        for part in batches:
            x = np.column_stack([part.column(f).to_numpy(zero_copy_only=False) for f in feats]).astype(float)
            for lo in range(0, len(x), 4096):
                block = x[lo : lo + 4096]
                at = (half - 2 * block @ centroids.T).argmin(1)
                np.add.at(sums, at, block)
                counts += np.bincount(at, minlength=k)
                losses += np.bincount(at, ((block - centroids[at]) ** 2).sum(1), minlength=k)
        used = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(used.astype(np.int32)), pa.array(counts[used]), pa.array(losses[used]), pa.array(list(sums[used]), pa.list_(pa.float64()))], ["c", "n", "loss", "s"])

    return run


def em_step(rows: DataFrame, centroids: np.ndarray, feats: list[str]) -> tuple[np.ndarray, float, int]:
    """(new centroids, mean squared distance to the old ones, rows); an empty cluster keeps its centroid.

    k * d sums and k counts leave each task. Few centroids are native
    expressions; many are blocks in numpy, without a row per pair.
    """
    new = centroids.copy()
    if centroids.size <= NATIVE_TERMS:
        at = rows.select(*feats, nearest(centroids, feats).alias("_m")).groupBy(F.col("_m.c").alias("c")).agg(F.count("*").alias("n"), F.sum("_m.d").alias("loss"), *(F.sum(f).alias(f"s{i}") for i, f in enumerate(feats)))
        found = [(r["c"], r["n"], r["loss"], [r[f"s{i}"] for i in range(len(feats))]) for r in at.collect()]
    else:
        parts = rows.select(*feats).mapInArrow(_block_kernel(centroids, feats), "c int, n long, loss double, s array<double>")
        long = parts.select("c", "n", "loss", F.posexplode("s").alias("i", "v")).groupBy("c", "i").agg(F.sum("v").alias("v"), F.sum("n").alias("n"), F.sum("loss").alias("loss"))
        sums: dict[int, list] = {}
        for r in long.collect():
            own = sums.setdefault(r["c"], [r["n"], r["loss"], np.zeros(len(feats))])
            own[2][r["i"]] = r["v"]
        found = [(c, n, l, s) for c, (n, l, s) in sums.items()]
    total, loss = 0, 0.0
    for c, n, l, s in found:
        new[c] = np.array(s, float) / n
        total, loss = total + n, loss + l
    return new, (loss / total if total else float("nan")), total


def em_kmeans(rows: DataFrame, feats: list[str], k: int, keys: list[str], iters: int = 10, init: str = "first", tol: float = 0.0, threshold: float | None = None) -> tuple[np.ndarray, list[float]]:
    """(centroids, loss of each iteration). Stops at the threshold, or when no centroid moves by more than tol squared."""
    start = {"first": first_rows, "random": random_rows, "spread": spread_rows}[init]
    rows = rows.persist()
    centroids, losses = start(rows, feats, k, keys), []
    for _ in range(iters):
        if not len(centroids):
            break
        new, loss, _ = em_step(rows, centroids, feats)
        losses.append(loss)
        shift = float(((new - centroids) ** 2).sum(1).max())
        centroids = new
        if (threshold is not None and loss <= threshold) or (tol and shift < tol):
            break
    rows.unpersist()
    return centroids, losses


def packed_em_step(blocks: DataFrame, centroids: np.ndarray) -> tuple[np.ndarray, float, int]:
    """em_step for rows that `linear.pack` holds; rows with a null are in no cluster."""
    k, d = centroids.shape

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, counts, losses = np.zeros((k, d)), np.zeros(k, np.int64), np.zeros(k)
        half = (centroids**2).sum(1)[:, None]
        for part in batches:
            for n, data in zip(part.column("n"), part.column("data")):
                rows = np.frombuffer(pa.decompress(data.as_buffer(), n.as_py() * 8 * (d + 1), "zstd")).reshape(d + 1, n.as_py())
                x = rows[1:, rows[0] != 0]
                at = (half - 2 * centroids @ x).argmin(0)
                counts += np.bincount(at, minlength=k)
                losses += np.bincount(at, ((x - centroids[at].T) ** 2).sum(0), minlength=k)
                for j in range(d):
                    sums[:, j] += np.bincount(at, x[j], minlength=k)
        used = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(used.astype(np.int32)), pa.array(counts[used]), pa.array(losses[used]), pa.array(list(sums[used]), pa.list_(pa.float64()))], ["c", "n", "loss", "s"])

    with settings(blocks.sparkSession, {"spark.sql.execution.arrow.maxBytesPerBatch": str(PACK_BYTES)}):
        parts = blocks.select("n", "data").mapInArrow(run, "c int, n long, loss double, s array<double>")
        return _moved(parts, centroids)


# ---- sparse rows in coordinate form


def sparse_assign(features: DataFrame, centroids: DataFrame, key: str) -> DataFrame:
    """(key, cluster, d): the nearest of centroids (cluster, coord, value) for rows (key, coord, value), of equal ones the smallest.

    Distances are |x|^2 - 2 x c + |c|^2, so only coordinates of both sides meet;
    clusters without a shared coordinate count with x c = 0. They are compared
    to nine digits, so that a tie does not hang on the order of a sum.
    """
    norms = features.groupBy(key).agg(F.sum(F.col("value") * F.col("value")).alias("xx"))
    sizes = centroids.groupBy("cluster").agg(F.sum(F.col("value") * F.col("value")).alias("cc"))
    meet = features.join(centroids.withColumnRenamed("value", "c"), "coord").groupBy(key, "cluster").agg(F.sum(F.col("value") * F.col("c")).alias("xc"))
    every = norms.crossJoin(F.broadcast(sizes))  # k rows
    d = F.round(F.col("xx") - 2 * F.coalesce("xc", F.lit(0.0)) + F.col("cc"), 9)
    best = every.join(meet, [key, "cluster"], "left").select(key, F.struct(d.alias("d"), "cluster").alias("m")).groupBy(key).agg(F.min("m").alias("m"))
    return best.select(key, "m.cluster", "m.d")


def sparse_em_step(features: DataFrame, centroids: DataFrame, key: str) -> tuple[DataFrame, DataFrame]:
    """(new centroids, (key, cluster, d) to the old ones); an empty cluster keeps its centroid. Centroids stay distributed."""
    at = sparse_assign(features, centroids, key)
    counts = at.groupBy("cluster").agg(F.count("*").alias("n"))
    sums = features.join(at.select(key, "cluster"), key).groupBy("cluster", "coord").agg(F.sum("value").alias("s"))
    moved = sums.join(F.broadcast(counts), "cluster").select("cluster", "coord", (F.col("s") / F.col("n")).alias("value"))
    kept = centroids.join(F.broadcast(counts), "cluster", "left_anti").select("cluster", "coord", "value")
    return moved.unionByName(kept), at


# ---- long dense vectors


def block_em_step(rows: DataFrame, centroids: np.ndarray) -> tuple[np.ndarray, float, int]:
    """em_step for (x array) rows of many dimensions, by blocks of distances in numpy."""
    k, d = centroids.shape

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, counts, losses = np.zeros((k, d)), np.zeros(k, np.int64), np.zeros(k)
        half = (centroids**2).sum(1)
        for batch in batches:
            for lo in range(0, batch.num_rows, 1024):
                part = batch.slice(lo, 1024).column("x")
                x = part.flatten().to_numpy(zero_copy_only=False).reshape(len(part), -1)
                at = (half - 2 * x @ centroids.T).argmin(1)
                np.add.at(sums, at, x)
                counts += np.bincount(at, minlength=k)
                losses += np.bincount(at, ((x - centroids[at]) ** 2).sum(1), minlength=k)
        used = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(used.astype(np.int32)), pa.array(counts[used]), pa.array(losses[used]), pa.array(list(sums[used]), pa.list_(pa.float64()))], ["c", "n", "loss", "s"])

    parts = rows.select("x").mapInArrow(run, "c int, n long, loss double, s array<double>")
    return _moved(parts, centroids)


def _moved(parts: DataFrame, centroids: np.ndarray) -> tuple[np.ndarray, float, int]:
    """(new centroids, mean squared distance, rows) from the tasks' (c, n, loss, s)."""
    long = parts.select("c", "n", "loss", F.posexplode("s").alias("i", "v")).groupBy("c", "i").agg(F.sum("v").alias("v"), F.sum("n").alias("n"), F.sum("loss").alias("loss"))
    new, seen = centroids.copy(), {}
    for r in long.collect():
        new[r["c"], r["i"]] = r["v"] / r["n"]
        seen[r["c"]] = (r["n"], r["loss"])
    total = sum(n for n, _ in seen.values())
    return new, (sum(l for _, l in seen.values()) / total if total else float("nan")), total
