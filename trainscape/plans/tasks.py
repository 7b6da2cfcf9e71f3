"""The five training tasks on the given tables, and the settings of the experiments."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.operators import features as X
from trainscape.operators import partition as P
from trainscape.sources.tables import cut_lineage, load

KEYS = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
DENSE = [f"f{i}" for i in range(28)]


@dataclass(frozen=True)
class TaskMeta:
    """What a run needs to know of a task: dimensions, kind, loss threshold, batch size and workers."""

    name: str
    dims: int
    kind: str
    threshold: float
    batch: int
    workers: int


def dense28_raw(spark: SparkSession, sf_dir: str) -> DataFrame:
    """28 numeric columns of order lines with their orders, parts, suppliers and customers.

    Customers join the orders, not their lines; small tables are broadcast, so
    that lines are exchanged once or twice.
    """
    return _dense28_columns(_dense28_joined(spark, sf_dir))


#: Rows of a joined table up to which it is broadcast.
BROADCAST_ROWS = 200_000


def _dense28_joined(spark: SparkSession, sf_dir: str) -> DataFrame:
    small = lambda df: F.broadcast(df) if df.count() <= BROADCAST_ROWS else df
    l = load(spark, sf_dir, "lineitem")
    o = load(spark, sf_dir, "orders")
    p = load(spark, sf_dir, "part", ["p_partkey", "p_brand", "p_size", "p_retailprice"])
    s = load(spark, sf_dir, "supplier", ["s_suppkey", "s_nationkey", "s_acctbal"])
    c = load(spark, sf_dir, "customer", ["c_custkey", "c_nationkey", "c_acctbal"])
    o = o.join(small(c), o.o_custkey == c.c_custkey).select("o_orderkey", "o_orderdate", "o_totalprice", "o_orderpriority", "o_orderstatus", "c_nationkey", "c_acctbal")
    return l.join(o, l.l_orderkey == o.o_orderkey).join(small(p), l.l_partkey == p.p_partkey).join(small(s), l.l_suppkey == s.s_suppkey).drop("o_orderkey", "p_partkey", "s_suppkey")


def dense28_kept(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The joined columns behind the dense task, written once as Parquet for several passes; give it to `task_dense28` and `forget` it."""
    kept = cut_lineage(_dense28_joined(spark, sf_dir))
    spark._jvm.System.gc()  # lets the cleaner delete the join's shuffle files
    return kept


def _dense28_columns(j: DataFrame) -> DataFrame:
    price, net = F.col("l_extendedprice"), F.col("l_extendedprice") * (1 - F.col("l_discount"))
    ship, ordered = F.to_date("l_shipdate"), F.to_date("o_orderdate")
    cols = [
        F.col("l_quantity"), price, F.col("l_discount"), F.col("l_tax"), F.col("l_linenumber"), net, net * (1 + F.col("l_tax")), price / F.col("l_quantity"),
        F.weekday(ship), F.month(ship), F.date_diff(ship, F.lit("1995-01-01").cast("date")), F.date_diff(ship, ordered), F.col("o_totalprice"), F.month(ordered), F.weekday(ordered),
        F.substring("o_orderpriority", 1, 1), F.col("o_orderstatus") == "F", F.col("o_orderstatus") == "O", F.col("p_size"), F.col("p_retailprice"), F.col("s_acctbal"), F.col("c_acctbal"),
        F.col("l_returnflag") == "A", F.col("l_returnflag") == "N", F.col("l_linestatus") == "F", F.col("s_nationkey") == F.col("c_nationkey"), price / F.col("o_totalprice"), F.regexp_extract("p_brand", r"(\d+)", 1),
    ]
    number = lambda c: c.cast("int").cast("double")
    whole = {15, 16, 17, 22, 23, 24, 25, 27}
    return j.select(*KEYS, "l_shipdate", *((number(c) if i in whole else c.cast("double")).alias(f"f{i}") for i, c in enumerate(cols)))


def task_dense28(spark: SparkSession, sf_dir: str, workers: int = 10, batches: int = 10, noise: float = 16.0, kept: DataFrame | None = None) -> tuple[DataFrame, TaskMeta]:
    raw = dense28_raw(spark, sf_dir) if kept is None else _dense28_columns(kept)
    scaled = X.minmax_apply(raw, X.minmax_fit(raw, DENSE), DENSE)
    df = X.plant_label(scaled, DENSE, KEYS, noise)
    df = P.assign_batches(P.assign_workers(P.split(df, KEYS), KEYS, workers), KEYS, batches)
    return df, TaskMeta("dense28", 28, "dense", 0.66, 10_000, workers)


def task_text(spark: SparkSession, sf_dir: str, target: str = "quality", dims: int = 47_236) -> tuple[DataFrame, DataFrame, TaskMeta]:
    """(doc_id, coord, value), (doc_id, y, split) and the task: hashed text weights of the labelled documents."""
    labels = load(spark, sf_dir, "labels").where(F.col(target).isNotNull())
    docs = load(spark, sf_dir, "documents", ["doc_id", "text"]).join(labels.select("doc_id"), "doc_id", "left_semi")
    y = P.split(labels.select("doc_id", F.when(F.col(target) == 1, 1.0).otherwise(-1.0).alias("y")), ["doc_id"])
    return X.tfidf(docs, dims=dims), y, TaskMeta("text47k", dims, "sparse", 0.68, 2_000, 5)


def task_grid10(spark: SparkSession, sf_dir: str, workers: int = 10) -> tuple[DataFrame, TaskMeta]:
    """(vec_id, x, y, split, worker): 8 x 8 grids of ten planted classes."""
    e = load(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    df = X.plant_class(e.select("vec_id", F.col("embedding").cast("array<double>").alias("x")), "x")
    return P.assign_workers(P.split(df, ["vec_id"]), ["vec_id"], workers), TaskMeta("grid10", 64, "image", 0.2, 128, workers)


def task_wide4096(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, TaskMeta]:
    """(vec_id, x, y, split): 4,096 products of components; class 0 against the rest, about a tenth positive."""
    e = load(spark, sf_dir, "embeddings")
    df = e.select("vec_id", X.outer_features("embedding").alias("x"), F.when(F.col("label") == 0, 1.0).otherwise(-1.0).alias("y"))
    return P.split(df, ["vec_id"]), TaskMeta("wide4096", 4096, "dense", 50.0, 800, 100)


def _ctr_events(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, dict[str, list[str]]]:
    e = load(spark, sf_dir, "events")
    e = e.withColumn("k", F.from_json("props", "k INT")["k"]).withColumn("hour", F.hour("ts")).withColumn("day", F.weekday("ts"))
    return e, {"user": ["user_id"], "k": ["k"], "hour": ["hour"], "day_hour": ["day", "hour"], "user_k": ["user_id", "k"], "user_hour": ["user_id", "hour"]}


def _click() -> Column:
    return F.when(F.col("event_type") == "click", 1.0).otherwise(-1.0).alias("y")


def task_ctr(spark: SparkSession, sf_dir: str, bins: int = 1 << 20) -> tuple[DataFrame, DataFrame, TaskMeta]:
    """(event_id, coord, value), (event_id, y, split): crosses of events in hashed bins, clicks against the rest."""
    e, named = _ctr_events(spark, sf_dir)
    y = P.split(e.select("event_id", _click()), ["event_id"])
    return X.hash_cross(e, named, ["event_id"], bins), y, TaskMeta("ctr1m", bins, "sparse", 0.68, 10_000, 10)


def ctr_rows(spark: SparkSession, sf_dir: str, bins: int = 1 << 20) -> tuple[DataFrame, TaskMeta]:
    """(event_id, y, coords, vals, split): the rows of `task_ctr` with the crosses of an event side by side."""
    e, named = _ctr_events(spark, sf_dir)
    rows = e.select("event_id", _click(), X.cross_cells(named, bins).alias("coords"), F.array_repeat(F.lit(1.0), len(named)).alias("vals"))
    return P.split(rows, ["event_id"]), TaskMeta("ctr1m", bins, "sparse", 0.68, 10_000, 10)


def event_work(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(task, n, users, mean_s): each event type as a workload of counted rows, a model of one number a user, and seconds by the mean value."""
    e = load(spark, sf_dir, "events", ["user_id", "event_type", "value"]).where("event_type is not null")
    return e.groupBy(F.col("event_type").alias("task")).agg(F.count("*").alias("n"), F.count_distinct("user_id").alias("users"), F.round(F.avg("value"), 6).alias("mean_s"))


def event_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The parameters of the analytic model for each event type: 64 bytes a row, 8 a user, a millisecond of an epoch for each unit of value."""
    n, users = F.col("n"), F.col("users")
    return event_work(spark, sf_dir).select("task", F.lit("ga").alias("algo"), (n * 64.0 / 1e6).alias("s_mb"), (users * 8.0 / 1e6).alias("m_mb"), F.lit(10.0).alias("rounds"), (n * F.col("mean_s") / 1000.0).alias("compute_s"), F.lit(0.01).alias("growth"))


#: The settings of the end-to-end runs (loss threshold, workers, batch, clusters).
PRESETS = {
    "w1_lr": ("dense28", "logistic", 0.66, 10, 10_000, None), "w1_svm": ("dense28", "hinge", 0.48, 10, 10_000, None), "w1_kmeans": ("dense28", "kmeans", 0.15, 10, 10_000, 10),
    "w2_lr": ("text47k", "logistic", 0.68, 5, 2_000, None), "w2_svm": ("text47k", "hinge", 0.05, 5, 2_000, None), "w2_kmeans": ("text47k", "kmeans", 0.01, 50, None, 3),
    "w4_lr": ("wide4096", "logistic", 50.0, 100, 800, None), "w4_svm": ("wide4096", "hinge", 50.0, 100, 800, None), "w4_kmeans": ("wide4096", "kmeans", 50.0, 100, 800, 10),
    "w3_conv": ("grid10", "separable_conv", 0.2, 10, 128, None), "w3_residual": ("grid10", "residual", 0.4, 10, 32, None), "w5_lr": ("ctr1m", "logistic", None, 10, 10_000, None),
}


def preset(name: str) -> dict:
    return dict(zip(("task", "model", "threshold", "workers", "batch", "k"), PRESETS[name]))
