"""The design space: every combination that can run, and the choices made before planning."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.plans.constants import KV_ITEM_BYTES

ALGORITHMS = [("ga", False), ("ma", False), ("admm", True), ("em", False)]
CHANNELS = ["object_store", "cache_mt", "cache_st", "kv_db", "vm_ps", "direct"]
MODELS = [("logistic", True, False, 224), ("svm", True, False, 224), ("kmeans", False, True, 2_240), ("separable_conv", False, False, 12_000_000), ("residual", False, False, 89_000_000)]
#: Numbers in a model for each user, where users are what it is trained on.
NUMBERS = {"logistic": 1, "svm": 1, "kmeans": 10, "separable_conv": 1000, "residual": 10_000}
INFRAS = [("fs", 3.0), ("vc", 64.0), ("hp", 3.0)]


def enumerate_designs(spark: SparkSession, workers: list[int] = (10, 50), models: DataFrame | None = None) -> DataFrame:
    """(model, algorithm, channel, pattern, protocol, infra, w): the valid combinations of all axes.

    ADMM needs a convex model and 'em' is for clustering alone; items over the
    key-value limit are out; machines talk directly, functions through storage,
    the hybrid through its server; asynchronous runs have no reduction pattern.
    """
    frame = lambda rows, ddl: spark.createDataFrame(rows, ddl)
    models = frame(MODELS, "model string, convex boolean, clusters boolean, m_bytes long") if models is None else models
    grid = models.crossJoin(frame(ALGORITHMS, "algorithm string, needs_convex boolean"))
    grid = grid.crossJoin(frame([(c,) for c in CHANNELS], "channel string")).crossJoin(frame([(p,) for p in ("all_reduce", "scatter_reduce")], "pattern string"))
    grid = grid.crossJoin(frame([("bsp",), ("async",)], "protocol string")).crossJoin(frame(INFRAS, "infra string, mem_gb double")).crossJoin(frame([(w,) for w in workers], "w int"))
    valid = (
        (~F.col("needs_convex") | F.col("convex")) & (F.col("clusters") == (F.col("algorithm") == "em"))
        & ((F.col("channel") != "kv_db") | (F.col("m_bytes") <= KV_ITEM_BYTES))
        & ((F.col("infra") == "vc") == (F.col("channel") == "direct")) & ((F.col("infra") == "hp") == (F.col("channel") == "vm_ps"))
        & ((F.col("protocol") == "bsp") | ((F.col("algorithm") == "ga") & (F.col("pattern") == "all_reduce")))
    )
    return grid.where(valid).select("model", "algorithm", "channel", "pattern", "protocol", "infra", "w")


def choose_gradient_path(dims: int, density: float, model_bytes: float) -> str:
    """'native' expressions for few dimensions, 'sparse' joins for sparse or very long models, 'arrow' blocks between."""
    if dims <= 64 and density > 0.1:
        return "native"
    return "sparse" if density < 0.05 or model_bytes > 1e8 else "arrow"


def recommend_algorithm(convex: bool, rows: float, batch: float, round_s: float, scan_s: float, rounds_ma: int = 15, rounds_admm: int = 3, epochs_ga: int = 10) -> str:
    """The algorithm of the least predicted seconds: GA pays a round per batch, MA one per scan, ADMM ten scans per round."""
    times = {"ga": epochs_ga * (rows / batch * round_s + scan_s), "ma": rounds_ma * (round_s + scan_s)}
    if convex:
        times["admm"] = rounds_admm * (round_s + 10 * scan_s)
    return min(times, key=times.get)
