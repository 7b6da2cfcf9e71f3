"""Limited lifetimes of function workers: restarts, and iterations that cannot fit."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trainscape.plans.constants import LIFETIME_S
from trainscape.plans.job import IterationTooLong


def apply_lifetime(trace: DataFrame, limit_s: float = LIFETIME_S, margin_s: float = 0.0) -> DataFrame:
    """Adds incarnation and restart to (worker, step, seconds) rows.

    A worker saves and is started again whenever its time since the start
    passes a multiple of the limit less the margin; the step that crosses it
    runs in the next incarnation.
    """
    order = Window.partitionBy("worker").orderBy("step")
    usable = F.lit(limit_s - margin_s)
    total = F.sum("seconds").over(order.rowsBetween(Window.unboundedPreceding, 0))
    marked = trace.withColumn("until_s", total).withColumn("incarnation", F.greatest(F.ceil(F.col("until_s") / usable) - 1, F.lit(0)).cast("int"))
    return marked.withColumn("restart", F.col("incarnation") > F.coalesce(F.lag("incarnation").over(order), F.lit(0)))


def check_iterations(trace: DataFrame, batch: int, limit_s: float = LIFETIME_S) -> float:
    """The longest step; refuses one over the limit and names a batch that fits."""
    longest = trace.agg(F.max("seconds")).first()[0] or 0.0
    if longest > limit_s:
        fits = max(1, int(batch * limit_s / longest))
        raise IterationTooLong(f"an iteration of {longest:g} s outlasts {limit_s:g} s; try a batch of {fits}", fits)
    return longest
