"""As-of and interval joins without a nested loop."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, on: list[str], at_left: str, at_right: str, value: str) -> DataFrame:
    """left with the latest right value not later than at_left within each key, or null.

    Both sides are united and the last value carried forward, one sort per key;
    of equal times the right row counts as earlier. A key must not hold an
    unbounded share of the rows: add a time bucket to `on` and carry the last
    value of each bucket first where one does.
    """
    names = left.columns
    l = left.select(*on, F.col(at_left).alias("_at"), F.lit(1).alias("_k"), F.struct(*names).alias("_row"), F.lit(None).cast(right.schema[value].dataType).alias("_v"))
    r = right.select(*on, F.col(at_right).alias("_at"), F.lit(0).alias("_k"), F.lit(None).cast(l.schema["_row"].dataType).alias("_row"), F.col(value).alias("_v"))
    carry = F.last("_v", ignorenulls=True).over(Window.partitionBy(*on).orderBy("_at", "_k").rowsBetween(Window.unboundedPreceding, 0))
    return l.unionByName(r).withColumn("_last", carry).where("_k = 1").select("_row.*", F.col("_last").alias(value))


def overlaps(left: DataFrame, right: DataFrame, left_span: tuple[str, str], right_span: tuple[str, str], bucket: float) -> DataFrame:
    """Pairs of rows whose half-open intervals overlap, each once.

    Intervals are put into all buckets of the given length that they touch and
    joined by bucket; a pair is kept in the bucket where the later start lies.
    """
    spread = lambda df, a, b, name: df.withColumn(name, F.explode(F.sequence(F.floor(F.col(a) / bucket), F.floor(F.col(b) / bucket))))
    l, r = spread(left, *left_span, "_bl"), spread(right, *right_span, "_br")
    (a, b), (c, d) = left_span, right_span
    hit = (F.col("_bl") == F.col("_br")) & (F.col(a) < F.col(d)) & (F.col(c) < F.col(b)) & (F.floor(F.greatest(F.col(a), F.col(c)) / bucket) == F.col("_bl"))
    return l.join(r, hit).drop("_bl", "_br")
