"""Feature preparation: scaling, text weights, crosses, planted labels."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from trainscape.functions.hashing import SPAN, portable_hash
from trainscape.sources.tables import COMPILED, settings


def minmax_fit(df: DataFrame, cols: list[str]) -> DataFrame:
    """One row with min and max of each column, in one aggregate."""
    return df.agg(*(f(F.col(c).cast("double")).alias(f"{c}_{n}") for c in cols for n, f in (("lo", F.min), ("hi", F.max))))


def minmax_apply(df: DataFrame, stats: DataFrame, cols: list[str]) -> DataFrame:
    """Scales to [-1, 1]; constant columns and nulls become 0.

    The one row of bounds is fetched here and becomes part of the plan, so that
    later passes over the scaled rows do not look for it again.
    """
    with settings(df.sparkSession, COMPILED):
        bounds = stats.first()

    def scaled(c: str) -> Column:
        lo, hi = bounds[f"{c}_lo"], bounds[f"{c}_hi"]
        if lo is None or not hi > lo:
            return F.lit(0.0)
        return F.coalesce((F.col(c) - F.lit(lo)) / (F.lit(hi) - F.lit(lo)) * 2.0 - 1.0, F.lit(0.0))

    return df.select(*(scaled(c).alias(c) if c in cols else F.col(c) for c in df.columns))


def plant_label(df: DataFrame, feats: list[str], keys: list[str], noise: float = 16.0, offset: float = 0.39) -> DataFrame:
    """Adds y in {-1, 1}: the sign of a fixed linear form with hash noise of the given amplitude."""
    margin = F.lit(offset)
    for j, f in enumerate(feats):
        margin = margin + F.lit(math.cos(j + 1)) * F.col(f)
    margin = margin + F.lit(noise) * (portable_hash("noise", *keys) / F.lit(float(SPAN)) - 0.5)
    return df.withColumn("y", F.when(margin >= 0, 1.0).otherwise(-1.0))


def plant_class(df: DataFrame, vector: str, classes: int = 10) -> DataFrame:
    """Adds y: the class whose fixed cosine form of the vector is largest, of equal ones the smallest class."""
    def form(c: int) -> Column:
        return F.aggregate(F.transform(vector, lambda x, j: x.cast("double") * F.cos(F.lit(float(c + 1)) * (j + 1))), F.lit(0.0), lambda s, x: s + x)

    best = F.array_max(F.array(*(F.struct(form(c).alias("v"), F.lit(-c).alias("c")) for c in range(classes))))
    return df.withColumn("y", (-best["c"]).cast("int"))


def tokens(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda t: t != "")


def tfidf(docs: DataFrame, key: str = "doc_id", text: str = "text", dims: int = 47_236) -> DataFrame:
    """(key, coord, value): hashed term frequencies times log((1 + N) / (1 + df)) + 1, of unit length per document.

    Terms are pre-aggregated per document before the exchange; document
    frequencies are counted over bins, which number at most dims.
    """
    words = docs.select(F.col(key), F.explode(tokens(F.col(text))).alias("term"))
    tf = words.groupBy(key, F.pmod(portable_hash("term", "term"), F.lit(dims)).cast("int").alias("coord")).agg(F.count("*").alias("tf"))
    df_ = tf.groupBy("coord").agg(F.count("*").alias("df"))
    n = docs.agg(F.count("*").alias("n"))
    idf = df_.crossJoin(F.broadcast(n)).select("coord", (F.log((1.0 + F.col("n")) / (1.0 + F.col("df"))) + 1.0).alias("idf"))
    weighted = tf.join(F.broadcast(idf) if dims <= 1 << 20 else idf, "coord").select(key, "coord", (F.col("tf") * F.col("idf")).alias("v"))
    norms = weighted.groupBy(key).agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))
    return weighted.join(norms, key).select(key, "coord", (F.col("v") / F.col("norm")).alias("value"))


def binarize_tag(df: DataFrame, tags: str, tag: str) -> DataFrame:
    """Adds target: 1 if the tag list holds the tag, else 0; a null list gives 0."""
    return df.withColumn("target", F.coalesce(F.array_contains(tags, tag), F.lit(False)).cast("int"))


def hash_cross(df: DataFrame, crosses: dict[str, list[Column]], keys: list[str], bins: int = 1 << 20) -> DataFrame:
    """(keys, coord, value 1): each named cross of columns hashed into a bin."""
    return df.select(*keys, F.explode(cross_cells(crosses, bins)).alias("coord")).withColumn("value", F.lit(1.0))


def cross_cells(crosses: dict[str, list[Column]], bins: int) -> Column:
    """The bins of a row's named crosses."""
    return F.array(*(F.pmod(portable_hash(name, *cols), F.lit(bins)).cast("int") for name, cols in crosses.items()))


def outer_features(vector: str) -> Column:
    """The flattened outer product of a vector with itself."""
    v = F.col(vector)
    return F.flatten(F.transform(v, lambda x: F.transform(v, lambda y: x.cast("double") * y.cast("double"))))
