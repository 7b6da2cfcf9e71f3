"""Mixing sources to target weights by hash-threshold histograms; DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from trainscape.llm._common import checkpointed, forget, small_side, table, words_count

#: Hexadecimal digits of a document's hash that each of the nested histograms takes: 4,096 buckets a level.
DIGITS, LEVELS = 3, 4
#: Weights of the sources in order, repeating.
WEIGHTS = (3, 1, 2)


def _targets(sizes: DataFrame, percent: int, repeats: int, weights: tuple[int, ...]) -> DataFrame:
    """(source, source_size, target) from one row per source.

    The total is poured over the sources by weight; a source is full at
    `repeats` times its size. Sources in the order of capacity per weight fill
    first, so the level at which the rest stands follows from running sums.
    """
    everything = Window.partitionBy(F.lit(1))
    order = everything.orderBy(F.col("source").asc_nulls_last())
    rank = F.row_number().over(order) - 1
    weight = F.element_at(F.array(*map(F.lit, weights)), (F.pmod(rank, F.lit(len(weights))) + 1).cast("int")).cast("double")
    t = sizes.select("source", "source_size", weight.alias("weight"), (F.lit(float(repeats)) * F.col("source_size")).alias("room"), (F.sum("source_size").over(everything) * F.lit(float(percent)) / F.lit(100.0)).alias("total"))
    fill = everything.orderBy(F.col("room") / F.col("weight"), F.col("source").asc_nulls_last())
    before = fill.rowsBetween(Window.unboundedPreceding, -1)
    level = (F.col("total") - F.coalesce(F.sum("room").over(before), F.lit(0.0))) / (F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    t = t.withColumn("level", level)
    first_open = F.min(F.when(F.col("room") > F.col("level") * F.col("weight"), F.struct((F.col("room") / F.col("weight")).alias("k"), F.col("level").alias("l")))).over(everything)
    share = F.when(first_open.isNull(), F.col("room")).otherwise(F.least("room", first_open["l"] * F.col("weight")))
    return t.select("source", "source_size", share.alias("target"))


def _bucket(level: int) -> Column:
    return F.conv(F.substring("digest", 1 + DIGITS * level, DIGITS), 16, 10).cast("int")


def _by_source(left: DataFrame, right: DataFrame) -> DataFrame:
    """Join on the source, null equal to null; the per-source side is broadcast if it is small."""
    right = right.withColumnRenamed("source", "source_r")
    return left.join(small_side(right), F.col("source").eqNullSafe(F.col("source_r")), "left").drop("source_r")


def _thresholds(base: DataFrame, percent: int, repeats: int, weights: tuple[int, ...]) -> DataFrame:
    """(source, source_size, target, whole, prefix, inclusive): how often a source is taken whole, and the hashes taken once more."""
    sizes = base.groupBy("source").agg(F.sum("size").alias("source_size"))
    targets = _targets(sizes, percent, repeats, weights)
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    state = checkpointed(targets.withColumn("whole", whole).withColumn("room", F.col("target") - F.col("whole") * F.col("source_size")).withColumn("prefix", F.lit("")))
    for level in range(LEVELS):
        inside = base if not level else _by_source(base, state.select("source", "prefix")).where(F.substring("digest", 1, DIGITS * level) == F.col("prefix"))
        sums = inside.groupBy("source", F.substring("digest", 1 + DIGITS * level, DIGITS).alias("part"), _bucket(level).alias("bucket")).agg(F.sum("size").alias("n"))
        upto = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)
        run = _by_source(sums.withColumn("upto", F.sum("n").over(upto)), state.select("source", "room"))
        edge = run.where(F.col("upto") > F.col("room")).groupBy("source").agg(F.min("bucket").alias("bucket"), F.min("part").alias("part"), F.min("upto").alias("upto"), F.min_by("n", "bucket").alias("n"))
        edge = checkpointed(edge.select("source", "part", (F.col("upto") - F.col("n")).alias("below"), "n"))
        joined = _by_source(state, edge)
        room = F.col("room") - F.coalesce("below", F.lit(0))
        if level == LEVELS - 1:
            include = F.col("part").isNull() | (2 * room >= F.col("n"))
            joined = joined.withColumn("inclusive", include)
        before, state = state, checkpointed(joined.withColumn("room", room).withColumn("prefix", F.concat("prefix", F.coalesce("part", F.lit("g")))).drop("part", "below", "n"))
        forget(before, edge)
    return state.select("source", "source_size", "target", "whole", "prefix", "inclusive")


def _times(repeats: int) -> Column:
    """How often a document is taken."""
    under = (F.col("digest") < F.col("prefix")) | ((F.col("digest") == F.col("prefix")) & F.col("inclusive"))
    return F.col("whole") + F.when((F.col("whole") < repeats) & under, 1).otherwise(0)


def _sized(docs: DataFrame, *more: str) -> DataFrame:
    key = F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), words_count(F.col("text").cast("string")).alias("size"), F.substring(F.md5(key), 1, DIGITS * LEVELS).alias("digest"), *more)


def mix_sources(docs: DataFrame, percent: int = 150, repeats: int = 2, weights: tuple[int, ...] = WEIGHTS) -> DataFrame:
    """(doc_id, size, source_size, target, taken) of a mix of `percent` of all words.

    Size is a text's number of words (null: 0). Sources in code-point order,
    null last, weigh `weights` in turn and share the total; none is taken more
    than `repeats` times, the excess is shared by the others by weight. Each
    source is taken whole as often as its target holds it; of the remainder,
    those documents are taken once more whose hash is under a threshold. The
    threshold is found in nested histograms of words by source and hash bucket:
    only the bucket on the boundary is refined, and the last boundary bucket is
    taken if at least half of it fits. Nothing is sorted.

    The hash is md5 of doc_id (null: of the empty string), so reruns agree and
    rows that repeat an id go together. Empty sources have target 0, an empty
    table gives no rows; texts of any length are counted whole. Targets come
    from one row per source, sorted in one task. Other columns are ignored.
    """
    base = checkpointed(_sized(docs))
    chosen = _by_source(base, _thresholds(base, percent, repeats, weights))
    return chosen.select("doc_id", "size", "source_size", "target", (F.col("size") * _times(repeats)).cast("long").alias("taken"))


def repeat_taken(docs: DataFrame, percent: int = 150, repeats: int = 2, weights: tuple[int, ...] = WEIGHTS) -> DataFrame:
    """The documents themselves, each row as often as mix_sources takes it; rows without words follow their hash too."""
    names = docs.columns
    base = checkpointed(_sized(docs))
    chosen = _by_source(_sized(docs, F.struct(*names).alias("row")), _thresholds(base, percent, repeats, weights))
    return chosen.select("row", F.explode(F.sequence(F.lit(0).cast("long"), _times(repeats).cast("long"))).alias("turn")).where("turn > 0").select("row.*")


def op3_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_sources(table(spark, sf_dir, "documents"))


OP3_SQL = r"""
with d as (select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint as size, substr(md5(coalesce(doc_id::varchar, '')), 1, 12) as h from documents),
 s as (select source, sum(size)::bigint as source_size, row_number() over (order by encode(source) nulls last) - 1 as k from d group by source),
 w as (select source, source_size, 2.0::double * source_size as room, ([3.0, 1.0, 2.0]::double[])[1 + k % 3] as weight, (sum(source_size) over ())::double * 150.0::double / 100.0::double as total from s),
 f as (select *, (total - coalesce(sum(room) over (order by room / weight, encode(source) nulls last rows between unbounded preceding and 1 preceding), 0)) /
                 (sum(weight) over () - coalesce(sum(weight) over (order by room / weight, encode(source) nulls last rows between unbounded preceding and 1 preceding), 0)) as lvl from w),
 t as (select source, source_size, case when (select min(lvl) from f where room > lvl * weight) is null then room
              else least(room, (select arg_min(lvl, room / weight) from f where room > lvl * weight) * weight) end as target from f),
 b as (select *, case when source_size > 0 then floor(target / source_size)::bigint else 0 end as whole from t),
 g as (select source, h, sum(size) as n, sum(sum(size)) over (partition by source order by h) as upto from d group by source, h)
select d.doc_id, d.size, b.source_size, b.target,
       (d.size * (whole + case when whole < 2 and (upto <= target - whole * source_size or 2 * (target - whole * source_size - (upto - n)) >= n) then 1 else 0 end))::bigint as taken
from d join b on d.source is not distinct from b.source join g on d.source is not distinct from g.source and d.h = g.h"""
