"""The SQL surface: tables and tasks as views, cost functions as SQL functions, the design grid as a table function."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from trainscape.plans import constants as K
from trainscape.plans import tasks
from trainscape.sources.tables import load

TABLES = "region nation customer supplier part orders lineitem events".split()


def _startup(infra: str) -> str:
    points = [(w, v) for n, c, w, v, _, _ in K.CONSTANTS if (n, c) == ("startup", infra)]
    out = f"CASE WHEN w <= {points[0][0]} THEN {points[0][1]}D"
    for (a, x), (b, y) in zip(points, points[1:]):
        out += f" {f'WHEN w <= {b} THEN' if b != points[-1][0] else 'ELSE'} {x}D + (w - {a}) * {(y - x) / (b - a)!r}D"
    return out + " END"


class DesignGrid:
    """One row per algorithm, channel and number of workers up to the argument, in doubling steps."""

    def eval(self, most: int) -> Iterator[tuple]:
        w = 1
        while w <= most:
            for algorithm in ("ga", "ma", "admm"):
                for channel in ("object_store", "cache_mt", "kv_db", "vm_ps"):
                    yield algorithm, channel, w
            w *= 2


def register(spark: SparkSession, sf_dir: str) -> None:
    """Views of the tables and of the dense task; functions startup_fs, startup_vc, runtime_fs, runtime_vc, dollars; table function design_grid."""
    for t in TABLES:
        load(spark, sf_dir, t).createOrReplaceTempView(t)
    tasks.task_dense28(spark, sf_dir)[0].createOrReplaceTempView("dense28")
    b, l = K.constant("bandwidth", "object_store"), K.constant("latency", "object_store")
    n, m = K.constant("bandwidth", "net_t2_medium"), K.constant("latency", "net_t2_medium")
    for infra in ("fs", "vc"):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION startup_{infra}(w INT) RETURNS DOUBLE RETURN {_startup(infra)}")
    form = "startup_{i}(w) + s_mb / {b!r}D + rounds * (({k} * w - 2) * (m_mb / w / {bw!r}D + {lat!r}D) + compute_s / w)"
    args = "w INT, s_mb DOUBLE, m_mb DOUBLE, rounds DOUBLE, compute_s DOUBLE"
    for i, k, bw, lat in (("fs", 3, b, l), ("vc", 2, n, m)):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION runtime_{i}({args}) RETURNS DOUBLE RETURN {form.format(i=i, b=b, k=k, bw=bw, lat=lat)}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION dollars(infra STRING, w INT, seconds DOUBLE) RETURNS DOUBLE RETURN seconds * w * IF(infra = 'vc', {K.PRICE_VC!r}D, {K.PRICE_FS!r}D)")
    spark.udtf.register("design_grid", udtf(DesignGrid, returnType="algorithm string, channel string, w int"))
