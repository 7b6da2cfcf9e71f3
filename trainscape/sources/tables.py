"""Tables in and out, and the checkpoint store."""

from __future__ import annotations

import tempfile
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Numbers that the driver may collect for one model; beyond it models stay in coordinate form.
COLLECT_LIMIT = 10_000_000


class SchemaMismatch(ValueError):
    """A frame lacks a column or holds another type."""


def load(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None) -> DataFrame:
    """A table's columns. Where the scan has fewer splits than the cluster has cores its rows are dealt out, so that none stands idle; other scans are read as they lie."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.select(*cols) if cols else df
    cores = spark.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


#: Generated methods over 8,000 bytes of code are never compiled by the JVM; wide rows are then computed in smaller methods.
COMPILED = {"spark.sql.codegen.hugeMethodLimit": "8000"}


@contextmanager
def settings(spark: SparkSession, values: dict[str, str]):
    """Session settings that hold while jobs are planned and run inside the block."""
    before = {k: spark.conf.get(k, None) for k in values}
    for k, v in values.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def read_any(spark: SparkSession, path: str, fmt: str = "parquet", schema: T.StructType | str | None = None, **options) -> DataFrame:
    """Parquet, ORC, JSON, CSV, text, libsvm or binary files; all but self-describing formats need a schema."""
    if fmt in ("csv", "json") and schema is None:
        raise SchemaMismatch(f"{fmt} needs an explicit schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def write_table(df: DataFrame, path: str, fmt: str = "parquet", by: list[str] | None = None, mode: str = "overwrite") -> None:
    """A file sink, partitioned by columns; overwriting replaces only the partitions that the frame holds."""
    writer = df.write.format(fmt).mode(mode)
    (writer.partitionBy(*by).option("partitionOverwriteMode", "dynamic") if by else writer).save(path)


def check_schema(df: DataFrame, expected: dict[str, str]) -> DataFrame:
    have = dict(df.dtypes)
    for name, kind in expected.items():
        if have.get(name) != kind:
            raise SchemaMismatch(f"{name}: {have.get(name)} where {kind} is expected")
    return df


def shared_folder(spark: SparkSession) -> str:
    """The folder that the cluster shares for checkpoints; a temporary one only if none is set and all runs on one machine."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    current = spark.sparkContext._jsc.sc().getCheckpointDir()
    path = path or (current.get() if current.isDefined() else None)
    if not path:
        if not spark.sparkContext.master.split("[")[0] == "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that all machines share")
        path = tempfile.mkdtemp(prefix="trainscape-")
    if not current.isDefined():
        spark.sparkContext.setCheckpointDir(path)
    return path


def _hadoop(spark: SparkSession, path: str):
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark._jsc.hadoopConfiguration()), where


def exists(spark: SparkSession, path: str) -> bool:
    store, where = _hadoop(spark, path)
    return store.exists(where)


def cut_lineage(df: DataFrame) -> DataFrame:
    """df, computed once and read again from Parquet in the shared folder, so that lost executors cost no earlier step and
    joins know its size. The files go with the session, or by `forget`."""
    spark = df.sparkSession
    path = f"{shared_folder(spark).rstrip('/')}/steps/{uuid.uuid4().hex}"
    df.write.parquet(path)
    store, where = _hadoop(spark, path)
    store.deleteOnExit(where)
    kept = spark.read.schema(df.schema).parquet(path)
    kept.step_path = path
    return kept


def forget(*steps: DataFrame) -> None:
    """Deletes the files of steps that cut_lineage wrote and nothing reads any more."""
    for df in steps:
        store, where = _hadoop(df.sparkSession, df.step_path)
        store.delete(where, True)
        store.cancelDeleteOnExit(where)


CHECKPOINT = "run_id string, worker long, epoch int, iteration int, w array<double>, dual array<double>"


def save_checkpoint(spark: SparkSession, path: str, run_id: str, rows: list[tuple]) -> None:
    """Writes (worker, epoch, iteration, w, dual) rows of a run; saving a round again replaces it."""
    frame = spark.createDataFrame([(run_id, *r) for r in rows], CHECKPOINT)
    write_table(frame, path, by=["run_id", "epoch", "iteration"])


def load_checkpoint(spark: SparkSession, path: str, run_id: str) -> list[dict]:
    """The latest saved row of each worker of a run."""
    rows = spark.read.schema(CHECKPOINT).parquet(path).where(F.col("run_id") == run_id)
    latest = rows.groupBy("worker").agg(F.max_by(F.struct("epoch", "iteration", "w", "dual"), F.struct("epoch", "iteration")).alias("s"))
    return [r.asDict() for r in latest.select("worker", "s.*").orderBy("worker").collect()]


def as_libsvm(df: DataFrame, label: str, coords: str, values: str) -> DataFrame:
    """One text line per row in libsvm form (indices from 1), for the text sink."""
    pairs = F.transform(F.array_sort(F.arrays_zip(coords, values)), lambda p: F.concat((p[coords] + 1).cast("string"), F.lit(":"), p[values].cast("string")))
    return df.select(F.concat_ws(" ", F.col(label).cast("string"), F.array_join(pairs, " ")).alias("value"))
