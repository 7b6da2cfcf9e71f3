"""What must hold for tables far larger than those of the tests: plans, passes and the memory of one task."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from tests.conftest import SF

from trainscape.functions.losses import LogisticLoss
from trainscape.operators import linear
from trainscape.plans import tasks


def test_long_sparse_models_are_not_broadcast(spark):
    x, y, meta = tasks.task_ctr(spark, SF)
    model = spark.range(meta.dims).select(F.col("id").cast("int").alias("coord"), F.lit(0.1).alias("value"))
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plans = [linear.sparse_gradient(x, y, model, LogisticLoss(), "event_id", dims)._jdf.queryExecution().executedPlan().toString() for dims in (meta.dims, 47_236)]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    assert "BroadcastExchange" not in plans[0] and "BroadcastExchange" in plans[1]


def test_packed_sums_equal_the_gradient_for_one_worker_in_many_tasks(spark):
    rows = [(i, "train" if i % 5 else "validation", 0, i % 3, 1.0 if i % 2 else -1.0, i / 50.0, None if i == 7 else 1.0 - i / 30.0) for i in range(60)]
    df = spark.createDataFrame(rows, "id int, split string, worker int, batch int, y double, a double, b double").repartition(4)
    blocks, w, loss = linear.pack(df, ["a", "b"]), np.array([0.3, -0.2, 0.1]), LogisticLoss()
    sums = linear.packed_sums(blocks.where("fit"), w, loss)[-1]
    want, n = linear.gradient(df.where("split = 'train'"), w, ["a", "b"], loss)
    assert sums[-1] == n and np.allclose(sums[:-1] / n, want)
    value = linear.packed_sums(blocks.where("not fit"), w, loss, value=True)[-1]
    assert np.isclose(value[0] / value[1], linear.eval_loss(df.where("split = 'validation'"), w, ["a", "b"], loss))
    assert blocks.where("fit").groupBy(F.spark_partition_id()).count().count() > 1  # a single worker's rows stay where they lie
    blocks.unpersist()


def test_experiments_join_the_tables_once(spark, monkeypatch):
    from trainscape.plans import experiments

    joined, inner = [], tasks._dense28_joined
    monkeypatch.setattr(tasks, "_dense28_joined", lambda *a: joined.append(1) or inner(*a))
    assert experiments.workers_in_training(spark, SF, (2, 3)).count() == 4 and len(joined) == 1
    assert spark.conf.get("spark.sql.codegen.hugeMethodLimit") == "65535"


READERS = "async_schedule breakdown_phases cache_threads channel_relative cost_grid_pareto design_space instance_scatter memory_failures model_validation pattern_table payload_reduce published_channels".split()


@pytest.mark.parametrize("name", READERS)
def test_query_loads_a_given_table(spark, monkeypatch, name):
    from trainscape import queries

    seen = []

    class Loaded(Exception):
        pass

    def load(_, __, table, cols=None):
        seen.append(table)
        raise Loaded

    monkeypatch.setattr(queries, "load", load)
    monkeypatch.setattr(tasks, "load", load)
    with pytest.raises(Loaded):
        queries.QUERIES[name](spark, SF)
    assert seen in (["events"], ["documents"], ["lineitem"])


def test_pipeline_stages_bound_the_texts_that_python_takes_at_once(spark):
    import corpus_pipeline

    def largest(batches):
        yield pa.RecordBatch.from_pydict({"n": pa.array([max(b.nbytes for b in batches)], pa.int64())})

    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(name)
    try:
        docs = spark.range(0, 400, 1, 1).select(F.col("id").alias("doc_id"), F.repeat(F.lit("word "), 10_000).alias("text"), F.lit("en").alias("lang"), F.lit("s").alias("source"), F.lit(50_000).cast("long").alias("n_chars"))
        corpus_pipeline.without_secrets(spark, docs, SF)
        assert docs.mapInArrow(largest, "n long").first()["n"] < 2 * corpus_pipeline.BATCH_BYTES  # 20 MB in one batch otherwise
    finally:
        spark.conf.set(name, before)


def test_presets_of_a_task_share_its_rows(spark, monkeypatch):
    from trainscape.plans import experiments

    made, inner = [], tasks.task_dense28
    monkeypatch.setattr(tasks, "task_dense28", lambda *a, **k: made.append(1) or inner(*a, **k))
    got = experiments.presets_end_to_end(spark, SF, ("w1_lr", "w1_svm", "w1_kmeans"), 1).collect()
    assert {r["preset"] for r in got} == {"w1_lr", "w1_svm", "w1_kmeans"} and len(made) == 1


def test_sparse_passes_equal_the_joins(spark):
    x, y, meta = tasks.task_ctr(spark, SF)
    rows, _ = tasks.ctr_rows(spark, SF)
    fit, loss = y.where("split = 'train'"), LogisticLoss()
    w = np.random.default_rng(1).normal(size=meta.dims)
    own = x.join(fit.select("event_id"), "event_id", "left_semi").persist()
    at = [r["coord"] for r in own.select("coord").distinct().collect()]
    model = spark.createDataFrame([(c, float(w[c])) for c in at], "coord int, value double")
    want = {r["coord"]: r["g"] for r in linear.sparse_gradient(own, fit, model, loss, "event_id", meta.dims).collect()}
    for given in (rows.where("split = 'train'"), linear.sparse_rows(own, fit, "event_id")):
        value, n, g = linear.sparse_pass(given, w, loss)
        assert n == fit.count() and np.isclose(value / n, linear.sparse_loss(own, fit, model, loss, "event_id"))
        assert set(np.flatnonzero(g)) <= set(want) and all(np.isclose(g[c] / n, v) for c, v in want.items())
    lone = linear.sparse_rows(own.limit(0), fit, "event_id")
    assert np.isclose(linear.sparse_train(lone, loss, 1.0, 2, meta.dims), np.log(2)).all()
