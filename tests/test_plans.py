import pytest
from pyspark.sql import functions as F

from trainscape.operators import features, joins, metrics, patterns
from trainscape.plans import analytic, channels, constants, designs, lifetime, pipeline, tasks, whatif
from trainscape.plans.job import ItemTooLarge, IterationTooLong
from trainscape.sources import tables
from trainscape.streaming import retrain


def test_communication_sanity_values(spark):
    """Seconds a round for 224 bytes, 12 MB and 89 MB."""
    cases = [("m224", "x", 0.0, 0.000224, 1.0, 0.0, 0.0), ("m12", "x", 0.0, 12.0, 1.0, 0.0, 0.0), ("m89", "x", 0.0, 89.0, 1.0, 0.0, 0.0)]
    p = analytic.parameter_grid(spark, cases, [10, 50])
    get = lambda df: {(r["task"], r["w"]): r["comm_s"] for r in df.collect()}
    store, cache, net = get(analytic.runtime_fs(p)), get(analytic.runtime_fs(p, "cache_t3_medium")), get(analytic.runtime_vc(p))
    near = lambda a, b: abs(a - b) <= 0.01 * b
    assert near(store["m224", 10], 2.24) and near(cache["m224", 10], 0.28) and near(net["m224", 10], 0.009)
    assert near(store["m224", 50], 11.84) and near(cache["m224", 50], 1.48) and near(net["m224", 50], 0.049)
    assert near(store["m12", 10], 2.757) and near(cache["m12", 10], 0.333) and near(net["m12", 10], 0.189)
    assert near(store["m89", 10], 6.07) and near(cache["m89", 10], 0.676) and near(net["m89", 10], 1.344)


def test_startup_hits_the_points(spark):
    df = spark.createDataFrame([(10,), (50,), (100,), (200,)], "w int")
    got = df.select(constants.startup(F.col("w"), "fs"), constants.startup(F.col("w"), "vc")).collect()
    assert [tuple(round(v, 9) for v in r) for r in got] == [(1.2, 132.0), (11.0, 160.0), (18.0, 292.0), (35.0, 606.0)]


def test_pipeline_prices():
    for infra, seconds, dollars in (("fs", 96, 0.47), ("fs", 1712, 8.37), ("vc", 233, 0.31), ("vc", 1350, 1.74)):
        assert abs(pipeline.price_pipeline(seconds, infra=infra) / dollars - 1) < 0.03


def test_pattern_ratio_by_model_size(spark):
    from trainscape.operators.patterns import transfers

    def ratio(m, w):
        cost = []
        for p in ("all_reduce", "scatter_reduce"):
            n, parts = transfers(p, "object_store", w)
            cost.append(n * (m / parts / 65 + 0.08))
        return cost[0] / cost[1]

    assert ratio(89, 10) > 1.6 and ratio(0.000224, 50) < 1


def test_channels_replay(spark):
    runs = spark.createDataFrame([("lr", 10, 0.000224, 10.0, 30.0), ("conv", 10, 12.0, 600.0, 900.0)], "run string, w int, m_mb double, rounds double, base_s double")
    r = {(x["run"], x["channel"]): x for x in channels.relative(channels.replay(runs)).collect()}
    assert r["lr", "cache_mt"]["slowdown"] > 1 > r["lr", "kv_db"]["slowdown"] and r["conv", "cache_mt"]["slowdown"] < 1
    assert r["conv", "kv_db"]["slowdown"] is None and r["lr", "vm_ps"]["slowdown"] > 1
    assert r["lr", "cache_mt"]["simulated"]
    channels.check_item("kv_db", 400_000)
    with pytest.raises(ItemTooLarge):
        channels.check_item("kv_db", 401_000)


def test_file_channel_rounds(spark, tmp_path):
    c = channels.FileChannel(spark, str(tmp_path / "channel"))
    for j in range(3):
        c.send(spark.createDataFrame([(j, 0, float(j), 1.0)], "worker int, coord int, value double, weight double"), 0, 0, j)
    c.await_count(0, 0, 3)
    with pytest.raises(TimeoutError):
        c.await_count(0, 0, 4, timeout_s=0.2)
    c.publish(patterns.scatter_reduce(c.merge(0, 0, 3)), 0, 0)
    assert c.fetch(0, 0).first()["value"] == 1.0


def test_lifetime(spark):
    t = spark.createDataFrame([(0, i, 500.0) for i in range(2)], "worker int, step int, seconds double")
    assert [r["incarnation"] for r in lifetime.apply_lifetime(t).orderBy("step").collect()] == [0, 1]
    with pytest.raises(IterationTooLong) as e:
        lifetime.check_iterations(spark.createDataFrame([(0, 0, 901.0)], "worker int, step int, seconds double"), 64)
    assert e.value.suggested_batch == 63


def test_pareto_keeps_duplicates(spark):
    df = spark.createDataFrame([("a", 1.0, 5.0), ("a", 2.0, 3.0), ("a", 2.0, 3.0), ("a", 3.0, 4.0), ("a", 2.0, 9.0)], "t string, runtime_s double, dollars double")
    assert sorted((r["runtime_s"], r["dollars"]) for r in analytic.pareto(df, ["t"]).collect()) == [(1.0, 5.0), (2.0, 3.0), (2.0, 3.0)]


def test_whatif_shapes(spark):
    p = analytic.parameter_grid(spark, workers=[10])
    f = {(r["task"], r["algo"], r["design"]): r["runtime_s"] for r in whatif.whatif_fast_link(p).collect()}
    conv = lambda d: f["conv_image", "ga", d]
    assert conv("hp_fast") < conv("vc") and conv("vc_gpu") < conv("hp_fast") and conv("hp_fast") < conv("hp")
    assert f["lr_wide", "admm", "hp_fast"] > f["lr_wide", "admm", "fs"]
    h = {(r["task"], r["algo"], r["design"]): r["runtime_s"] for r in whatif.whatif_hot_data(analytic.parameter_grid(spark, workers=[10])).collect()}
    assert h["lr_wide", "admm", "vc"] < h["lr_wide", "admm", "fs"]


def test_choices():
    assert designs.choose_gradient_path(28, 1, 224) == "native" and designs.choose_gradient_path(4096, 1, 32768) == "arrow" and designs.choose_gradient_path(47_236, 0.001, 377_888) == "sparse"
    assert designs.recommend_algorithm(True, 1e7, 1e4, 1.0, 5.0) != "ga" and designs.recommend_algorithm(False, 1e7, 1e4, 1.0, 5.0) == "ma"
    assert tasks.preset("w1_lr")["threshold"] == 0.66


def test_minmax_edges(spark):
    df = spark.createDataFrame([(1.0, 5.0, None), (3.0, 5.0, 1.0)], "a double, b double, c double")
    got = features.minmax_apply(df, features.minmax_fit(df, ["a", "b", "c"]), ["a", "b", "c"]).collect()
    assert [tuple(r) for r in got] == [(-1.0, 0.0, 0.0), (1.0, 0.0, 0.0)]


def test_auc_and_class_edges(spark):
    df = spark.createDataFrame([(1, 0.9), (1, 0.4), (0, 0.4), (0, 0.1)], "l int, s double")
    assert metrics.auc(df, "l", "s").first()["auc"] == 0.875
    assert metrics.auc(df.where("l = 1"), "l", "s").first()["auc"] is None
    none = spark.createDataFrame([(-1.0, -1.0)], "y double, label_hat double")
    assert metrics.class_metrics(none).first()["precision"] == 0.0


def test_as_of_and_overlaps(spark):
    left = spark.createDataFrame([(1, 5.0), (1, 0.5), (2, 9.0)], "k int, t double")
    right = spark.createDataFrame([(1, 1.0, "a"), (1, 5.0, "b"), (1, 7.0, "c")], "k int, u double, v string")
    assert sorted((r["k"], r["t"], r["v"]) for r in joins.as_of(left, right, ["k"], "t", "u", "v").collect() if r["v"]) == [(1, 5.0, "b")]
    a = spark.createDataFrame([(1, 0.0, 25.0), (2, 30.0, 31.0)], "i int, a double, b double")
    b = spark.createDataFrame([(7, 5.0, 40.0), (8, 25.0, 26.0)], "j int, c double, d double")
    assert sorted((r["i"], r["j"]) for r in joins.overlaps(a, b, ("a", "b"), ("c", "d"), 10.0).collect()) == [(1, 7), (2, 7)]


def test_missing_workers(spark):
    listing = spark.createDataFrame([(0, 0, 0), (0, 0, 2)], "epoch int, iteration int, partition int")
    assert [r["worker"] for r in patterns.missing_workers(listing, spark.createDataFrame([(0,), (1,), (2,)], "worker int")).collect()] == [1]


def test_tables_round_trips(spark, tmp_path):
    df = spark.createDataFrame([(1, "a"), (2, "b")], "x int, k string")
    tables.write_table(df, str(tmp_path / "t"), by=["k"])
    tables.write_table(df.where("k = 'a'").withColumn("x", F.lit(9)), str(tmp_path / "t"), by=["k"])
    assert sorted(r["x"] for r in tables.read_any(spark, str(tmp_path / "t")).collect()) == [2, 9]
    with pytest.raises(tables.SchemaMismatch):
        tables.read_any(spark, "x", "csv")
    with pytest.raises(tables.SchemaMismatch):
        tables.check_schema(df, {"x": "long"})
    sparse = spark.createDataFrame([(1.0, [2, 0], [0.5, 1.5])], "y double, c array<int>, v array<double>")
    line = tables.as_libsvm(sparse, "y", "c", "v")
    line.write.text(str(tmp_path / "svm"))
    assert spark.read.format("libsvm").option("numFeatures", 3).load(str(tmp_path / "svm")).first()["features"].toArray().tolist() == [1.5, 0.0, 0.5]


def test_stream_is_batch_equivalent_and_replays_once(spark, tmp_path):
    events = tables.load(spark, "/root/testdata/sf0.001", "events")
    folder = str(tmp_path / "in")
    for i in range(3):
        events.where(F.col("event_id") % 3 == i).coalesce(1).write.mode("append").parquet(folder)
    t = retrain.Retrainer()
    history = t.run(retrain.event_stream(spark, folder), str(tmp_path / "ck"))
    assert len(history) == 3 and sum(h[1] for h in history) == 1000
    before = t.w.copy()
    t.apply(events, 1)
    assert (t.w == before).all()


def test_watermark_drops_late_rows(spark, tmp_path):
    base = spark.createDataFrame([(1, 1, "2024-01-01 00:00:00"), (2, 1, "2024-01-01 10:00:00")], "event_id long, user_id long, ts string")
    late = spark.createDataFrame([(3, 1, "2024-01-01 00:05:00"), (4, 1, "2024-01-02 00:00:00")], "event_id long, user_id long, ts string")
    make = lambda d: d.select("event_id", F.col("ts").cast("timestamp_ntz").alias("ts"), "user_id", F.lit("view").alias("event_type"), F.lit(1.0).alias("value"), F.lit("{}").alias("props")).coalesce(1)
    folder = str(tmp_path / "late")
    make(base).write.parquet(folder)
    stream = retrain.arrivals(retrain.event_stream(spark, folder), watermark="10 minutes")

    def drain():
        q = stream.writeStream.format("parquet").outputMode("append").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
        q.awaitTermination()
        return sorted((str(r["start"]), r["n"]) for r in spark.read.parquet(str(tmp_path / "out")).collect())

    drain()
    make(late).write.mode("append").parquet(folder)
    assert drain() == [("2024-01-01 00:00:00", 1), ("2024-01-01 10:00:00", 1)]


def test_plans_stay_native_and_pruned(spark):
    from trainscape.operators.linear import score

    df, _ = tasks.task_dense28(spark, "/root/testdata/sf0.001")
    plan = df.select(score([0.1] * 29, tasks.DENSE).alias("s"))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "CartesianProduct" not in plan
    one = tables.load(spark, "/root/testdata/sf0.001", "orders").where("o_orderkey < 10").select("o_orderkey")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(o_orderkey), LessThan(o_orderkey,10)]" in one and "o_totalprice" not in one
