from pyspark.sql import functions as F

from trainscape.operators import patterns
from trainscape.plans import experiments as X
from trainscape.plans import pricing, sql
from trainscape.queries import RUNS
from trainscape.sources.tables import load
from trainscape.streaming import retrain

SF = "/root/testdata/sf0.001"


def test_admm_needs_fewest_synchronisations(spark):
    got = {r["algorithm"]: r for r in X.compare_algorithms(spark, "/root/testdata/sf0.01", batches=5, limits={"ga": 10, "ma": 30, "admm": 6}).collect()}
    assert got["admm"]["status"] == got["ma"]["status"] == "threshold"
    assert got["admm"]["syncs"] < got["ma"]["syncs"] < got["ga"]["syncs"]
    assert X.admm_on_network_is_refused()


def test_channel_orderings(spark):
    r = {(x["run"], x["channel"]): x["slowdown"] for x in X.channel_table(spark, RUNS).collect()}
    assert r["lr_w10", "cache_mt"] > 1 and r["lr_w10", "kv_db"] < 1 and r["conv_w10", "cache_mt"] < 1 and r["conv_w10", "kv_db"] is None and r["conv_w50", "vm_ps"] > 1
    s = {(x["m_mb"], x["w"]): x["ratio"] for x in X.single_against_multi_thread(spark).collect()}
    assert s[0.000224, 2] < 1.05 and s[89.0, 50] > 3


def test_servers_and_patterns(spark):
    t = [r["seconds"] for r in X.rpc_servers(spark).orderBy("servers").collect()]
    assert (t[0] - t[-1]) / t[0] < 0.05
    p = {r["model"]: r["all_reduce_s"] / r["scatter_reduce_s"] for r in X.pattern_table(spark).collect()}
    assert p["residual"] > 1.6 and p["lr"] < 1
    assert X.pattern_timings(spark, 80_000, 4).count() == 3
    assert patterns.payload(spark, 224, 3).count() == 84


def test_async_is_faster_a_step_and_less_stable(spark):
    r = X.sync_against_async(spark, SF, {0: 1.0, 1: 1.0, 2: 3.0}, 6).collect()
    a, b = ([(x["sim_s"], x["loss"]) for x in sorted(r, key=lambda x: x["step"]) if x["protocol"] == p] for p in ("async", "bsp"))
    rises = lambda v: sum(y[1] > x[1] for x, y in zip(v, v[1:]))
    assert a[0][0] < b[0][0] and rises(a) >= rises(b)


def test_replayed_systems(spark):
    r = {(x["infra"], x["phase"]): x["seconds"] for x in X.end_to_end(spark, SF, rounds=2).collect()}
    total = lambda i: r[i, "total"]
    assert r["fs_object_store", "startup"] < 2 < 120 <= r["vc_net_t2_medium", "startup"]
    assert total("fs_object_store") < total("vc_net_t2_medium") and total("fs_object_store") - r["fs_object_store", "startup"] > total("vc_net_t2_medium") - r["vc_net_t2_medium", "startup"]
    assert r["fs_cache_mt", "communicate"] < r["fs_object_store", "communicate"]
    assert pricing.Profile.vc_gpu("older").price > pricing.Profile.vc_gpu().price and pricing.Profile.hadoop_ps(3, 200).speed < 1


def test_model_agrees_with_replay(spark):
    assert X.validate_model(spark, (1, 5)).agg(F.max("rel_error")).first()[0] < 1e-3


def test_sweeps(spark):
    w = X.workers_sweep(spark)
    assert w.where("on_front").count() > 0 and w.count() == 4 * 54
    gpu = {(r["infra"], r["lr"]): r["runtime_s"] for r in X.instance_scatter(spark).collect()}
    assert gpu["gpu", 0.1] < gpu["vc", 0.1] < gpu["vc", 0.01]
    losses = [r["loss"] for r in X.batch_sweep(spark, SF).collect()]
    assert max(losses) - min(losses) < 0.1
    assert sorted(tuple(r) for r in X.memory_failures(spark).collect()) == [("fs", 32, True), ("fs", 64, False), ("vc", 32, True), ("vc", 64, True)]


def test_sql_surface(spark):
    from trainscape.plans import analytic

    sql.register(spark, SF)
    p = analytic.parameter_grid(spark, [("t", "x", 8000.0, 0.000224, 10.0, 90.0, 0.0)], [10])
    got = spark.sql("select runtime_fs(10, 8000D, 0.000224D, 10D, 90D) f, runtime_vc(10, 8000D, 0.000224D, 10D, 90D) v, dollars('fs', 10, 100D) d").first()
    assert abs(got["f"] - analytic.runtime_fs(p).first()["runtime_s"]) < 1e-9 and abs(got["v"] - analytic.runtime_vc(p).first()["runtime_s"]) < 1e-9 and got["d"] > 0
    assert spark.sql("select * from design_grid(8)").count() == 48
    assert spark.sql("select count(*) n from dense28 join orders on l_orderkey = o_orderkey").first()["n"] == 6000


def test_stateful_user_models_equal_batch(spark, tmp_path):
    events = load(spark, SF, "events")
    folder = str(tmp_path / "in")
    for i in range(2):
        events.where(F.col("event_id") >= 500 if i else F.col("event_id") < 500).coalesce(1).write.mode("append").parquet(f"{folder}/{i}")
    latest = {}

    def keep(df, _):
        latest.update({r["user_id"]: (r["n"], r["w"]) for r in df.collect()})

    q = retrain.user_models(retrain.event_stream(spark, f"{folder}/*")).writeStream.foreachBatch(keep).outputMode("update").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert sum(n for n, _ in latest.values()) == 1000


def test_request_and_completion_join(spark):
    e = load(spark, SF, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    got = retrain.completions(e.where("event_type = 'signup'"), e.where("event_type = 'purchase'"), "6 hours").count()
    a, b = (e.where(f"event_type = '{t}'").toPandas() for t in ("signup", "purchase"))
    want = sum(((b["user_id"] == r.user_id) & (b["ts"] >= r.ts) & ((b["ts"] - r.ts).dt.total_seconds() <= 21600)).sum() for r in a.itertuples())
    assert got == want
