import numpy as np
import pytest
from pyspark.sql import functions as F

from trainscape.functions.losses import HingeLoss, LogisticLoss
from trainscape.operators import asynchronous, clustering, linear, nets, partition, patterns
from trainscape.plans import job as J
from trainscape.sources.tables import load_checkpoint

FEATS = ["f0", "f1", "f2"]


@pytest.fixture(scope="module")
def data(spark):
    r = np.random.default_rng(3)
    x = r.normal(size=(600, 3))
    y = np.where(x @ [1.0, -2.0, 0.5] + 0.3 + r.normal(size=600) > 0, 1.0, -1.0)
    rows = [(i, *map(float, x[i]), float(y[i]), int(i % 4), int(i // 4 % 3), "validation" if i % 10 == 0 else "train") for i in range(600)]
    df = spark.createDataFrame(rows, "id long, f0 double, f1 double, f2 double, y double, worker int, batch int, split string").cache()
    return df, np.column_stack([x, np.ones(600)]), y, np.array([r[5] for r in rows]), np.array([r[6] for r in rows]), np.array([r[7] == "train" for r in rows])


def grad(loss, w, x, y):
    m = y * (x @ w)
    return (loss.np_slope(m) * y) @ x / len(y) + loss.l2 * np.append(w[:-1], 0)


def run(df, **kw):
    stop = J.StopRule(max_rounds=kw.pop("rounds", 2))
    return linear.train(df, FEATS, ["id"], J.JobSpec(stop=stop, lr=J.LrSchedule(0.3), workers=4, batches=3, **kw))


@pytest.mark.parametrize("loss", [LogisticLoss(0.01), HingeLoss(0.01), HingeLoss(squared=True)])
def test_slopes_are_derivatives(loss):
    m = np.linspace(-3, 3, 41) + 0.013
    numeric = (loss.np_value(m + 1e-6) - loss.np_value(m - 1e-6)) / 2e-6
    assert np.allclose(loss.np_slope(m), numeric, atol=1e-5)


def test_column_and_block_losses_agree(spark):
    m = [-800.0, -2.0, 0.0, 0.5, 1.0, 900.0]
    df = spark.createDataFrame([(v,) for v in m], "m double")
    for loss in (LogisticLoss(), HingeLoss(), HingeLoss(squared=True)):
        got = df.select(loss.value(F.col("m")).alias("v"), loss.slope(F.col("m")).alias("s")).toPandas()
        assert np.allclose(got["v"], loss.np_value(np.array(m))) and np.allclose(got["s"], loss.np_slope(np.array(m)))


def test_ga_equals_numpy(data):
    df, x, y, worker, batch, fit = data
    w = np.zeros(4)
    for _ in range(2):
        for t in range(3):
            at = fit & (batch == t)
            w = w - 0.3 * grad(LogisticLoss(), w, x[at], y[at])
    assert np.allclose(run(df, algorithm="ga").w, w, atol=1e-10)


@pytest.mark.parametrize("weighted", [True, False])
@pytest.mark.parametrize("sync", [None, 1, 2])
def test_ma_equals_numpy(data, weighted, sync):
    df, x, y, worker, batch, fit = data
    w = np.zeros(4)
    for _ in range(2):
        for first in range(0, 3, sync or 3):
            own, n = [], []
            for j in range(4):
                v, seen = w.copy(), 0
                for t in range(first, min(3, first + (sync or 3))):
                    at = fit & (worker == j) & (batch == t)
                    v, seen = v - 0.3 * grad(LogisticLoss(), v, x[at], y[at]), seen + at.sum()
                own.append(v)
                n.append(seen if weighted else 1)
            w = np.average(own, axis=0, weights=n)
    assert np.allclose(run(df, algorithm="ma", weighted=weighted, sync_every=sync).w, w, atol=1e-10)


def test_admm_equals_numpy_and_converges(data):
    df, x, y, worker, batch, fit = data
    z, xs, us = np.zeros(4), np.zeros((4, 4)), np.zeros((4, 4))
    for _ in range(2):
        for j in range(4):
            for _ in range(3):
                for t in range(3):
                    at = fit & (worker == j) & (batch == t)
                    xs[j] = xs[j] - 0.3 * (grad(LogisticLoss(), xs[j], x[at], y[at]) + 0.1 * (xs[j] - z + us[j]))
        z = (xs + us).mean(0)
        us = us + xs - z
    result = run(df, algorithm="admm", inner_epochs=3)
    assert np.allclose(result.w, z, atol=1e-10)
    more = run(df, algorithm="admm", inner_epochs=3, rounds=6)
    assert more.history[-1]["primal"] < more.history[0]["primal"] and more.history[-1]["loss"] < more.history[0]["loss"]


def test_one_worker_one_step_all_agree(data):
    df = data[0].withColumn("worker", F.lit(0)).withColumn("batch", F.lit(0))
    ga, ma = (linear.train(df, FEATS, ["id"], J.JobSpec(a, lr=J.LrSchedule(0.3), workers=1, batches=1)).w for a in ("ga", "ma"))
    assert np.allclose(ga, ma, atol=1e-10)


def test_result_does_not_depend_on_partitions(data):
    df = data[0]
    assert np.allclose(run(df.repartition(1), algorithm="ma").w, run(df.repartition(13), algorithm="ma").w, atol=1e-9)


def test_checkpoint_resume_gives_the_same_model(spark, data, tmp_path):
    df, path = data[0], str(tmp_path / "ck")
    spec = dict(algorithm="admm", lr=J.LrSchedule(0.3), workers=4, batches=3, inner_epochs=2)
    whole = linear.train(df, FEATS, ["id"], J.JobSpec(stop=J.StopRule(max_rounds=3), **spec))
    first = linear.train(df, FEATS, ["id"], J.JobSpec(stop=J.StopRule(max_rounds=2), run_id="a", **spec), checkpoint=path)
    saved = {r["worker"]: r for r in load_checkpoint(spark, path, "a")}
    rest = linear.train(df, FEATS, ["id"], J.JobSpec(stop=J.StopRule(max_rounds=1), **spec), resume=saved)
    assert np.allclose(saved[-1]["w"], first.w) and np.allclose(whole.w, rest.w, atol=1e-10)
    two = J.JobSpec("ma", lr=J.LrSchedule(0.3), workers=4, batches=3, stop=J.StopRule(max_rounds=2), run_id="b")
    one = J.JobSpec("ma", lr=J.LrSchedule(0.3), workers=4, batches=3, stop=J.StopRule(max_rounds=1), run_id="b")
    linear.train(df, FEATS, ["id"], one, checkpoint=path)
    again = linear.train(df, FEATS, ["id"], one, resume={r["worker"]: r for r in load_checkpoint(spark, path, "b")})
    assert np.allclose(again.w, linear.train(df, FEATS, ["id"], two).w, atol=1e-10)


def test_refusals_and_stops(data):
    with pytest.raises(J.NonConvexModelError):
        J.JobSpec("admm", loss=nets.SeparableConvNet()).validate()
    with pytest.raises(J.OutOfWorkerMemory):
        J.check_memory(89_000_000, 64, 40_000_000)
    assert J.check_memory(89_000_000, 32, 40_000_000) and J.check_memory(89_000_000, 64, 40_000_000, 64)
    assert J.StopRule(0.5).reason(1, 0.4, 1.0) == "threshold" and J.StopRule().reason(1, float("nan"), 1.0) == "diverged"
    result = run(data[0], algorithm="ma", rounds=1)
    sent = [r for r in result.trace_rows if r[5] == "communicate"]
    assert len(sent) == 4 and all(r[7] == 3 * 4 - 2 and r[8] == 10 * 8 * 4 // 4 for r in sent)
    assert sum(r[6] for r in result.trace_rows if r[5] == "compute") == 540


def test_empty_and_missing_workers(spark, data):
    df = data[0].where("worker < 2")
    assert np.isfinite(run(df, algorithm="ma").w).all() and np.isfinite(run(df, algorithm="admm", inner_epochs=1).w).all()
    none = data[0].where("id < 0")
    assert (linear.train(none, FEATS, ["id"], J.JobSpec("ga", workers=2, batches=1, stop=J.StopRule(max_rounds=1))).w == 0).all()


def test_tune_equals_single_runs(data):
    df = data[0]
    tuned = {r["lr"]: r["loss"] for r in linear.tune_lr(df, FEATS, LogisticLoss(), [0.1, 0.5], 1, 3).collect()}
    one = linear.train(df, FEATS, ["id"], J.JobSpec("ga", lr=J.LrSchedule(0.5), workers=4, batches=3, stop=J.StopRule(max_rounds=1)))
    assert abs(tuned[0.5] - one.history[-1]["loss"]) < 1e-12


def test_sparse_equals_dense(spark, data):
    df = data[0]
    x = df.select("id", F.posexplode(F.array(*FEATS)).alias("coord", "value"))
    y = df.select("id", "y")
    model = spark.createDataFrame([(0, 0.2), (2, -0.1)], "coord int, value double")
    g = {r["coord"]: r["g"] for r in linear.sparse_gradient(x, y, model, LogisticLoss(), "id", 3).collect()}
    dense, _ = linear.gradient(df, np.array([0.2, 0.0, -0.1, 0.0]), FEATS, LogisticLoss())
    assert np.allclose([g[i] for i in range(3)], dense[:3])
    stepped = {r["coord"]: r["value"] for r in linear.sparse_step(model, linear.sparse_gradient(x, y, model, LogisticLoss(), "id", 3, 0), 0.5).collect()}
    assert abs(stepped[1] + 0.5 * dense[1]) < 1e-12


def test_kmeans_steps_and_empty_cluster(spark):
    df = spark.createDataFrame([(0, 0.0), (1, 0.2), (2, 10.0)], "id long, f0 double")
    c, loss, n = clustering.em_step(df, np.array([[0.0], [9.0], [50.0]]), ["f0"])
    assert np.allclose(c, [[0.1], [10.0], [50.0]]) and n == 3 and abs(loss - (0.04 + 1) / 3) < 1e-12
    centroids, losses = clustering.em_kmeans(df, ["f0"], 5, ["id"], 3)
    assert len(centroids) == 3 and all(a >= b for a, b in zip(losses, losses[1:]))
    spread, _ = clustering.em_kmeans(df, ["f0"], 2, ["id"], 4, init="spread")
    assert sorted(round(float(v), 3) for v in spread.ravel()) == [0.1, 10.0]


def test_kmeans_blocks_equal_native(data, monkeypatch):
    df = data[0]
    start = clustering.first_rows(df, FEATS, 4, ["id"])
    native = clustering.em_step(df, start, FEATS)
    monkeypatch.setattr(clustering, "NATIVE_TERMS", 0)
    blocks = clustering.em_step(df, start, FEATS)
    assert np.allclose(native[0], blocks[0]) and abs(native[1] - blocks[1]) < 1e-9


def test_patterns_agree(spark):
    r = np.random.default_rng(1)
    rows = [(j, c, float(r.normal()), float(j + 1)) for j in range(7) for c in range(11)]
    s = spark.createDataFrame(rows, "worker int, coord int, value double, weight double")
    want = {c: sum(v * w for _, d, v, w in rows if d == c) / 28 for c in range(11)}
    for p in patterns.PATTERNS:
        got = {x["coord"]: x["value"] for x in patterns.reduce_with(p, s, 7).collect()}
        assert all(abs(got[c] - want[c]) < 1e-12 for c in want)
    assert patterns.transfers("scatter_reduce", "object_store", 10) == (28, 10) and patterns.transfers("scatter_reduce", "direct", 10) == (18, 10)
    assert patterns.transfers("all_reduce", "vm_ps", 10)[0] == 2
    assert patterns.choose_pattern(224e-6, 50, 65, 0.08) == "all_reduce" and patterns.choose_pattern(89, 10, 65, 0.08) == "scatter_reduce"
    with pytest.raises(ValueError):
        patterns.gather(s, 5)


def test_async_schedule_and_bsp_limit(spark, data):
    df = data[0]
    s = asynchronous.async_schedule(spark, {0: 1.0, 1: 3.0}, 3)
    seen = {(r["worker"], r["step"]): r["staleness"] for r in s.collect()}
    assert seen[(1, 0)] == 3 and seen[(0, 1)] == 0
    alone = asynchronous.async_schedule(spark, {0: 1.0}, 3)
    assert alone.agg(F.max("staleness")).first()[0] == 0
    one = df.withColumn("worker", F.lit(0))
    w, events = asynchronous.async_train(one, FEATS, LogisticLoss(), 0.3, alone, 3, decay=False)
    assert np.allclose(w, linear.train(one, FEATS, ["id"], J.JobSpec("ga", lr=J.LrSchedule(0.3), workers=1, batches=3, stop=J.StopRule(max_rounds=1))).w)
    assert len(events) == 3 and asynchronous.staleness_summary(s).agg(F.sum("lost")).first()[0] > 0


@pytest.mark.parametrize("net", [nets.Mlp(5, 4, 3), nets.Mlp(5, 0, 3), nets.SeparableConvNet(3, 1, 2, 2, 3), nets.ResidualNet(3, 1, 2, 2, 3)])
def test_net_gradients_are_derivatives(net):
    r = np.random.default_rng(0)
    x, y = r.normal(size=(6, 5 if isinstance(net, nets.Mlp) else 9)), r.integers(0, 3, 6)
    w = net.init(1) + 0.05 * r.normal(size=net.size)
    _, g = net.loss_grad(w, x, y)
    for i in r.choice(net.size, min(25, net.size), replace=False):
        e = np.zeros(net.size)
        e[i] = 1e-6
        assert abs((net.loss_grad(w + e, x, y)[0] - net.loss_grad(w - e, x, y)[0]) / 2e-6 - g[i]) < 1e-4


def test_nets_learn(spark):
    r = np.random.default_rng(5)
    x = r.normal(size=(200, 9))
    y = (x[:, 0] > 0).astype(int) + (x[:, 1] > 0)
    df = spark.createDataFrame([(i, i % 2, [float(v) for v in x[i]], int(y[i])) for i in range(200)], "vec_id long, worker int, x array<double>, y int")
    net = nets.Mlp(9, 8, 3)
    w, losses = nets.net_ga(df, net, 0.5, 40)
    assert losses[-1] < losses[0]
    assert nets.net_predict(df, net, w, ["vec_id"]).where("y = label_hat").count() > 150
    _, losses = nets.net_ma(df, net, 0.2, 3, 2, 4)
    assert losses[-1] < losses[0]


def test_exact_workers_are_even(spark):
    got = partition.assign_workers(spark.range(103), ["id"], 4, "exact").groupBy("worker").count().collect()
    assert sorted(r["count"] for r in got) == [25, 26, 26, 26]
    few = partition.assign_workers(spark.range(2), ["id"], 4, "exact").count()
    assert few == 2


def test_random_centroids_do_not_depend_on_layout(data):
    df = data[0]
    a, b = (clustering.random_rows(df.repartition(n), FEATS, 4, ["id"]) for n in (1, 7))
    assert (a == b).all() and not np.allclose(a, clustering.random_rows(df, FEATS, 4, ["id"], "other"))


def test_stratified_sample(spark):
    df = spark.range(4000).withColumn("s", F.when(F.col("id") % 4 == 0, "a").when(F.col("id") % 4 == 1, "b"))
    n = {r["s"]: r["count"] for r in partition.sample_stratified(df, ["id"], "s", {"a": 1.0, "b": 0.1}, 0.5).groupBy("s").count().collect()}
    assert n["a"] == 1000 and 60 < n["b"] < 140 and 900 < n[None] < 1100
