"""Hand examples, invariants and plan shapes of the training engine."""

import io

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from slicegrad.nn import models
from slicegrad.operators import optim, persist, slices
from slicegrad.operators.estimator import NetworkEstimator
from slicegrad.operators.kernel import local_train, predict, train_net
from slicegrad.operators.recovery import train_with_snapshots
from slicegrad.operators.train import Glm, minibatch, to_samples, train, train_stale, unrolled, update, weight_rows

OPTIMIZERS = [optim.Sgd(0.1), optim.Sgd(0.1, decay=0.1), optim.Momentum(0.1), optim.Momentum(0.1, nesterov=True, dampening=0.1), optim.Adagrad(0.1), optim.RmsProp(0.1), optim.Adadelta(1.0), optim.Adam(0.1), optim.Adam(0.1, decay=0.1), optim.Adamax(0.1), optim.Ftrl(0.1)]


@pytest.fixture(scope="module")
def data(spark):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(60, 5))
    y = x @ [1.0, -2.0, 0.5, 0.0, 3.0]
    return x, y, spark.createDataFrame([(i, a.tolist(), float(b)) for i, (a, b) in enumerate(zip(x, y))], "id long, x array<double>, y double").persist()


def reference(x, y, opt, rounds):
    w, s = np.zeros(x.shape[1]), {k: np.zeros(x.shape[1]) for k in opt.slots}
    for it in range(1, rounds + 1):
        w, s = opt.step_np(w, x.T @ (x @ w - y) / len(x), s, it)
    return w


def test_slicing_by_hand():
    assert [slices.ParamLayout(10, 4).bounds(s) for s in range(4)] == [(0, 2), (2, 5), (5, 7), (7, 10)]
    assert [b - a for a, b in (slices.ParamLayout(3, 5).bounds(s) for s in range(5))] == [0, 1, 0, 1, 1]


@given(st.integers(0, 500), st.integers(1, 40))
@settings(max_examples=60, deadline=None)
def test_slices_cover(k, n):
    edges = slices.ParamLayout(k, n).edges
    sizes = [b - a for a, b in zip(edges[:-1], edges[1:])]
    assert edges[0] == 0 and edges[-1] == k and max(sizes) - min(sizes) <= 1


def test_one_step_by_hand(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0], 1.0), (1, [0.0, 2.0], 2.0)], "id long, x array<double>, y double")
    samples = to_samples(df, 2)
    assert train(samples, Glm(2), optim.Sgd(0.1), 1, 2, reduce="sum").weights == pytest.approx([0.1, 0.4])
    assert train(samples, Glm(2), optim.Sgd(0.1), 1, 2).weights == pytest.approx([0.05, 0.2])


def test_stale_by_hand(spark):
    df = spark.createDataFrame([(0, [1.0], 1.0)], "id long, x array<double>, y double")
    run = lambda n, d: train_stale(to_samples(df, 1), Glm(1), 0.5, n, lambda p: F.lit(d))[0]
    assert [run(n, 1) for n in (1, 2, 3)] == [0.5, 1.0, 1.25] and [run(n, 0) for n in (1, 2, 3)] == [0.5, 0.75, 0.875]


@pytest.mark.parametrize("opt", OPTIMIZERS, ids=lambda o: type(o).__name__)
def test_optimizers_are_the_single_process(data, opt):
    x, y, df = data
    assert train(to_samples(df, 3), Glm(5), opt, 3, 2).weights == pytest.approx(reference(x, y, opt, 3).tolist())


@pytest.mark.parametrize("parts,n", [(1, 1), (2, 7), (7, 3), (16, 16)])
def test_any_split_gives_the_same(data, parts, n):
    x, y, df = data
    assert train(to_samples(df, parts), Glm(5), optim.Momentum(0.1), 2, n).weights == pytest.approx(reference(x, y, optim.Momentum(0.1), 2).tolist(), rel=1e-9)


def test_fused_split_grouped_resumed(data):
    x, y, df = data
    samples = to_samples(df, 3)
    want = reference(x, y, optim.Adam(0.1), 4).tolist()
    split = train(samples, Glm(5), optim.Adam(0.1), 4, split_jobs=True)
    assert split.weights == pytest.approx(want) and sum(r["jobs"] for r in split.ledger) == 8
    first = train(samples, Glm(5), optim.Adam(0.1), 1)
    assert train(samples, Glm(5), optim.Adam(0.1), 3, init=first).weights == pytest.approx(want)
    grouped = sorted(unrolled(samples, Glm(5), optim.Adam(0.1), 4).collect(), key=lambda r: r["slice"])
    assert [v for r in grouped for v in r["w"]] == pytest.approx(want)


def test_stops_at_the_goal(data):
    x, y, df = data
    out = train(to_samples(df, 2), Glm(5), optim.Sgd(0.3), 50, stop=lambda w: np.mean((x @ w - y) ** 2) < 1.0)
    assert out.rounds < 50 and np.mean((x @ out.weights - y) ** 2) < 1.0


@pytest.mark.parametrize("mode", ["bucket", "epoch"])
def test_minibatches_cover_an_epoch_once(data, mode):
    samples = to_samples(data[2], 3, buckets=7)
    for epoch in range(2):
        seen = [r["sample_id"] for it in range(7) for r in minibatch(samples, epoch * 7 + it, 7, mode).collect()]
        assert sorted(seen) == list(range(60))


def test_plan_has_one_exchange_by_id(spark, data):
    samples = to_samples(data[2], 3)
    layout = slices.ParamLayout(5, 2)
    grads = spark.createDataFrame([(0, 0, 1.0, 0.0, [1.0])], "producer int, slice int, n double, loss double, g array<double>")
    plan = update(grads, weight_rows(spark, layout, [0.0] * 5, {}), optim.Sgd(0.1), 1, 2)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and "hashpartitioning" not in plan and "Join" not in plan
    assert "Exchange" not in samples._jdf.queryExecution().executedPlan().toString()


def test_slice_owner_is_its_partition(spark):
    rows = spark.range(40).select((F.col("id") % 8).cast("int").alias("slice")).repartitionById(8, "slice")
    assert rows.filter(F.spark_partition_id() != F.col("slice")).isEmpty()


@pytest.mark.parametrize("way", [lambda c: slices.sliced(c, 3), lambda c: slices.central(c, 3, 2), lambda c: slices.tree(c, 3, 2), lambda c: slices.driver(c, 3), lambda c: slices.ring(c, 3, 4), lambda c: slices.barrier(c, 3, 2)])
def test_strategies_agree(spark, way):
    grads = spark.createDataFrame([(p, 1, 0, [p * 10 + j for j in range(7)]) for p in range(4)], "producer int, n long, loss long, g array<long>")
    out = {r["slice"]: r for r in way(slices.ParamLayout(7, 3).cut(grads)).collect()}
    assert [v for s in range(3) for v in out[s]["g"]] == [60 + 4 * j for j in range(7)] and all(r["n"] == 4 for r in out.values())


NETS = [
    (models.Mlp(64, 6, 4), "img"), (models.Inception(8, 4, 4), "img"), (models.Inception(8, 4, 4, "factored"), "img"), (models.Inception(8, 4, 4, "residual"), "img"),
    (models.TextConv(20, 6, 4, 5, 3, 4), "tok"), (models.Recurrent(20, 6, 4, 5, 4, "rnn"), "tok"), (models.Recurrent(20, 6, 4, 5, 4, "lstm"), "tok"), (models.Recurrent(20, 6, 4, 5, 4, "gru"), "tok"),
    (models.ConvLstm(4, 2, 3, 2), "seq"), (models.NeuMf(8, 8, 3, 4, "mf"), "ui"), (models.NeuMf(8, 8, 3, 4, "gmf"), "ui"), (models.NeuMf(8, 8, 3, 4, "mlp"), "ui"), (models.NeuMf(8, 8, 3, 4), "ui"),
]


def batch(kind, n, seed=0):
    rng = np.random.default_rng(seed)
    return {
        "img": (rng.normal(size=(n, 64)), rng.integers(0, 4, (n, 1))), "tok": (rng.integers(0, 20, (n, 6)), rng.integers(0, 4, (n, 1))),
        "seq": (rng.normal(size=(n, 48)), rng.normal(size=(n, 32))), "ui": (rng.integers(0, 8, (n, 2)), rng.integers(0, 2, (n, 1))),
    }[kind]


@pytest.mark.parametrize("net,kind", NETS, ids=lambda v: f"{type(v).__name__}-{getattr(v, 'kind', '')}" if isinstance(v, models.Net) else v)
def test_gradients_are_differences(net, kind):
    x, y = batch(kind, 4)
    theta = net.init(3) * 0.7
    _, g = net.loss_grad(theta, x, y, (1, 2, 3))
    for k in np.random.default_rng(1).choice(net.k, 25):
        d = np.zeros(net.k)
        d[k] = 1e-5
        numeric = (net.loss_grad(theta + d, x, y, (1, 2, 3))[0] - net.loss_grad(theta - d, x, y, (1, 2, 3))[0]) / 2e-5
        assert g[k] == pytest.approx(numeric, abs=1e-4)


@pytest.mark.parametrize("loss", ["mse", "l1", "smooth_l1", "bce", "hinge"])
def test_criteria(loss):
    net = models.NeuMf(4, 4, 2, 3)
    net.loss = loss
    x, y = np.array([[0, 1], [2, 3], [1, 1]]), np.array([[0], [1], [1]])
    theta = net.init(2)
    _, g = net.loss_grad(theta, x, y)
    for k in range(net.k):
        d = np.zeros(net.k)
        d[k] = 1e-6
        assert g[k] == pytest.approx((net.loss_grad(theta + d, x, y)[0] - net.loss_grad(theta - d, x, y)[0]) / 2e-6, abs=1e-4)


def frame(spark, x, y):
    return spark.createDataFrame([(i, list(map(float, a)), list(map(float, b))) for i, (a, b) in enumerate(zip(x, y))], "id long, x array<double>, y array<double>")


def test_kernel_training_is_the_single_process(spark):
    x, y = batch("ui", 40)
    net = models.NeuMf(8, 8, 3, 4)
    want, losses = local_train(x, y, net, optim.Adam(0.05), 3)
    for options in ({"parts": 3, "n": 4}, {"parts": 1, "n": 2, "threads": 3}):
        out = train_net(frame(spark, x, y), net, optim.Adam(0.05), 3, **options)
        assert out.weights == pytest.approx(want.tolist()) and [r["loss"] for r in out.ledger] == pytest.approx(losses)


WAYS = [{"publish": "replicate"}, {"publish": "replicate", "group": 3}, {"publish": "store", "group": 2}, {"wire": "f32"}, {"measure": True}, {"publish": "store", "measure": True}]


@pytest.mark.parametrize("way", WAYS, ids=str)
def test_every_way_to_publish_is_the_single_process(spark, way):
    x, y = batch("ui", 40)
    net = models.NeuMf(8, 8, 3, 4)
    want, losses = local_train(x, y, net, optim.Adam(0.05), 3)
    out = train_net(frame(spark, x, y), net, optim.Adam(0.05), 3, parts=3, **way)
    assert out.weights == pytest.approx(want.tolist(), abs=1e-6 if "wire" in way else 1e-12) and out.rounds == len(out.ledger) == 3
    assert out.ledger[-1]["loss"] == pytest.approx(losses[-1], rel=1e-5) and out.ledger[-1]["gradient_bytes"] == 3 * net.k * (4 if "wire" in way else 8)
    if way.get("measure"):
        assert all(r["compute_ms"] > 0 and r["sync_ms"] > 0 and r["dispatch_ms"] >= 0 and r["jobs"] == 2 for r in out.ledger)


def test_two_byte_gradients_come_near(spark):
    x, y = batch("img", 40)
    net = models.Mlp(64, 6, 4)
    want, _ = local_train(x, y, net, optim.Sgd(0.1), 2)
    out = train_net(frame(spark, x, y), net, optim.Sgd(0.1), 2, wire="f16")
    assert out.weights == pytest.approx(want.tolist(), abs=2e-3) and out.ledger[0]["gradient_bytes"] == 4 * net.k * 2


def test_weights_stay_in_the_cluster(spark, monkeypatch):
    """Between the start and the trained model no action brings weights to the driver."""
    from pyspark.sql.classic.dataframe import DataFrame as Frame

    brought = []
    collect = Frame.collect
    monkeypatch.setattr(Frame, "collect", lambda self: brought.append(self.columns) or collect(self))
    x, y = batch("img", 24)
    train_net(frame(spark, x, y), models.Mlp(64, 6, 4), optim.Sgd(0.1), 3, publish="replicate")
    assert len(brought) == 4 and all("v" not in c and "w" not in c for c in brought[:3]) and "v" in brought[3]


@pytest.mark.parametrize("opt,options", [(optim.Lars(0.5, decay=0.01), {}), (optim.Lamb(0.05, decay=0.01), {}), (optim.Sgd(0.5), {"clip_norm": 0.05}), (optim.Adam(0.05), {"l1": 0.01, "l2": 0.1, "clip": 0.02})], ids=str)
@pytest.mark.parametrize("publish", ["driver", "replicate"])
def test_layers_norms_and_regularisers(spark, opt, options, publish):
    x, y = batch("img", 30)
    net = models.Mlp(64, 6, 4)
    want, losses = local_train(x, y, net, opt, 3, **options)
    out = train_net(frame(spark, x, y), net, opt, 3, parts=2, n=5, publish=publish, **options)
    assert out.weights == pytest.approx(want.tolist()) and [r["loss"] for r in out.ledger] == pytest.approx(losses) and losses[-1] != losses[0]


def test_accumulated_batches_are_one_larger_batch(spark):
    x, y = batch("img", 40)
    net = models.Mlp(64, 6, 4)
    few = train_net(frame(spark, x, y), net, optim.Sgd(0.1), 1, buckets=4, accumulate=2)
    own = np.array([(i * 7919) % 4 < 2 for i in range(40)])
    want, _ = local_train(x[own], y[own], net, optim.Sgd(0.1), 1)
    assert few.weights == pytest.approx(want.tolist()) and few.ledger[0]["samples"] == own.sum()


def test_frozen_slices_are_never_sent(spark):
    x, y = batch("img", 20)
    net = models.Mlp(64, 6, 4)
    net.frozen = ("w1", "w1_b")
    out = train_net(frame(spark, x, y), net, optim.Momentum(0.1), 2, parts=2)
    assert out.ledger[0]["gradient_bytes"] == 2 * 8 * (6 * 4 + 4)


def test_plateau_and_goal(spark):
    s = optim.Plateau(0.5, patience=2)
    for v in (1.0, 0.9, 0.95, 0.91, 0.92, 0.93):
        s.seen(v)
    assert s(0.1, 9) == pytest.approx(0.025)
    goal = optim.TargetMetric(lambda w: w, 0.9, patience=2)
    assert [goal(v) for v in (0.5, 0.6, 0.55, 0.58)] == [False, False, False, True]
    assert optim.TargetMetric(lambda w: w, 0.2, higher=False)(0.1) and not optim.TargetMetric(lambda w: w, 0.2, every=2)(0.3)
    x, y = batch("img", 24)
    opt = optim.Sgd(5.0, schedule=optim.Plateau(0.1, patience=1))
    out = train_net(frame(spark, x, y), models.Mlp(64, 6, 4), opt, 6)
    assert opt.schedule.scale < 1 and len(out.ledger) == 6


def test_large_models_go_in_slices(spark):
    """A quarter of a million parameters, which as plan literals or one row an element would not run."""
    x, y = batch("img", 12)
    net = models.Mlp(64, 3_700, 4)
    out = train_net(frame(spark, x, y), net, optim.Sgd(0.1), 2, parts=2, n=8, publish="replicate", group=2)
    want, _ = local_train(x, y, net, optim.Sgd(0.1), 2)
    assert net.k > 250_000 and out.weights == pytest.approx(want.tolist())


@pytest.mark.parametrize("lag", [0, 1, 12])
def test_any_lag(spark, lag):
    df = spark.createDataFrame([(0, [1.0], 1.0)], "id long, x array<double>, y double")
    w = [0.0]
    for it in range(15):
        w.append(w[-1] - 0.05 * (w[max(0, it - lag)] - 1))
    assert train_stale(to_samples(df, 1), Glm(1), 0.05, 15, lambda p: F.lit(lag)) == pytest.approx([w[-1]])
    bounded = train_stale(to_samples(df, 1), Glm(1), 0.05, 15, lambda p, it: F.lit(100), bound=lag)
    assert bounded == pytest.approx([w[-1]])


def test_a_failed_task_alone_runs_again(spark):
    def fault(part, attempt):
        if part == 1 and attempt == 0:
            raise RuntimeError("lost")

    x, y = batch("img", 24)
    net = models.Inception(8, 4, 4)  # with dropout: a rerun must draw the same mask
    whole = train_net(frame(spark, x, y), net, optim.Sgd(0.1), 2, parts=3)
    hurt = train_net(frame(spark, x, y), net, optim.Sgd(0.1), 2, parts=3, fault=fault)
    assert hurt.weights == pytest.approx(whole.weights, rel=1e-12)


def test_snapshots_lose_rounds_not_results(spark):
    x, y = batch("ui", 20)
    net = models.NeuMf(8, 8, 2, 3)
    whole = train_net(frame(spark, x, y), net, optim.Sgd(0.1), 4)
    back, lost = train_with_snapshots(frame(spark, x, y), net, optim.Sgd(0.1), 4, every=2, fails_at={4})
    assert back.weights == pytest.approx(whole.weights) and lost == 2


def test_frozen_layers_stay(spark):
    x, y = batch("img", 20)
    net = models.Mlp(64, 6, 4)
    net.frozen = ("w1", "w1_b")
    out = np.array(train_net(frame(spark, x, y), net, optim.Sgd(0.5), 2).weights)
    moved = out != net.init(0)
    assert not moved[: 64 * 6 + 6].any() and moved[64 * 6 + 6 :].any()


def test_models_travel(spark, tmp_path):
    net = models.Mlp(5, 4, 3)
    theta = net.init(7)
    persist.save(spark, net, theta, str(tmp_path / "m"), d=5, hidden=4, classes=3)
    again, back = persist.load(spark, str(tmp_path / "m"))
    assert np.array_equal(back, theta) and again.k == net.k
    named = {k: v.value for k, v in net.params(theta).items()}
    raw = io.BytesIO()
    np.savez(raw, **named)
    (tmp_path / "w.npz").write_bytes(raw.getvalue())
    assert np.array_equal(persist.read_npz(spark, net, str(tmp_path / "w.npz")), theta)
    with pytest.raises(KeyError):
        persist.import_weights(net, {"w1": named["w1"]})
    rows = spark.createDataFrame([(0, [1.0, 0.25, -3.5])], "slice int, g array<double>")
    assert persist.from_half(persist.to_half(rows)).first()["g"] == [1.0, 0.25, -3.5]


def test_estimator_learns_the_planted_class(spark):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(300, 64))
    y = (x[:, 0] > 0).astype(int)
    df = spark.createDataFrame([(i, a.tolist(), int(b)) for i, (a, b) in enumerate(zip(x, y))], "id long, x array<double>, y int")
    model = NetworkEstimator(models.Mlp(64, 8, 2), optim.Adam(0.05), 12).fit(df)
    assert model.ledger[-1]["loss"] < model.ledger[0]["loss"]
    assert model.transform(df).filter(F.col("prediction") == F.col("y")).count() > 260


def test_prediction_keeps_pushdown(spark, tmp_path):
    x, _ = batch("img", 10)
    frame(spark, x, np.zeros((10, 1))).write.parquet(str(tmp_path / "p"))
    net = models.Mlp(64, 4, 2)
    df = predict(spark.read.parquet(str(tmp_path / "p")), net, net.init(0)).filter("id = 3").select("id", "scores")
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(id,3)" in plan and "Exchange" not in plan
    assert df.first()["scores"] == pytest.approx(net.outputs(net.init(0), x[3:4])[0].tolist())


def test_boxes():
    a, b = np.array([[0.0, 0, 2, 2]]), np.array([[1.0, 1, 3, 3]])
    assert models.iou(a, b)[0, 0] == pytest.approx(1 / 7)
    box = np.array([[0, 0, 10, 10], [1, 1, 10, 10], [20, 20, 30, 30]], dtype=float)
    assert models.suppress(box, np.array([0.9, 0.8, 0.7])) == [0, 2]
    assert models.decode(models.boxes(2, 8), np.zeros((4, 4)), 8).tolist() == models.boxes(2, 8).tolist()


def test_detector_gradient_and_criterion():
    net = models.Detector(16, 2, 3)
    rng = np.random.default_rng(0)
    x, y = rng.normal(size=(3, 256)), np.array([[0.0, 0, 8, 8], [8, 8, 16, 16], [1, 7, 8, 15]])
    theta = net.init(1)
    _, g = net.loss_grad(theta, x, y)
    for k in rng.choice(net.k, 40):
        d = np.zeros(net.k)
        d[k] = 1e-5
        assert g[k] == pytest.approx((net.loss_grad(theta + d, x, y)[0] - net.loss_grad(theta - d, x, y)[0]) / 2e-5, abs=1e-3)
    box = np.array([[1.0, 2, 7, 9]])
    assert models.decode(net.anchors[:1], models.encode(net.anchors[:1], box), 16) == pytest.approx(box)


def test_batch_norm_and_steps():
    from slicegrad.nn import tape as t

    v = t.lift(np.random.default_rng(0).normal(3, 2, (4, 5, 5, 2)))
    out = models.batch_norm(v, t.lift(np.array([2.0, 1.0])), t.lift(np.array([0.5, 0.0]))).value
    assert out.mean((0, 1, 2)) == pytest.approx([0.5, 0.0]) and out.std((0, 1, 2)) == pytest.approx([2.0, 1.0], rel=1e-3)
    seq = t.lift(np.arange(12.0).reshape(2, 3, 2))
    assert models.each_step(lambda z: z @ t.lift(np.ones((2, 1))), seq).value.shape == (2, 3, 1)


def test_gang_is_refused_without_slots(spark):
    df = spark.createDataFrame([(i, [1.0], 1.0) for i in range(40)], "id long, x array<double>, y double")
    assert slices.barrier_train(df, 1, 0.5, 3, 2) == pytest.approx([0.875])
    with pytest.raises(Exception, match="barrier|slots"):
        slices.barrier_train(df, 1, 0.5, 1, 12)


def test_drawn_items_favour_no_group(spark):
    from slicegrad.plans import apps
    from slicegrad.sources.tables import interactions

    d = "/root/testdata/sf0.001"
    had = {(r["u"], r["i"]) for r in interactions(spark, d).select("u", "i").collect()}
    drawn = [(int(r["x"][0]), int(r["x"][1])) for r in apps.taste_samples(spark, d).filter("y[0] = 0").select("x").collect()]
    assert drawn and not had & set(drawn)
    share = np.bincount([(i - u) % 4 for u, i in drawn], minlength=4) / len(drawn)
    assert (share > 0.2).all() and (share < 0.3).all()
    net = apps.recommender(spark, d)
    wide = models.NeuMf(net.shapes["emb_gu"][0], net.shapes["emb_gi"][0], 8, 8)
    n = sum(int(np.prod(s)) for k, s in net.shapes.items() if k.startswith("emb_g"))
    assert np.allclose(net.init(0)[:n], 0.1 * wide.init(0)[:n])


def test_measures_of_a_real_run(spark):
    from slicegrad.operators import measures

    x, y = batch("img", 40)
    net = models.Mlp(64, 6, 4)
    rows = [r | {"nodes": p} for p in (1, 4) for r in train_net(frame(spark, x, y), net, optim.Sgd(0.1), 3, parts=p, measure=True).ledger]
    led = measures.ledger_frame(spark, rows)
    got = {r["nodes"]: r["sync_share"] for r in measures.sync_share(led, "nodes").collect()}
    for p in (1, 4):
        own = [r for r in rows if r["nodes"] == p]
        assert got[p] == pytest.approx(sum(r["sync_ms"] for r in own) / sum(r["compute_ms"] for r in own), rel=1e-4)
    c = measures.counters(led.filter("nodes = 4")).first()
    assert (c["rounds"], c["jobs_per_round"], c["tasks_per_round"], c["gradient_bytes"]) == (3, 2, 8, 4 * 8 * net.k)
    made = [{"iter": k, "nodes": n, "tasks": 2 * n, "samples": 1000.0 * n, "wall_ms": 1000 * (0.002 * 1000 + 0.3 + 0.01 * 2 * n)} for k, n in enumerate((1, 2, 4, 8, 16))]
    made += [m | {"samples": 3 * m["samples"], "wall_ms": m["wall_ms"] + 1000 * 0.002 * 2000} for m in made]
    fit = measures.fit_cost_model(measures.ledger_frame(spark, made))
    assert fit == pytest.approx({"per_sample_s": 0.002, "fixed_s": 0.3, "per_task_s": 0.01})
    assert measures.predict_nodes(fit, 10, 1000) == pytest.approx(0.2 + 0.3 + 0.2)


def test_edges(spark):
    empty = spark.createDataFrame([], "id long, x array<double>, y double")
    assert train(to_samples(empty, 2), Glm(3), optim.Sgd(0.1), 1, 5).weights == [0.0, 0.0, 0.0]
    one = spark.createDataFrame([(0, [0.0, 0.0], 1.0)], "id long, x array<double>, y double")
    assert train(to_samples(one, 4), Glm(2), optim.Adagrad(0.1), 2, 8).weights == [0.0, 0.0]


def test_training_reads_whole_tables(spark):
    """Every interaction, every window of six and three frames, every word of a turn."""
    from slicegrad.plans import apps
    from slicegrad.sources.tables import interactions

    d = "/root/testdata/sf0.001"
    assert apps.rating_samples(spark, d).count() == interactions(spark, d).count()
    words = {r["id"]: len(r["w"]) for r in apps._turns(spark, d).collect()}
    rows = apps.token_samples(spark, d).collect()
    assert {r["id"]: sum(v > 0 for v in r["x"]) for r in rows} == words and max(words.values()) > 16
    hours = {r["hour"] for r in apps.frames(spark, d).select("hour").distinct().collect()}
    windows = apps.frame_samples(spark, d).collect()
    assert {r["id"] for r in windows} == {h for h in hours if hours >= set(range(h, h + 9))} and {(len(r["x"]), len(r["y"])) for r in windows} == {(6 * 64, 3 * 64)}


@pytest.mark.parametrize("net", [models.Recurrent(64, 386, 6, 8, 2, "lstm"), models.Recurrent(64, 386, 6, 8, 2, "gru"), models.Recurrent(64, 386, 6, 8, 2, "rnn"), models.TextConv(64, 386, 6, 8, 3, 2)], ids=["lstm", "gru", "rnn", "textconv"])
def test_memory_of_a_batch_is_bounded(net):
    """A task's batch goes through in pieces: the sums are those of its halves, and the memory doesn't grow with the rows."""
    import tracemalloc

    rng = np.random.default_rng(0)
    x, y = rng.integers(0, 64, (1600, 386)).astype(np.float64), rng.integers(0, 2, (1600, 1)).astype(np.float64)
    theta = net.init(0)
    tracemalloc.start()
    loss, g = net.loss_grad(theta, x, y)
    said = net.outputs(theta, x)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 250e6
    halves = [net.loss_grad(theta, x[a : a + 100], y[a : a + 100]) for a in range(0, 1600, 100)]
    assert loss == pytest.approx(sum(h[0] for h in halves)) and np.allclose(g, sum(h[1] for h in halves))
    assert np.allclose(said[-100:], net.outputs(theta, x[-100:])) and len(said) == 1600


def test_rounds_of_a_plan_make_no_object_a_row(spark, monkeypatch):
    """A cogroup takes the samples in Arrow, and the weights are still the single process's."""
    import slicegrad.operators.kernel as kernel

    plans = []
    real = kernel.paired_gradients

    def noted(*a):
        out = real(*a)
        plans.append(out._jdf.queryExecution().executedPlan().toString())
        return out

    monkeypatch.setattr(kernel, "paired_gradients", noted)
    x, y = batch("ui", 200)
    samples = spark.createDataFrame([(k, a.tolist(), b.tolist()) for k, (a, b) in enumerate(zip(x.astype(float), y.astype(float)))], "id long, x array<double>, y array<double>")
    net = models.NeuMf(8, 8, 3, 4)
    got = train_net(samples, net, optim.Adam(0.05), 2, publish="replicate").weights
    want, _ = local_train(x.astype(float), y.astype(float), net, optim.Adam(0.05), 2)
    assert np.allclose(got, want)
    assert "FlatMapCoGroupsInArrow" in plans[0] and "InPandas" not in plans[0]


def test_ranks_of_several_models_are_those_of_each(spark):
    from slicegrad.plans import apps

    sf = "/root/testdata/sf0.001"
    net = apps.recommender(spark, sf)
    both = apps.ranked(spark, sf, net, net.init(0), net.init(1)).orderBy("model").collect()
    assert [r["model"] for r in both] == [0, 1]
    for r, theta in zip(both, (net.init(0), net.init(1))):
        assert apps.ranked(spark, sf, net, theta).first()[1:] == r[1:]


@pytest.mark.parametrize("kind", ["gru", "lstm", "rnn"])
def test_memory_of_a_long_sequence_is_bounded(kind):
    """Of sequences longer than a span the steps between are run again: hundreds of long rows fit beside each other, and the gradient is the one kept whole."""
    import tracemalloc

    from slicegrad.nn import tape

    rng = np.random.default_rng(0)
    net = models.Recurrent(64, 4000, 6, 8, 2, kind)
    x, y = rng.integers(0, 64, (190, 4000)).astype(np.float64), rng.integers(0, 2, (190, 1)).astype(np.float64)
    theta = net.init(0)
    assert net.rows >= 190
    tracemalloc.start()
    net.loss_grad(theta, x, y)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 150e6  # every step kept: 190 * 4000 * (2 to 6) * 64 bytes
    x, y = x[:7, :50], y[:7]
    net = models.Recurrent(64, 50, 6, 8, 2, kind)
    want = net.loss_grad(theta, x, y)
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(tape, "SPAN", 16)
        got = net.loss_grad(theta, x, y)
    assert got[0] == pytest.approx(want[0]) and np.allclose(got[1], want[1])


@pytest.mark.parametrize("publish", ["driver", "replicate"])
@pytest.mark.parametrize("net", [models.Recurrent(20, 40, 4, 5, 4, "gru"), models.TextConv(20, 40, 4, 5, 3, 4)], ids=["gru", "textconv"])
def test_sequences_keep_their_own_length(spark, net, publish):
    """One long turn doesn't widen the others: rows come as they are, and the weights are those of rows filled up with zeros."""
    rng = np.random.default_rng(0)
    rows = [rng.integers(1, 20, n).astype(float).tolist() for n in (40, 0, 1, 3, 3, 17, 2, 5)]
    y = rng.integers(0, 4, (len(rows), 1)).astype(float)
    samples = spark.createDataFrame([(k, r, y[k].tolist()) for k, r in enumerate(rows)], "id long, x array<double>, y array<double>")
    got = train_net(samples, net, optim.Adam(0.05), 2, 2, publish=publish).weights
    x = np.array([r + [0.0] * (40 - len(r)) for r in rows])
    want, _ = local_train(x, y, net, optim.Adam(0.05), 2)
    assert np.allclose(got, want)
    said = {r["id"]: r["scores"] for r in predict(samples, net, got).collect()}
    assert np.allclose([said[k] for k in range(len(rows))], net.outputs(want, x))


def test_turns_have_no_more_ids_than_words(spark, tmp_path):
    """One long turn, one without text: no row of another turn grows."""
    from slicegrad.plans import apps

    turns = [(1, 0, "user", "word " * 5000), (1, 1, "user", None), (2, 0, "user", ""), (2, 1, "user", "Two words"), (3, 0, "user", "12 !")]
    spark.createDataFrame(turns, "conv_id long, turn long, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    rows = {r["id"]: r for r in apps.token_samples(spark, str(tmp_path)).collect()}
    assert {k: len(r["x"]) for k, r in rows.items()} == {1000: 5000, 1001: 0, 2000: 0, 2001: 2, 3000: 0}
    assert {k: r["y"] for k, r in rows.items()} == {1000: [1.0], 1001: [0.0], 2000: [0.0], 2001: [0.0], 3000: [0.0]}
    said = apps.QUERIES["w7_gru_train"](spark, str(tmp_path)).collect()
    assert [r["samples"] for r in said] == [5.0] * 3 and all(np.isfinite(r["mean_loss"]) for r in said)
