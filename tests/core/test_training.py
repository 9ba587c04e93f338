import numpy as np
import pytest
from pyspark.sql import functions as F

from gradsift.operators import losses as L
from gradsift.operators import quality as Q
from gradsift.operators import simulate as SIM
from gradsift.operators import trainers as T
from gradsift.operators.hashing import HashFamily


@pytest.fixture(scope="module")
def data(spark):
    rnd = np.random.default_rng(3)
    x = rnd.normal(size=(40, 5))
    y = x @ np.array([1.0, -2.0, 0.0, 3.0, 0.5])
    rows = [(i, i % 2, float(y[i]), [(j, float(x[i, j])) for j in range(5)]) for i in range(40)]
    df = spark.createDataFrame(rows, "ex_id long, worker int, y double, x array<struct<coord:bigint,val:double>>").cache()
    return x, y, df


def weights(run):
    return np.array([r.w for r in run.w.orderBy("coord").collect()])


def test_gradients_match_numpy(spark, data):
    x, y, df = data
    w = np.array([0.3, -0.1, 0.2, 0.0, 1.0])
    frame = spark.createDataFrame(list(enumerate(w.tolist())), "coord long, w double")
    z = x @ w
    for loss, slope, target in (
        (L.RidgeLoss(0.1), z - y, df),
        (L.AbsLoss(0.1), np.sign(z - y), df),
        (L.LogisticLoss(0.1), 1 / (1 + np.exp(-z)) - (y > 0), df.withColumn("y", F.when(F.col("y") > 0, 1.0).otherwise(0.0))),
        (L.HingeLoss(0.1), np.where(np.where(y > 0, 1, -1) * z < 1, -np.where(y > 0, 1, -1), 0), df.withColumn("y", F.when(F.col("y") > 0, 1.0).otherwise(0.0))),
    ):
        got = {(r.worker, r.coord): r.g for r in loss.gradient(target, frame, 5).collect()}
        for worker in (0, 1):
            mine = np.arange(40) % 2 == worker
            want = x[mine].T @ slope[mine] / mine.sum() + 0.1 * w
            assert np.allclose([got[worker, j] for j in range(5)], want)


def test_kernels_by_finite_differences():
    rnd = np.random.default_rng(1)
    x, y = rnd.normal(size=(12, 4)), rnd.integers(0, 3, 12)
    for model in (SIM.Softmax(4, 3), SIM.Mlp(4, 5, 3), SIM.Mlp(4, 5, 3, "relu")):
        w = model.start(2) + rnd.normal(size=model.d) * 0.1
        g = model.gradient(w, x, y)
        for j in rnd.permutation(model.d)[:12]:
            e = np.zeros(model.d)
            e[j] = 1e-6
            assert g[j] == pytest.approx((model.evaluate(w + e, x, y)[0] - model.evaluate(w - e, x, y)[0]) / 2e-6, abs=1e-4)


def test_limits_of_the_trainers(data):
    """k = d without momentum is dense SGD, whatever is sent; the simulator takes the same steps."""
    x, y, df = data
    loss, fam = L.RidgeLoss(0.1), HashFamily(5, 64, 1)
    dense = weights(T.train_dense(df, loss, 5, 2, 2, eta=0.05))
    for method in ("true_top_k", "sketch"):
        assert np.allclose(weights(T.train_momentum(df, loss, 5, 5, 2, 2, 0.05, 0.0, 1, fam, method)), dense)
    parts = [np.arange(40) % 2 == i for i in (0, 1)]
    w = np.zeros(5)
    for _ in range(2):
        w -= 0.05 * sum(x[p].T @ (x[p] @ w - y[p]) / p.sum() + 0.1 * w for p in parts)
    assert np.allclose(dense, w)


def test_masking_at_full_k_removes_momentum(data):
    run = T.train_true_top_k(data[2], L.RidgeLoss(0.1), 5, 5, 2, 2, eta=0.05, m=0.9)
    assert run.state.agg(F.max(F.abs("u")), F.max(F.abs("v"))).first() == (0.0, 0.0)


def test_annealed_keeps_the_mass(spark, data):
    x, y, df = data
    fam, loss = HashFamily(5, 32, 1), L.RidgeLoss(0.1)
    run = T.train_annealed(df, loss, 5, 2, 5.0, 2, 2, fam, output="last")
    assert run.state.count() == 10 and np.isfinite(weights(run)).all()
    best = Q.closed_form_ridge(df, 5, 0.1)
    assert np.allclose(best, np.linalg.solve(x.T @ x / 40 + 0.1 * np.eye(5), x.T @ y / 40))
    high, low = Q.curvature(df, 5, 0.1)
    assert high > low > 0.1


def test_simulator_orders_methods():
    rnd = np.random.default_rng(0)
    x = rnd.normal(size=(300, 10))
    y = (x @ rnd.normal(size=(10, 4))).argmax(1)
    run = lambda **s: SIM.simulate(SIM.Softmax(10, 4), (x, y), (x, y), workers=4, steps=40, batch=100, eta=0.3, **s)
    dense, top = run(method="dense"), run(method="true_top_k", k=8)
    local = [run(method="local_top_k", k=4)["updated"] for _ in range(1)][0]
    assert dense["train_loss"] < 0.5 and top["train_loss"] < 1.0 and 4 <= local <= 16
    risk = [SIM.simulate(SIM.Ridge(10, 1.0), (x, x[:, 0]), (x, x[:, 0]), "annealed", 4, t, 50, 0.0, k=2, cols=16, xi=40.0)["train_loss"] for t in (30, 300)]
    assert risk[1] < risk[0]


def test_bleu(spark):
    pairs = spark.createDataFrame([(1, "a b c d e".split(), "a b c d e".split()), (2, "x y z w".split(), "x y q w".split())], "pair_id long, candidate array<string>, reference array<string>")
    rows = {r.n: r for r in Q.corpus_bleu(pairs).collect()}
    assert (rows[1].matched, rows[1].total, rows[4].matched, rows[4].total) == (8, 9, 2, 3)
    assert Q.corpus_bleu(pairs.where("pair_id = 1")).first().score == pytest.approx(100.0)


def test_hidden_layer_loss_equals_its_kernel(spark):
    rnd = np.random.default_rng(8)
    x, y, worker = rnd.normal(size=(60, 6)) * (rnd.random((60, 6)) < 0.5), rnd.integers(0, 3, 60), rnd.integers(0, 3, 60)
    rows = [(i, int(worker[i]), int(y[i]), [(j, float(x[i, j])) for j in np.flatnonzero(x[i]).tolist()]) for i in range(60)]
    df = spark.createDataFrame(rows, "ex_id long, worker int, y int, x array<struct<coord:bigint,val:double>>").repartition(4)
    loss = L.MlpLoss(6, 4, 3)
    w = loss.start(spark, 3)
    at = loss.net.start(3)
    got = {(r.worker, r.coord): r.g for r in loss.gradient(df, w, loss.d).collect()}
    assert len(got) == 3 * loss.d
    for k in range(3):
        want = loss.net.gradient(at, x[worker == k], y[worker == k])
        assert np.allclose([got[k, j] for j in range(loss.d)], want)
    measured = loss.evaluate(df, w, loss.d).first()
    assert (measured.loss, measured.accuracy) == pytest.approx(loss.net.evaluate(at, x, y))
    run = T.train_momentum(df, loss, loss.d, 12, 3, 3, 0.3, 0.9, 3, HashFamily(5, 16, 1), w0=w, evaluate=df)
    losses = [v for _, n, v in run.metrics if n == "loss"]
    assert losses[-1] < measured.loss


def test_clipping_warm_up_and_sharding(spark, data):
    x, y, df = data
    g = spark.createDataFrame([(0, 0, 3.0), (0, 1, 4.0), (1, 0, 0.3)], "worker int, coord long, g double")
    assert {(r.worker, r.coord): round(r.g, 9) for r in T.clipped(g, 1.0).collect()} == {(0, 0): 0.6, (0, 1): 0.8, (1, 0): 0.3}
    k = T.sparsity_warmup(1000, 10, 4)
    assert [k(t) for t in range(1, 7)] == [316, 100, 32, 10, 10, 10]
    run = T.train_local_top_k(df, L.RidgeLoss(), 5, T.sparsity_warmup(5, 1, 2), 3, 2, eta=0.01, clip=0.5)
    assert [v for _, n, v in run.metrics if n == "numbers"][-1] <= 1 + 2
    skewed = T.shard(df.withColumn("key", F.col("ex_id") % 2 * 2), 4, "key")
    assert {r.worker for r in skewed.collect()} == {0, 2} and {r.worker for r in T.shard(df, 4).collect()} == {0, 1, 2, 3}


def test_only_two_versions_of_a_table_stay(spark, data, tmp_path):
    from pathlib import Path

    from gradsift.plans.durable import shared_dir

    folder = Path(shared_dir(spark).removeprefix("file:"))
    before = set(folder.iterdir()) if folder.exists() else set()
    run = T.train_momentum(data[2], L.RidgeLoss(0.1), 5, 2, 5, 2, 0.05, 0.9, 2, HashFamily(5, 16, 1))
    kept = [p.name.split("-")[0] for p in set(folder.iterdir()) - before]
    assert sorted(kept) == ["state", "state", "update", "update", "w", "w"] and run.state.count() == 10 and run.w.count() == 5


def test_merging_exchanges_no_more_than_the_cells(spark):
    from gradsift.operators import sketch as S
    from gradsift.plans.measure import exchanged

    fam = HashFamily(3, 8, 1)
    v = spark.range(1000).selectExpr("cast(id % 4 as int) as worker", "id % 200 as coord", "id as delta")
    (records, size), *more = exchanged(S.sketch(v, fam))
    assert not more and size > 0 and records <= 4 * 3 * 8
