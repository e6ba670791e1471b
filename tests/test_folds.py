"""Models of a fold trained side by side, one task a model, and the linear learner without rows sent."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from structcurve.operators import learn


def reference(x, y, config):
    """Plain Adam steps, a model by itself."""
    (xm, xs), (ym, ys) = ((v.mean(axis=0), v.std(axis=0, ddof=1)) for v in (x, y))
    xn, yn = (x - xm) / xs, (y - ym) / ys
    model = learn.new_mlp([x.shape[1], *config.hidden, y.shape[1]], config.seed)
    rng, t, m, v = np.random.default_rng(config.seed + 1), 0, 0.0, 0.0
    for _ in range(config.epochs):
        order = rng.permutation(len(xn))
        for lo in range(0, len(order), config.batch):
            rows = order[lo : lo + config.batch]
            grads = model.gradients(xn[rows], yn[rows])[1]
            g = np.concatenate([p.ravel() for (gw, gb), (w, _) in zip(grads, model.layers) for p in (gw / len(rows) + config.decay * w, gb / len(rows))])
            t, m, v = t + 1, 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
            flat, at = model.flat() - config.rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8), 0
            for i, (w, b) in enumerate(model.layers):
                model.layers[i] = flat[at : at + w.size].reshape(w.shape), flat[at + w.size : at + w.size + b.size]
                at += w.size + b.size
    model.x_scale, model.y_scale = (xm, xs), (ym, ys)
    return model


@pytest.mark.parametrize("hidden", [(8,), (8, 5)])
def test_side_by_side(hidden):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(300, 6))
    y = x[:, :2] @ rng.normal(size=(2, 2)) + rng.normal(size=(300, 2))
    config = learn.MlpConfig(hidden=hidden, epochs=4, batch=37)
    for k, model in zip((1, 4, 6), learn.train_side_by_side(x, y, [1, 4, 6], config)):
        assert np.allclose(model.predict(x[:, :k]), reference(x[:, :k], y, config).predict(x[:, :k]), atol=1e-9)


@pytest.fixture(scope="module")
def table(spark):
    rng = np.random.default_rng(1)
    x = rng.normal(size=(400, 3))
    rows = [(i, i % 5, v.tolist(), float(v.sum() + rng.normal()), float(v[0] + 4)) for i, v in enumerate(x)]
    return spark.createDataFrame(rows, "structure_id bigint, fold int, vec array<double>, a double, b double").repartition(3)


def test_all_k_in_one_pass(table):
    config = learn.MlpConfig(hidden=(4,), epochs=3)
    p = learn.cross_predict(table, ["a"], config, folds=5, ks=[1, 3])
    plan = p._jdf.queryExecution().executedPlan().toString()
    assert plan.count("MapInArrow") == 1
    for k in (1, 3):
        cut = learn.cross_predict(table.withColumn("vec", F.slice("vec", 1, k)), ["a"], config, folds=5)
        got, want = ({(r.structure_id, r.fold): (r.split, r.pred) for r in d.collect()} for d in (p.where(F.col("k") == k), cut))
        assert len(got) == 2000 and got.keys() == want.keys()
        assert all(got[i][0] == want[i][0] and abs(got[i][1] - want[i][1]) < 1e-9 for i in got)


def test_one_task_for_each_model(table):
    def one(model, ids, fold, x, y):
        import pyarrow as pa

        yield pa.RecordBatch.from_pylist([{"model": model, "n": len(ids)}])

    got = learn.in_one_task_each(table, 7, ["a"], one, "model bigint, n bigint").withColumn("task", F.spark_partition_id()).collect()
    assert sorted((r.model, r.n) for r in got) == [(i, 400) for i in range(7)] and len({r.task for r in got}) == 7


def test_linear_learner_sends_no_rows(table):
    p = learn.cross_predict(table, ["a", "b"], learner="ridge", folds=5)
    plan = p._jdf.queryExecution().executedPlan().toString()
    assert "Generate" not in plan and "FlatMapGroups" not in plan
    t = table.toPandas().sort_values("structure_id")
    x, y, fold = np.array(t["vec"].tolist()), t[["a", "b"]].to_numpy(), t["fold"].to_numpy()
    got = {(r.structure_id, r.fold, r.target): (r.split, r.calc, r.pred) for r in p.collect()}
    assert len(got) == 4000
    for f in range(5):
        want = learn.ridge(x[fold != f], y[fold != f])(x)
        for i in range(400):
            for j, target in enumerate("ab"):
                split, calc, pred = got[i, f, target]
                assert split == ("test" if fold[i] == f else "train") and calc == y[i, j] and abs(pred - want[i, j]) < 1e-9
