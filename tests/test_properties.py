"""Bijections, invariance, and comparison with numpy."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from structcurve.functions import curves
from structcurve.operators import descriptors, encode, geometry, learn, lsi, metrics
from structcurve.operators.encode import EncodeConfig
from structcurve.operators.zorder import decompose_box
from structcurve.plans.methods import moved
from structcurve.sources.tables import atoms_from_lineitem, random_structures

SMALL = "/root/testdata/sf0.001"


def test_morton_is_a_bijection(spark):
    codes = spark.range(65536).withColumnRenamed("id", "c")
    back = codes.select("c", curves.morton_encode(curves.morton_decode("c", 4, 4), 4).alias("b"))
    assert back.where("c <> b").count() == 0


@pytest.mark.parametrize("n,bits", [(2, 3), (3, 3), (4, 2)])
def test_hilbert_steps_to_neighbours(spark, n, bits):
    grid = spark.createDataFrame(list(itertools.product(range(1 << bits), repeat=n)), ", ".join(f"c{i} int" for i in range(n)))
    cols = [f"c{i}" for i in range(n)]
    coded = sorted(tuple(r)[::-1] for r in curves.hilbert_encode(grid, cols, bits).collect())
    assert [r[0] for r in coded] == list(range(1 << n * bits))
    assert all(sum(abs(x - y) for x, y in zip(a[1:], b[1:])) == 1 for a, b in zip(coded, coded[1:]))
    back = curves.hilbert_decode(spark.createDataFrame([(r[0],) for r in coded], "h bigint"), "h", n, bits, cols)
    assert {tuple(r)[1:] for r in back.collect()} == {r[:0:-1] for r in coded}


def test_peano_steps_to_neighbours(spark):
    grid = spark.createDataFrame(list(itertools.product(range(9), repeat=2)), "a int, b int")
    coded = sorted((r.c, r.a, r.b) for r in grid.withColumn("c", curves.peano_encode(["a", "b"], 2)).collect())
    assert [r[0] for r in coded] == list(range(81))
    assert all(abs(p[1] - q[1]) + abs(p[2] - q[2]) == 1 for p, q in zip(coded, coded[1:]))


def test_box_ranges_cover_the_box(spark):
    for lo, hi, most in (([1, 2], [5, 6], 64), ([0, 0], [7, 7], 4), ([3, 3], [3, 3], 8), ([1, 0], [6, 7], 3)):
        ranges = decompose_box(lo, hi, 3, most)
        assert len(ranges) <= most
        codes = {curve_code(x, y) for x in range(lo[0], hi[0] + 1) for y in range(lo[1], hi[1] + 1)}
        assert all(any(a <= c <= b for a, b in ranges) for c in codes)
    exact = decompose_box([1, 2], [5, 6], 3)
    assert sum(b - a + 1 for a, b in exact) == 25


def curve_code(x, y):
    return sum((x >> b & 1) << 2 * b + 1 | (y >> b & 1) << 2 * b for b in range(3))


def shapes(spark):
    t = 1 / np.sqrt(2)
    rows = {
        1: [(8, 3, 4, 5)], 2: [(8, 0, 0, 0), (1, 1, 0, 0)], 3: [(6, 0, 0, 0), (6, 1, 1, 1), (1, 3, 3, 3)],
        4: [(6, 1, 0, 0), (6, -1, 0, 0), (6, 0, 1, 0), (6, 0, -1, 0)],
        5: [(6, 1, 0, -t), (6, -1, 0, -t), (6, 0, 1, t), (6, 0, -1, t)],
        6: [(6, 0, 0, 0), (7, 1.5, 0.2, -0.4), (8, -0.8, 2.2, 0.3), (1, 0.5, -0.9, 3.1), (1, -2.0, -1.1, -1.3)],
        7: [(6, 1, 1, 1), (6, 1, 1, 1)],
    }
    data = [(s, i, z, float(z), *map(float, p)) for s, atoms in rows.items() for i, (z, *p) in enumerate(atoms)]
    return spark.createDataFrame(data, "structure_id bigint, atom_id int, z int, mass double, x double, y double, w double")


def test_axes_of_degenerate_shapes(spark):
    axes = geometry.principal_axes(geometry.moments(shapes(spark))).collect()
    assert len(axes) == 7
    for r in axes:
        m = np.array([[r[f"r{i}{j}"] for j in (1, 2, 3)] for i in (1, 2, 3)])
        assert np.allclose(m @ m.T, np.eye(3), atol=1e-9) and abs(np.linalg.det(m) - 1) < 1e-9
    line = next(r for r in axes if r.structure_id == 3)
    assert abs(abs(line.r11) - 3**-0.5) < 1e-9


def test_distances_survive_the_pose(spark):
    a = shapes(spark)
    far = lambda df: {(r.structure_id, r.atom_id, r.atom_id2): r.d for r in descriptors.pairs(df).collect()}
    before, after = far(a), far(geometry.pose(a))
    assert before.keys() == after.keys() and all(abs(before[k] - after[k]) < 1e-9 for k in before)


@pytest.mark.parametrize("seed", [0, 1])
def test_histograms_ignore_rigid_motions_and_order(spark, seed):
    a = atoms_from_lineitem(spark, SMALL)
    gap = metrics.compare_histograms(encode.encode_structures(a), encode.encode_structures(moved(a, seed).orderBy(F.rand(3))))
    assert gap.where("moved > 0").count() == 0


def test_axes_equal_numpys(spark):
    m = geometry.moments(random_structures(spark, 40, 12))
    a = {r.structure_id: r for r in geometry.principal_axes(m).collect()}
    for r in geometry.principal_axes(m, backend="eigh").collect():
        assert all(abs(a[r.structure_id][k] - r[k]) < 1e-6 * max(1, abs(r[k])) for k in (*geometry.ROTATION, "e1", "e3"))


def test_outside_atoms_are_dropped_or_clamped(spark):
    a = spark.createDataFrame([(1, 0, 6, 6.0, 0.0, 0.0, 0.0), (1, 1, 6, 6.0, 90.0, 0.0, 0.0), (1, 2, 6, 6.0, 0.0, 1.0, 0.0)], "structure_id bigint, atom_id int, z int, mass double, x double, y double, w double")
    total = lambda how: encode.encode_structures(a, EncodeConfig(radius=40.0, outside=how)).agg(F.sum("n")).first()[0]
    assert total("drop") == 2 and total("clamp") == 3


def test_blocked_neighbours_equal_brute_force(spark):
    a = random_structures(spark, 5, 60)
    rows = lambda df: {(r.structure_id, r.atom_id, r.atom_id2) for r in df.collect()}
    assert rows(descriptors.neighbours(a, 9.0)) == rows(descriptors.neighbours_blocked(a, 9.0))


def matrix(spark):
    t = encode.encode_structures(random_structures(spark, 30, 25), EncodeConfig(bits=2))
    rows = lsi.tfidf(t).toPandas()
    return t, rows.pivot(index="cell", columns="structure_id", values="weight").fillna(0).sort_index().to_numpy()


@pytest.mark.parametrize("backend,tolerance", [("gram", 1e-8), ("subspace", 1e-4), ("mllib", 1e-6)])
def test_svd_equals_numpys(spark, backend, tolerance):
    t, a = matrix(spark)
    model = lsi.fit_lsi(t, 4, backend, tolerance=1e-10, passes=300)
    u, s, vt = np.linalg.svd(a, full_matrices=False)
    assert np.allclose(model.sigma, s[:4], rtol=tolerance)
    if backend == "gram":
        vec = np.array([r.vec for r in lsi.reduce_structures(t, model, 4).orderBy("structure_id").collect()])
        assert np.allclose(np.abs(vec), np.abs((s[:4, None] * vt[:4]).T), atol=1e-7)


def test_model_pruning_and_limits(spark):
    t, _ = matrix(spark)
    assert len(lsi.fit_lsi(t, 2, min_df=3).cells) < len(lsi.fit_lsi(t, 2).cells)


def test_gradients_equal_differences():
    rng = np.random.default_rng(0)
    m = learn.new_mlp([3, 4, 2], 1)
    x, y = rng.normal(size=(7, 3)), rng.normal(size=(7, 2))
    loss, grads = m.gradients(x, y)
    for i, (w, b) in enumerate(m.layers):
        for p, g in ((w, grads[i][0]), (b, grads[i][1])):
            for at in np.ndindex(p.shape):
                old, h = p[at], 1e-6
                p[at] = old + h
                up = m.gradients(x, y)[0]
                p[at] = old - h
                down = m.gradients(x, y)[0]
                p[at] = old
                assert abs((up - down) / (2 * h) - g[at]) < 1e-5


def table(spark, n=400):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(n, 3))
    y = np.column_stack([5 + x[:, 0] + np.sin(x[:, 1]), 3 - x[:, 2]])
    rows = [(i, i % 5, [float(v) for v in x[i]], float(y[i, 0]), float(y[i, 1])) for i in range(n)]
    return spark.createDataFrame(rows, "structure_id bigint, fold int, vec array<double>, a double, b double")


def test_training_beats_the_mean_and_predicts_in_sql(spark):
    t = table(spark)
    p = t.toPandas()
    m = learn.train_local(np.array(p["vec"].tolist()), p[["a", "b"]].to_numpy(), learn.MlpConfig((8,), 0.02, 32, 80))
    got = learn.mlp_predict(t, m).toPandas()
    assert np.allclose(np.array(got["pred"].tolist()), m.predict(np.array(got["vec"].tolist())))
    assert np.abs(np.array(got["pred"].tolist())[:, 0] - got["a"]).mean() < 0.3 * np.abs(got["a"] - got["a"].mean()).mean()


def test_distributed_training_equals_local_full_batch(spark):
    t = table(spark)
    config = learn.MlpConfig((6,), 0.05, None, 15)
    p = t.toPandas()
    far = learn.train_distributed(t, ["a", "b"], config)
    near = learn.train_local(np.array(p["vec"].tolist()), p[["a", "b"]].to_numpy(), config)
    assert np.allclose(far.flat(), near.flat(), atol=1e-6)


def test_folds_are_a_partition(spark):
    df = spark.range(2000).withColumnRenamed("id", "structure_id")
    counts = [r.n for r in learn.kfold(df).groupBy("fold").agg(F.count("*").alias("n")).orderBy("fold").collect()]
    assert counts == [201, 201, 200, 200, 199, 196, 201, 202, 200, 200]


def test_scaler_inverts(spark):
    t = table(spark)
    s = learn.fit_scaler(t, ["a", "b"])
    back = s.inverse(s.apply(t)).join(t.select("structure_id", F.col("a").alias("a0")), "structure_id")
    assert back.agg(F.max(F.abs(F.col("a") - F.col("a0")))).first()[0] < 1e-9


def test_model_based_search_beats_random():
    space = learn.Space({"x": ("uniform", -5, 5), "y": ("loguniform", 1e-3, 1e3), "c": ("choice", ["u", "v"])})
    cost = lambda ps: [(p["x"] - 1) ** 2 + np.log10(p["y"]) ** 2 + (p["c"] == "u") for p in ps]
    run = lambda how: np.mean([learn.smbo_search(space, cost, 60, seed=s, method=how).loss for s in range(6)])
    assert run("smbo") < run("random")


def test_mean_predictor(spark):
    t = table(spark, 50)
    p = t.toPandas()
    for r in metrics.mean_predictor(t, ["a", "b"]).collect():
        assert abs(r.pred - p.loc[p["fold"] != r.fold, r.target].mean()) < 1e-9


def test_nearest_in_blocks(spark):
    from structcurve.operators.joins import knn_exact

    rng = np.random.default_rng(4)
    rows = [(i, [float(v) for v in rng.normal(size=5)]) for i in range(60)]
    points = spark.createDataFrame(rows, "pid bigint, vec array<double>")
    queries = points.where("pid % 3 = 0").withColumnRenamed("pid", "qid")
    one, many = (sorted(map(tuple, knn_exact(queries, points, 4, block=b).collect())) for b in (1000, 6))
    v = np.array([r[1] for r in rows])
    brute = {(q, int(p)) for q in range(0, 60, 3) for p in sorted((i for i in range(60) if i != q), key=lambda i: (-round(float(v[q] @ v[i]), 6), i))[:4]}
    assert one == many and {(r[0], r[2]) for r in one} == brute
