"""Hand-computed values."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from structcurve.functions import curves, vectors
from structcurve.operators import curation, descriptors, encode, lsi, metrics
from structcurve.plans import methods
from structcurve.sources.tables import load


def one(spark, cols):
    return spark.createDataFrame([(0,)], "a int").select(*cols).first()


@pytest.mark.parametrize("dims,code", [((0, 0, 0, 0), 0), ((0, 0, 0, 15), 4369), ((8, 0, 0, 0), 32768), ((1, 2, 3, 4), 362), ((15, 15, 15, 15), 65535)])
def test_morton(spark, dims, code):
    assert one(spark, [curves.morton_encode([F.lit(d) for d in dims], 4)])[0] == code
    assert tuple(one(spark, curves.morton_decode(F.lit(code), 4, 4))) == dims


def test_tfidf(spark):
    t = spark.createDataFrame([(1, 0, 1), (1, 1, 1), (2, 0, 2)], "structure_id bigint, cell bigint, n bigint")
    got = lsi.tfidf(t).collect()
    assert [(r.structure_id, r.cell) for r in got] == [(1, 1)] and abs(got[0].weight - 0.5 * math.log(2)) < 1e-12
    model = lsi.fit_lsi(t, 1)
    assert {r.structure_id: r.vec for r in lsi.reduce_structures(t, model, 1, t).collect()}[2] == [0.0]


def atoms(spark, rows):
    return spark.createDataFrame([(s, i, z, float(z), *map(float, p)) for i, (s, z, *p) in enumerate(rows)], "structure_id bigint, atom_id int, z int, mass double, x double, y double, w double")


def test_coulomb(spark):
    got = descriptors.descriptor_coulomb(atoms(spark, [(1, 8, 0, 0, 0), (1, 1, 1, 0, 0), (2, 6, 0, 0, 0)])).orderBy("atom_id").collect()
    assert [r.descriptor for r in got] == [8.0, 8.0, 0.0]
    twin = descriptors.descriptor_coulomb(atoms(spark, [(1, 2, 0, 0, 0), (1, 3, 0, 0, 0)])).collect()
    assert all(math.isfinite(r.descriptor) for r in twin)


@pytest.mark.parametrize("mode,value", [("bonded", 10), ("steric", 12), ("double", 12)])
def test_oxygen_with_two_bonds(spark, mode, value):
    water = atoms(spark, [(1, 8, 0, 0, 0), (1, 1, 0.7, 0.6, 0), (1, 1, -0.7, 0.6, 0)])
    assert descriptors.descriptor_coordination(water, 1.2, mode).where("z = 8").first().descriptor == value


def test_fraction_error(spark):
    p = spark.createDataFrame([(2.0, 1.0), (-4.0, -5.0), (0.0, 3.0)], "calc double, pred double")
    r = metrics.fraction_error(p.where("calc <> 0"), []).first()
    assert r.error == 0.375
    r = metrics.fraction_error(p, []).first()
    assert (r.error, r.undefined, r.n) == (0.375, 1, 3)


def test_recall(spark):
    df = spark.createDataFrame([(i, float(i), float(i), float(-i)) for i in range(20)], "structure_id bigint, calc double, same double, reverse double")
    assert tuple(metrics.recall_at(df, 15, pred="same").first()) == (1.0, 3)
    assert metrics.recall_at(df, 15, pred="reverse").first().recall == 0
    assert metrics.recall_at(df, 15, pred="reverse", direction="desc").first().recall == 0


def test_slope_rule():
    s = np.array([2.0, 1.0, 0.6, 0.58, 0.57, 0.5695, 0.5692, 0.5691])
    assert lsi.choose_k(s) == 5 and lsi.choose_k(s, "energy", energy=0.5) == 1 and lsi.choose_k(s[:1]) == 1


def test_logistic(spark):
    assert one(spark, [vectors.logistic(F.lit(0.0))])[0] == 0.5


def test_quantise_edges(spark):
    grid = encode.GridSpec((encode.DimSpec("v", 0.0, 16.0),))
    df = spark.createDataFrame([(v,) for v in (-1.0, 0.0, 0.999999, 1.0, 15.9999999999, 16.0, 99.0)], "v double")
    assert [r.q0 for r in encode.quantize(df, grid).collect()] == [0, 0, 0, 1, 15, 15, 15]


def test_curation_counts(spark):
    d = "/root/testdata/sf0.01"
    kept, audit = curation.curate(load(spark, d, "part"), load(spark, d, "lineitem"))
    r = audit.first()
    assert (r["all"], r.elements, r.r_factor, r.temperature, r.molecules, r.distinct, r.disorder, r.coordinates, r.rules, r.kept) == (2000, 2000, 1781, 1942, 1940, 1669, 1943, 2000, 1358, 1310)
    assert kept.count() == 1310


def test_wide_order_is_checked_on_all_lines(spark, tmp_path, monkeypatch):
    rows = [(k, k // 7, 3, 1) for k in (1, 5, 32767, 32768, 40_001, 150_000, (1 << 24) - 1)]
    spark.createDataFrame(rows, "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int").write.parquet(f"{tmp_path}/lineitem.parquet")
    assert tuple(methods.m13b(spark, str(tmp_path)).select("codes", "ordered").first()) == (len(rows), True)
    right = curves.morton_encode_wide
    monkeypatch.setattr(methods.curves, "morton_encode_wide", lambda cols, *a: F.when(F.col(cols[0]) > 100_000, F.reverse(right(cols, *a))).otherwise(right(cols, *a)))
    assert not methods.m13b(spark, str(tmp_path)).first().ordered


def test_fold_in_is_checked_on_all_structures_and_places(spark, monkeypatch):
    right, calls = lsi.reduce_structures, []

    def wrong(*args):
        calls.append(1)
        moved = F.when(F.col("structure_id") % 5 == 3, F.transform("vec", lambda x, i: x + (i == 2).cast("double"))).otherwise(F.col("vec"))
        return right(*args) if len(calls) == 1 else right(*args).withColumn("vec", moved)

    monkeypatch.setattr(methods.lsi, "reduce_structures", wrong)
    assert not methods.m20a(spark, "/root/testdata/sf0.001").first().same_as_fitted
