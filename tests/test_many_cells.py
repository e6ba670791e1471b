"""More cells than the driver takes: term vectors stay rows, and give what the arrays gave."""

import numpy as np
import pytest

from structcurve.operators import lsi
from structcurve.plans import catalogue

DATA = "/root/testdata/sf0.001"


def _some(spark):
    rng = np.random.default_rng(11)
    rows = [(s, int(c), int(rng.integers(1, 4))) for s in range(90) for c in rng.choice(400, 9, replace=False)]
    return spark.createDataFrame([*rows, (90, 9999, 2), *((s, 5000, 1) for s in range(91))], "structure_id bigint, cell bigint, n bigint")


@pytest.mark.parametrize("backend", ["gram", "subspace"])
@pytest.mark.parametrize("min_df", [1, 2])
def test_as_the_arrays(spark, monkeypatch, tmp_path, backend, min_df):
    t = _some(spark)
    want = lsi.fit_lsi(t, 5, backend, min_df=min_df)
    monkeypatch.setattr(lsi, "BLOCK_TERMS", 100)
    got = lsi.fit_lsi(t, 5, backend, min_df=min_df)
    assert want.terms is None and got.cells is None and got.cell_count() == len(want.cells)
    assert np.allclose(got.sigma, want.sigma, atol=1e-7)
    rows = got.table(spark).orderBy("cell").collect()
    assert [r.cell for r in rows] == want.cells.tolist() and np.allclose([r.idf for r in rows], want.idf)
    assert np.allclose([r.u for r in rows], want.u, atol=1e-4)
    got.save(spark, str(tmp_path / "model"))
    loaded = lsi.LsiModel.load(spark, str(tmp_path / "model"))
    new = t.where("structure_id < 50").union(spark.createDataFrame([(200, 7777, 1), (201, 9999, 1)], t.schema))
    for model in (got, loaded):
        for k, scale in ((5, "svt"), (3, "vt")):
            a, b = ({r.structure_id: r.vec for r in lsi.reduce_structures(new, m, k, new, scale).collect()} for m in (want, model))
            assert a.keys() == b.keys() and all(np.allclose(a[s], b[s], atol=1e-4) for s in a)
        assert sorted(lsi.unseen_cells(new, model).collect()) == sorted(lsi.unseen_cells(new, want).collect())


@pytest.mark.parametrize("name,lines", [("w10_scaling", 4), ("c12_scaling", 3)])
def test_all_resolutions_of_many_cells(spark, monkeypatch, name, lines):
    want = {r.bits: (r.nonzeros, r.cells) for r in catalogue.QUERIES[name](spark, DATA).collect()}
    monkeypatch.setattr(lsi, "BLOCK_TERMS", 300)
    got = {r.bits: (r.nonzeros, r.cells) for r in catalogue.QUERIES[name](spark, DATA).collect()}
    assert got == want and len(got) == lines
