"""The subspace backend on spectra without a gap, on both sides, restarted and in many packed rows."""

import numpy as np
import pytest

from structcurve.operators import encode, lsi
from structcurve.plans import experiments as ex

DATA = "/root/testdata/sf0.001"


@pytest.mark.parametrize("structures,cells", [(700, 300), (300, 700)])
@pytest.mark.parametrize("small", [False, True])
def test_flat_spectrum(spark, monkeypatch, structures, cells, small):
    if small:
        monkeypatch.setattr(lsi, "BASIS_BYTES", 300 * 8 * 40)
        monkeypatch.setattr(lsi, "PACKED", 50)
    rng = np.random.default_rng(5)
    rows = [(s, int(c), int(rng.integers(1, 4))) for s in range(structures) for c in rng.choice(cells, 12, replace=False)]
    t = spark.createDataFrame(rows, "structure_id bigint, cell bigint, n bigint")
    dense = np.zeros((structures, cells))
    for r in lsi.tfidf(t).collect():
        dense[r.structure_id, r.cell] = r.weight
    model = lsi.fit_lsi(t, 6, "subspace")
    assert model.passes < 40
    want = np.linalg.svd(dense)
    assert np.allclose(model.sigma, want[1][:6], atol=1e-6)
    assert np.allclose(np.abs(model.u.T @ want[2][:6].T[model.cells]), np.eye(6), atol=1e-2)


def test_one_pose_for_all_resolutions(spark, monkeypatch):
    right, calls = encode.spherical_atoms, []
    monkeypatch.setattr(encode, "spherical_atoms", lambda *a: calls.append(1) or right(*a))
    got = {r.bits: r.nonzeros for r in ex.scaling(spark, DATA, (3, 4)).collect()}
    assert len(calls) == 1 and got[4] == ex.triplets_of(spark, DATA).count()


def test_a_basis_beyond_memory_converges(spark, monkeypatch):
    rng = np.random.default_rng(5)
    dense = np.where(rng.random((1500, 900)) < 0.02, rng.random((1500, 900)), 0.0)
    lists = spark.createDataFrame([(i, np.flatnonzero(r).tolist(), r[r > 0].tolist()) for i, r in enumerate(dense)], "k bigint, names array<bigint>, weights array<double>")
    packed = lsi._packed(lists, np.arange(900)).persist()
    monkeypatch.setattr(lsi, "BASIS_BYTES", 900 * 8 * 6)
    sizes, right = [], lsi._room
    monkeypatch.setattr(lsi, "_room", lambda m, columns: sizes.append(columns) or right(m, columns))
    _, sigma, used = lsi._svd_subspace(packed, 900, 5, 1e-5, 60)
    assert used < 60 and sizes == [44] and np.allclose(sigma, np.linalg.svd(dense)[1][:5], atol=1e-6)
