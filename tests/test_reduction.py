"""Reductions never make the term vectors rows on the driver."""

import numpy as np
import pytest

from structcurve.operators import lsi


@pytest.mark.parametrize("scale", ["svt", "vt"])
def test_no_table_of_terms(spark, monkeypatch, scale):
    rng = np.random.default_rng(2)
    rows = [(s, int(c), int(rng.integers(1, 4))) for s in range(40) for c in rng.choice(60, 8, replace=False)]
    t = spark.createDataFrame([*rows, (99, 1000, 1)], "structure_id bigint, cell bigint, n bigint")
    model = lsi.fit_lsi(t.where("cell < 1000"), 3)
    table = {r.cell: (r.idf, r.u) for r in model.table(spark).collect()}
    monkeypatch.setattr(lsi.LsiModel, "table", lambda *a: pytest.fail("a table of terms"))
    got = {r.structure_id: r.vec for r in lsi.reduce_structures(t, model, 3, t, scale).collect()}
    for s in range(40):
        own = [(c, n) for i, c, n in rows if i == s]
        total = sum(n for _, n in own)
        want = sum(n / total * table[c][0] * np.array(table[c][1]) for c, n in own if c in table)
        assert np.allclose(got[s], want if scale == "svt" else want / model.sigma, atol=1e-12)
    assert got[99] == [0.0, 0.0, 0.0]
