"""The Gram backend against numpy, on both sides, with all dimensions kept."""

import numpy as np
import pytest
from pyspark.sql import DataFrame

from structcurve.operators import lsi


@pytest.mark.parametrize("structures,cells", [(90, 200), (200, 90)])
def test_all_dimensions(spark, monkeypatch, structures, cells):
    rng = np.random.default_rng(3)
    rows = [(s, int(c) * 7, int(rng.integers(1, 5))) for s in range(structures) for c in rng.choice(cells, 12, replace=False)]
    t = spark.createDataFrame(rows, "structure_id bigint, cell bigint, n bigint")
    weights = lsi.tfidf(t).collect()
    names = sorted({r.cell for r in weights})
    dense = np.zeros((structures, len(names)))
    for r in weights:
        dense[r.structure_id, names.index(r.cell)] = r.weight
    # pairs of the matrix never come to the driver as rows
    right = DataFrame.toPandas
    monkeypatch.setattr(DataFrame, "toPandas", lambda self: pytest.fail("pairs as rows") if "g" in self.columns else right(self))
    model = lsi.fit_lsi(t, min(dense.shape), "gram")
    assert np.allclose(model.sigma, np.linalg.svd(dense, compute_uv=False)[: len(model.sigma)], atol=1e-7)
    vectors = lsi.reduce_structures(t, model, structures=t)
    assert "MapInArrow" in vectors._jdf.queryExecution().executedPlan().toString()
    got = {r.structure_id: np.array(r.vec) for r in vectors.collect()}
    found = np.array([got[s] for s in range(structures)])
    assert np.allclose(found @ found.T, dense @ dense.T, atol=1e-9)
