"""Experiments make the pair sums once, whatever they use them for."""

import pytest

from structcurve.plans import catalogue
from structcurve.plans import experiments as ex

DATA = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name,runs", [("b3_representations", 1), ("w14_funnel", 1)])
def test_targets_made_once(spark, monkeypatch, name, runs):
    right, calls = ex.pair_targets, []
    monkeypatch.setattr(ex, "pair_targets", lambda *a: calls.append(1) or right(*a))
    assert catalogue.QUERIES[name](spark, DATA).count() > 0
    assert len(calls) == runs


def test_coulomb_sums_are_written_before_their_range(spark):
    plan = ex.triplets_of(spark, DATA, "D3")._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan


def test_raw_bins_and_reduced_share_cells(spark, monkeypatch):
    right, calls = ex.triplets_of, []
    monkeypatch.setattr(ex, "triplets_of", lambda *a, **b: calls.append(1) or right(*a, **b))
    assert catalogue.QUERIES["b4_raw_histogram"](spark, DATA).count() == 2
    assert len(calls) == 1


def test_one_fit_on_all_rows(spark, monkeypatch):
    right, calls = ex.lsi.fit_lsi, []
    monkeypatch.setattr(ex.lsi, "fit_lsi", lambda *a, **b: calls.append(1) or right(*a, **b))
    assert ex.fit_on(spark, DATA).count() == 8
    assert len(calls) == 4
