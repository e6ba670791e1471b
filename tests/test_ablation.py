"""The ablation's variants share one pose of the atoms."""

from structcurve.operators import encode
from structcurve.operators.encode import EncodeConfig
from structcurve.plans import experiments as ex

DATA = "/root/testdata/sf0.001"


def test_one_pose_for_all_variants(spark, monkeypatch):
    right, calls = encode.spherical_atoms, []
    monkeypatch.setattr(encode, "spherical_atoms", lambda *a: calls.append(1) or right(*a))
    got = {r.variant: (r.nonzeros, r.atoms) for r in ex.ablation(spark, DATA).collect()}
    assert len(got) == 11 and len(calls) == 1
    for name, config in {"curve=hilbert": EncodeConfig(curve="hilbert"), "bits=3": EncodeConfig(bits=3), "radius=30": EncodeConfig(radius=30.0)}.items():
        rows = ex.triplets_of(spark, DATA, config=config).collect()
        assert got[name] == (len(rows), sum(r.n for r in rows))
