"""Queries that once made their data up read a given table, through Spark."""

import pytest

from structcurve.plans import catalogue, methods, relational

DATA = "/root/testdata/sf0.001"
READS = {"b6_random_recall": "part", "m21_choose_k": "events", "m26a_priors": "supplier", "n3_gradient": "events", "n4_energy_kept": "events", "s7_crystal_text": "supplier", "s9_random_structures": "supplier", "u5_table_function_images": "supplier"}


@pytest.mark.parametrize("name", sorted(READS))
def test_reads_its_table(spark, monkeypatch, name):
    seen = []
    for module in (methods, relational):
        monkeypatch.setattr(module, "load", lambda s, d, t, right=module.load: seen.append(t) or right(s, d, t))
    assert catalogue.QUERIES[name](spark, DATA).count() > 0
    assert seen == [READS[name]]


def test_several_structures_in_a_file(spark, tmp_path):
    from structcurve.sources.crystal import CrystalTextSource

    head = "loop_\n_atom_site_type_symbol\n_atom_site_Cartn_x\n_atom_site_Cartn_y\n_atom_site_Cartn_z\n"
    (tmp_path / "two.cif").write_text("".join(f"data_{i}\n_structure_number {i}\n{head}C {i}.5 0 1\n" for i in (4, 7)))
    spark.dataSource.register(CrystalTextSource)
    rows = spark.read.format("crystaltext").option("path", f"file://{tmp_path}").load().collect()
    assert sorted((r.structure_id, r.x) for r in rows) == [(4, 4.5), (7, 7.5)]
