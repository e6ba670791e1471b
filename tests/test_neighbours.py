"""Neighbour counts without copies or shuffled pairs."""

import re

from pyspark.sql import functions as F

from structcurve.operators import descriptors
from structcurve.plans import catalogue
from structcurve.sources.tables import random_structures

DATA = "/root/testdata/sf0.001"


def test_counts_are_those_of_all_pairs(spark):
    for structures, atoms in ((2, 900), (150, 30), (1, 1)):
        a = random_structures(spark, structures, atoms)
        want = a.join(descriptors.neighbours(a, 6.0).groupBy("structure_id", "atom_id").agg(F.count("*").alias("n")), ["structure_id", "atom_id"], "left")
        want = {(r.structure_id, r.atom_id): r.n or 0 for r in want.collect()}
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "100")
        try:
            got = {(r.structure_id, r.atom_id): r.n for r in descriptors.neighbour_counts(a, 6.0).collect()}
        finally:
            spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
        assert got == want


def test_atoms_are_not_copied_to_blocks(spark):
    for name in ("j10_blocked_range_join", "k7_composition"):
        plan = catalogue.QUERIES[name](spark, DATA)._jdf.queryExecution().executedPlan().toString()
        assert not re.search(r"Generate|Join", plan)
