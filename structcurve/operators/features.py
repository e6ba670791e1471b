"""Other structure representations that serve as comparison features."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .descriptors import neighbour_counts, pairs


def rdf(atoms: DataFrame, r_max: float = 30.0, bins: int = 30) -> DataFrame:
    """Radial distribution: ``structure_id, bin, n`` of pair distances below r_max."""
    width = r_max / bins
    return pairs(atoms).where((F.col("d") < r_max) & (F.col("atom_id") < F.col("atom_id2"))).groupBy("structure_id", F.floor(F.round(F.col("d") / width, 9)).alias("bin")).agg(F.count("*").alias("n"))


def _width(atoms: DataFrame, max_atoms: int | None) -> int:
    """Atoms of the largest structure, or ``max_atoms``; a structure that is larger than that is an error, not cut."""
    most = atoms.groupBy("structure_id").agg(F.count("*").alias("n")).agg(F.coalesce(F.max("n"), F.lit(0))).first()[0]
    if max_atoms is not None and most > max_atoms:
        raise ValueError(f"a structure has {most} atoms, more than max_atoms={max_atoms}; leave it out for the largest structure's width")
    return max_atoms or most


def coulomb_matrix(atoms: DataFrame, max_atoms: int | None = None) -> DataFrame:
    """Sorted row norms of the Coulomb matrix (diagonal 0.5 z^2.4), padded with zeros to the width of :func:`_width`."""
    max_atoms = _width(atoms, max_atoms)
    off = pairs(atoms).groupBy("structure_id", "atom_id").agg(F.sum(F.pow(F.col("z") * F.col("z2") / F.col("d"), 2)).alias("s"))
    norms = atoms.join(off, ["structure_id", "atom_id"], "left").select("structure_id", F.sqrt(F.coalesce("s", F.lit(0.0)) + F.pow(0.5 * F.pow(F.col("z").cast("double"), 2.4), 2)).alias("norm"))
    return norms.groupBy("structure_id").agg(F.sort_array(F.collect_list("norm"), asc=False).alias("v")).select("structure_id", F.slice(F.concat("v", F.array_repeat(F.lit(0.0), max_atoms)), 1, max_atoms).alias("norms"))


def coulomb_eigenvalues(atoms: DataFrame, max_atoms: int | None = None) -> DataFrame:
    """The eigenvalue form, by numpy on one structure at a time; padded like the matrix."""
    max_atoms = _width(atoms, max_atoms)

    def one(t):
        import pandas as pd

        p, z = t[["x", "y", "w"]].to_numpy(), t["z"].to_numpy(np.float64)
        d = np.sqrt(((p[:, None] - p[None]) ** 2).sum(-1))
        np.fill_diagonal(d, 1.0)
        m = z[:, None] * z[None] / np.maximum(d, 1e-6)
        np.fill_diagonal(m, 0.5 * z**2.4)
        v = np.sort(np.linalg.eigvalsh(m))[::-1]
        return pd.DataFrame({"structure_id": [t["structure_id"].iloc[0]], "eigenvalues": [np.pad(v, (0, max(0, max_atoms - len(v))))[:max_atoms].tolist()]})

    return atoms.groupBy("structure_id").applyInPandas(one, "structure_id bigint, eigenvalues array<double>")


def flat_coordinates(atoms: DataFrame, lattice: DataFrame | None = None, max_atoms: int | None = None) -> DataFrame:
    """Coordinates in a fixed order, padded like the matrix, after the lattice vectors if there are any."""
    max_atoms = _width(atoms, max_atoms)
    rows = atoms.groupBy("structure_id").agg(F.sort_array(F.collect_list(F.struct("atom_id", "z", "x", "y", "w"))).alias("a"))
    flat = F.flatten(F.transform("a", lambda r: F.array(r["z"].cast("double"), r["x"], r["y"], r["w"])))
    out = rows.select("structure_id", F.slice(F.concat(flat, F.array_repeat(F.lit(0.0), 4 * max_atoms)), 1, 4 * max_atoms).alias("flat"))
    if lattice is None:
        return out
    return out.join(lattice, "structure_id").select("structure_id", F.concat(F.flatten("lattice"), "flat").alias("flat"))


def composition(atoms: DataFrame, elements: tuple[int, ...] = (1, 2, 3, 4, 5, 6, 7), cutoff: float = 10.0) -> DataFrame:
    """Counts of elements and of bond degrees 0 to 3 and more: what a connectivity table knows."""
    joined = neighbour_counts(atoms, cutoff, ("z",)).withColumnRenamed("n", "deg")
    return joined.groupBy("structure_id").agg(*(F.count_if(F.col("z") == e).alias(f"z{e}") for e in elements), *(F.count_if(F.col("deg") == d).alias(f"deg{d}") for d in range(3)), F.count_if(F.col("deg") >= 3).alias("deg3"))


def top_cells(triplets: DataFrame, k: int = 3) -> DataFrame:
    order = Window.partitionBy("structure_id").orderBy(F.col("n").desc(), "cell")
    return triplets.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
