"""Atomic descriptors (the fourth coordinate), pairs of atoms and the pair-sum targets."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Lone pairs by element, and covalent radii in angstrom (H, C, N, O).
LONE_PAIRS = {7: 1, 8: 2}
COVALENT_RADII = {1: 0.31, 6: 0.76, 7: 0.71, 8: 0.66}


def pairs(atoms: DataFrame, min_distance: float = 1e-6) -> DataFrame:
    """All ordered pairs of different atoms of a structure with their distance, ``d``."""
    a = atoms.select("structure_id", "atom_id", "z", "x", "y", "w")
    b = a.select("structure_id", *(F.col(c).alias(f"{c}2") for c in ("atom_id", "z", "x", "y", "w")))
    joined = a.join(b, "structure_id").where("atom_id <> atom_id2")
    d = F.sqrt(F.expr("(x - x2) * (x - x2) + (y - y2) * (y - y2) + (w - w2) * (w - w2)"))
    return joined.select("structure_id", "atom_id", "z", "atom_id2", "z2", F.greatest(d, F.lit(min_distance)).alias("d"))


def neighbours(atoms: DataFrame, cutoff: float | None = None, radii: dict[int, float] | None = None, tolerance: float = 1.3) -> DataFrame:
    """Ordered pairs within a cutoff, or within the sum of covalent radii times a tolerance."""
    p = pairs(atoms)
    if radii is not None:
        table = F.create_map(*(x for k, v in radii.items() for x in (F.lit(k), F.lit(float(v)))))
        return p.where(F.col("d") <= (F.coalesce(F.element_at(table, F.col("z")), F.lit(0.0)) + F.coalesce(F.element_at(table, F.col("z2")), F.lit(0.0))) * tolerance)
    return p.where(F.col("d") <= cutoff)


def neighbours_blocked(atoms: DataFrame, cutoff: float, min_distance: float = 1e-6) -> DataFrame:
    """The same pairs by blocks of one cutoff's side: one side is copied to its 27 blocks, so work follows the
    neighbours and not the square of a structure's atoms."""
    block = lambda c: F.floor(F.col(c) / F.lit(float(cutoff)))
    a = atoms.select("structure_id", "atom_id", "z", "x", "y", "w", *(block(c).alias(f"b{c}") for c in "xyw"))
    b = a
    around = F.array(*(F.lit(i).cast("bigint") for i in (-1, 0, 1)))
    for c in "xyw":
        b = b.withColumn("_s", F.explode(around)).withColumn(f"b{c}", F.col(f"b{c}") + F.col("_s")).drop("_s")
    b = b.select("structure_id", "bx", "by", "bw", *(F.col(c).alias(f"{c}2") for c in ("atom_id", "z", "x", "y", "w")))
    d = F.sqrt(F.expr("(x - x2) * (x - x2) + (y - y2) * (y - y2) + (w - w2) * (w - w2)"))
    joined = a.join(b, ["structure_id", "bx", "by", "bw"]).where("atom_id <> atom_id2")
    return joined.select("structure_id", "atom_id", "z", "atom_id2", "z2", F.greatest(d, F.lit(min_distance)).alias("d")).where(F.col("d") <= cutoff)


def neighbour_counts(atoms: DataFrame, cutoff: float, keep: tuple[str, ...] = (), min_distance: float = 1e-6) -> DataFrame:
    """``structure_id, atom_id, keep.., n``: every atom's number of neighbours within the cutoff, 0 included.

    A structure's atoms are dealt to one task in order of x and each is compared with those that follow until x is
    too far off: no copies and no pairs are shuffled, and a task holds a batch and one structure.
    """
    import numpy as np

    names = ["structure_id", "atom_id", *keep]
    order = Window.partitionBy("structure_id").orderBy("x")
    dealt = atoms.select(*names, "x", "y", "w", F.row_number().over(order).alias("_place"))

    def counted(t):
        import pyarrow as pa

        ids, x, y, w = (t[c].to_numpy() for c in ("structure_id", "x", "y", "w"))
        n, at, step = np.zeros(len(ids), np.int64), np.arange(len(ids)), 0
        while len(at):
            step += 1
            at = at[: np.searchsorted(at, len(ids) - step)]
            at = at[(ids[at + step] == ids[at]) & (x[at + step] - x[at] <= cutoff * (1 + 1e-9))]
            other = at + step
            dx, dy, dw = x[at] - x[other], y[at] - y[other], w[at] - w[other]
            hit = np.maximum(np.sqrt(dx * dx + dy * dy + dw * dw), min_distance) <= cutoff
            n[at[hit]] += 1
            n[other[hit]] += 1
        return t.select(names).append_column("n", pa.array(n)).combine_chunks().to_batches()

    def run(batches):
        import pyarrow as pa

        held = None
        for batch in batches:
            if not batch.num_rows:
                continue
            t = pa.Table.from_batches([batch])
            t = t if held is None else pa.concat_tables([held, t])
            ids = t["structure_id"].to_numpy()
            cut = int(np.searchsorted(ids, ids[-1]))
            if cut:
                yield from counted(t.slice(0, cut))
            held = t.slice(cut)
        if held is not None:
            yield from counted(held)

    kinds = dict(atoms.dtypes)
    return dealt.mapInArrow(run, ", ".join(f"{c} {kinds[c]}" for c in names) + ", n bigint")


def nearest_atoms(atoms: DataFrame, t: int = 3) -> DataFrame:
    """Each atom's t nearest others (ties: smaller id)."""
    order = Window.partitionBy("structure_id", "atom_id").orderBy("d", "atom_id2")
    return pairs(atoms).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= t).select("structure_id", "atom_id", "rank", "atom_id2", "d")


def descriptor_atomic_number(atoms: DataFrame) -> DataFrame:
    return atoms.withColumn("descriptor", F.col("z").cast("double"))


def coordination_value(z: Column, bonds: Column, mode: str = "bonded") -> Column:
    """Atomic number plus coordination: bonded atoms; with lone pairs (steric); or bonds counted twice."""
    if mode == "bonded":
        return z + bonds
    if mode == "double":
        return z + 2 * bonds
    if mode == "steric":
        table = F.create_map(*(F.lit(x) for kv in LONE_PAIRS.items() for x in kv))
        return z + bonds + F.when(bonds > 0, F.coalesce(F.element_at(table, z.cast("int")), F.lit(0))).otherwise(F.lit(0))
    raise ValueError(f"unknown mode {mode}")


def prefers_blocks(atoms: DataFrame) -> bool:
    """Whether 27 copies of every atom are fewer than half of all pairs: one aggregate of counts decides."""
    n = atoms.groupBy("structure_id").agg(F.count("*").cast("double").alias("n"))
    r = n.agg(F.sum(F.col("n") * F.col("n")).alias("pairs"), F.sum("n").alias("atoms")).first()
    return bool(r.atoms) and r.pairs > 54 * r.atoms


def descriptor_coordination(atoms: DataFrame, cutoff: float = 10.0, mode: str = "bonded", blocked: bool | None = None) -> DataFrame:
    """Adds ``descriptor`` = atomic number plus coordination; bonds are pairs within the cutoff.

    Without ``blocked`` the cheaper of the two range joins is taken: all pairs for small structures,
    blocks for large ones.
    """
    blocked = prefers_blocks(atoms) if blocked is None else blocked
    found = (neighbours_blocked if blocked else neighbours)(atoms, cutoff).groupBy("structure_id", "atom_id").agg(F.count("*").alias("_bonds"))
    joined = atoms.join(found, ["structure_id", "atom_id"], "left")
    return joined.withColumn("descriptor", coordination_value(F.col("z"), F.coalesce("_bonds", F.lit(0)), mode).cast("double")).drop("_bonds")


def descriptor_coulomb(atoms: DataFrame, min_distance: float = 1e-6) -> DataFrame:
    """Adds ``descriptor``: sum over the structure's other atoms of charge products over distances."""
    found = pairs(atoms, min_distance).groupBy("structure_id", "atom_id").agg(F.sum(F.col("z") * F.col("z2") / F.col("d")).alias("_c"))
    return atoms.join(found, ["structure_id", "atom_id"], "left").withColumn("descriptor", F.coalesce("_c", F.lit(0.0))).drop("_c")


def descriptor_coulomb_grouped(atoms: DataFrame, min_distance: float = 1e-6) -> DataFrame:
    """The same by numpy, a structure at a time: no pairs are shuffled; for structures that fit a task."""
    import numpy as np

    def one(t):
        p = t[["x", "y", "w"]].to_numpy()
        d = np.sqrt(((p[:, None] - p[None]) ** 2).sum(-1))
        np.fill_diagonal(d, np.inf)
        z = t["z"].to_numpy(np.float64)
        t["descriptor"] = z * (z[None, :] / np.maximum(d, min_distance)).sum(1)
        return t

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in atoms.schema) + ", descriptor double"
    return atoms.groupBy("structure_id").applyInPandas(one, schema)


def descriptor_custom(atoms: DataFrame, fn: Callable[[], Column]) -> DataFrame:
    """Any Column expression over the atoms as the descriptor."""
    return atoms.withColumn("descriptor", fn().cast("double"))


REGISTRY: dict[str, Callable[..., DataFrame]] = {"atomic_number": descriptor_atomic_number, "coordination": descriptor_coordination, "coulomb": descriptor_coulomb, "custom": descriptor_custom}


def pair_targets(atoms: DataFrame) -> DataFrame:
    """Four stand-in energies per structure by exact pair sums: ``t_point, t_ffsum, t_lattice, t_dispersion``.

    Structures of one atom have no pairs; their pair sums are 0.
    """
    half = pairs(atoms).where("atom_id < atom_id2")
    sums = half.groupBy("structure_id").agg(
        F.sum(F.col("z") * F.col("z2") / F.col("d")).alias("f"),
        F.sum(1 / (1 + F.pow(F.col("d") / 6, 6))).alias("l"),
        F.sum(F.col("z") * F.col("z2") / (F.pow("d", 6) + 46656.0)).alias("q"),
    )
    # rounded, so that structures of equal composition tie whatever the order of the sum
    own = atoms.groupBy("structure_id").agg(F.round(-F.sum(0.5 * F.pow(F.col("z").cast("double"), 2.4)), 9).alias("t_point"))
    zero = F.lit(0.0)
    return own.join(sums, "structure_id", "left").select("structure_id", "t_point", F.coalesce("f", zero).alias("t_ffsum"), (-F.coalesce("l", zero)).alias("t_lattice"), (-1e6 * F.coalesce("q", zero)).alias("t_dispersion"))


TARGETS = ("t_point", "t_ffsum", "t_lattice", "t_dispersion")
