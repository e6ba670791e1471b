"""Canonical pose: centre, inertia, principal axes, orientation, spherical coordinates."""

from __future__ import annotations

from itertools import combinations_with_replacement

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

AXES = ("x", "y", "w")
PAIRS = [a + b for a, b in combinations_with_replacement(AXES, 2)]
TRIPLES = [a + b + c for a, b, c in combinations_with_replacement(AXES, 3)]
#: Relative gap below which two moments count as equal.
GAP = 1e-9


def _weight(how: str) -> Column:
    return F.col("mass") if how == "mass" else F.lit(1.0)


def centers(atoms: DataFrame, how: str = "mass", lattice: DataFrame | None = None) -> DataFrame:
    """``structure_id, cx, cy, cw``: mass centre, centroid, or middle of the cell."""
    if how == "cell":
        middle = lambda i: (F.aggregate("lattice", F.lit(0.0), lambda s, v: s + F.get(v, F.lit(i))) / 2).alias(f"c{AXES[i]}")
        return lattice.select("structure_id", *(middle(i) for i in range(3)))
    m = _weight(how)
    return atoms.groupBy("structure_id").agg(*((F.sum(m * F.col(a)) / F.sum(m)).alias(f"c{a}") for a in AXES))


def center(atoms: DataFrame, how: str = "mass", lattice: DataFrame | None = None) -> DataFrame:
    """Atoms relative to their structure's centre."""
    c = centers(atoms, how, lattice)
    keep = [k for k in atoms.columns if k not in AXES]
    return atoms.join(c, "structure_id").select(*keep, *((F.col(a) - F.col(f"c{a}")).alias(a) for a in AXES))


def moments(atoms: DataFrame, how: str = "mass") -> DataFrame:
    """Centre and central second and third moments of each structure from one aggregate of raw sums.

    20 partial sums are all that is shuffled; :func:`inertia` is the two-pass form for comparison.
    """
    m = _weight(how)
    product = lambda key: _times([F.col(a) for a in key])
    raw = atoms.groupBy("structure_id").agg(
        F.count("*").alias("n_atoms"), F.sum(m).alias("m"),
        *(F.sum(m * F.col(a)).alias(f"s{a}") for a in AXES),
        *(F.sum(m * product(p)).alias(f"s{p}") for p in PAIRS),
        *(F.sum(m * product(t)).alias(f"s{t}") for t in TRIPLES),
    )
    raw = raw.withColumns({f"c{a}": F.col(f"s{a}") / F.col("m") for a in AXES})
    c = {a: F.col(f"c{a}") for a in AXES}
    m0 = F.col("m")
    second = {f"m{a}{b}": F.col(f"s{a}{b}") - m0 * c[a] * c[b] for a, b in (tuple(p) for p in PAIRS)}
    s2 = lambda a, b: F.col("s" + "".join(sorted((a, b), key=AXES.index)))
    third = {}
    for t in TRIPLES:
        a, b, d = t
        third[f"m{t}"] = F.col(f"s{t}") - c[a] * s2(b, d) - c[b] * s2(a, d) - c[d] * s2(a, b) + 2 * m0 * c[a] * c[b] * c[d]
    return raw.withColumns(second | third).select("structure_id", "n_atoms", "m", *c.values(), *(f"m{p}" for p in PAIRS), *(f"m{t}" for t in TRIPLES))


def _times(cols: list[Column]) -> Column:
    out = cols[0]
    for c in cols[1:]:
        out = out * c
    return out


def inertia(atoms: DataFrame) -> DataFrame:
    """The six entries of the inertia tensor about the mass centre (two passes)."""
    a = center(atoms)
    m, x, y, w = (F.col(k) for k in ("mass", *AXES))
    return a.groupBy("structure_id").agg(
        F.sum(m * (y * y + w * w)).alias("ixx"), F.sum(m * (x * x + w * w)).alias("iyy"), F.sum(m * (x * x + y * y)).alias("iww"),
        (-F.sum(m * x * y)).alias("ixy"), (-F.sum(m * x * w)).alias("ixw"), (-F.sum(m * y * w)).alias("iyw"),
    )


def axis_steps(gap: float = GAP) -> list[dict[str, str]]:
    """Closed-form eigenvalues and eigenvectors of the second moments as SQL that engines share.

    In: mxx..mww (second moments) and mxxx..mwww (third).  Out: moments e1 <= e2 <= e3 of inertia and
    rotation rows (r11..r33).  Inertia's eigenvectors are the second moments', its order reversed.  Where
    moments coincide the missing axis is completed from the coordinate axis that lies farthest off; a
    sign makes the third moment along an axis positive, or its largest component where that is 0.
    """
    steps: list[dict[str, str]] = [
        {"q": "(mxx + myy + mww) / 3"},
        {"p": "sqrt(greatest(((mxx - q) * (mxx - q) + (myy - q) * (myy - q) + (mww - q) * (mww - q) + 2 * (mxy * mxy + mxw * mxw + myw * myw)) / 6, CAST(0 AS DOUBLE)))"},
        {"flat": f"p <= {gap} * q OR q <= 0"},
        {"det": "CASE WHEN flat THEN CAST(0 AS DOUBLE) ELSE ((mxx - q) * ((myy - q) * (mww - q) - myw * myw) - mxy * (mxy * (mww - q) - myw * mxw) + mxw * (mxy * myw - (myy - q) * mxw)) / (2 * p * p * p) END"},
        {"phi": "acos(greatest(CAST(-1 AS DOUBLE), least(CAST(1 AS DOUBLE), det))) / 3"},
        {"l1": "q + 2 * p * cos(phi)", "l3": "q + 2 * p * cos(phi + 2 * pi() / 3)"},
        {"l2": "3 * q - l1 - l3"},
        {"gap1": f"NOT flat AND l1 - l2 > {gap} * l1", "gap3": f"NOT flat AND l2 - l3 > {gap} * l1"},
    ]
    for v in ("1", "3"):
        lam = f"l{v}"
        rows = ((f"(mxx - {lam})", "mxy", "mxw"), ("mxy", f"(myy - {lam})", "myw"), ("mxw", "myw", f"(mww - {lam})"))
        for k, (i, j) in enumerate(((0, 1), (0, 2), (1, 2))):
            a, b = rows[i], rows[j]
            cross = [f"{a[1]} * {b[2]} - {a[2]} * {b[1]}", f"{a[2]} * {b[0]} - {a[0]} * {b[2]}", f"{a[0]} * {b[1]} - {a[1]} * {b[0]}"]
            steps.append({f"k{k}{d}": c for d, c in enumerate(cross)})
        steps.append({f"n{k}": f"k{k}0 * k{k}0 + k{k}1 * k{k}1 + k{k}2 * k{k}2" for k in range(3)})
        steps.append({f"a{v}{d}": f"CASE WHEN n0 >= n1 AND n0 >= n2 THEN k0{d} WHEN n1 >= n2 THEN k1{d} ELSE k2{d} END" for d in range(3)})
        steps.append({f"s{v}": f"sqrt(a{v}0 * a{v}0 + a{v}1 * a{v}1 + a{v}2 * a{v}2)"})
        steps.append({f"a{v}{d}": f"CASE WHEN s{v} > 0 THEN a{v}{d} / s{v} ELSE CAST(0 AS DOUBLE) END" for d in range(3)})
        steps.append({f"gap{v}": f"gap{v} AND s{v} > 0"})
    # an axis known alone: its companion starts from the coordinate axis with its least component
    off = lambda v, d: f"CASE WHEN abs(a{v}0) <= abs(a{v}1) AND abs(a{v}0) <= abs(a{v}2) THEN {1 if d == 0 else 0} WHEN abs(a{v}1) <= abs(a{v}2) THEN {1 if d == 1 else 0} ELSE {1 if d == 2 else 0} END"
    steps.append({f"o1{d}": off("1", d) for d in range(3)} | {f"o3{d}": off("3", d) for d in range(3)})
    steps.append({"t1": "o10 * a10 + o11 * a11 + o12 * a12", "t3": "o30 * a30 + o31 * a31 + o32 * a32"})
    steps.append({f"o1{d}": f"o1{d} - t1 * a1{d}" for d in range(3)} | {f"o3{d}": f"o3{d} - t3 * a3{d}" for d in range(3)})
    steps.append({"t1": "sqrt(o10 * o10 + o11 * o11 + o12 * o12)", "t3": "sqrt(o30 * o30 + o31 * o31 + o32 * o32)"})
    unit = (("1", "0", "0"), ("0", "1", "0"), ("0", "0", "1"))
    steps.append({f"b1{d}": f"CASE WHEN gap1 THEN a1{d} WHEN gap3 THEN o3{d} / t3 ELSE CAST({unit[0][d]} AS DOUBLE) END" for d in range(3)} | {f"b3{d}": f"CASE WHEN gap3 THEN a3{d} WHEN gap1 THEN o1{d} / t1 ELSE CAST({unit[2][d]} AS DOUBLE) END" for d in range(3)})
    # the third is made exactly perpendicular to the first, the second completes them
    steps.append({"t3": "b30 * b10 + b31 * b11 + b32 * b12"})
    steps.append({f"b3{d}": f"b3{d} - t3 * b1{d}" for d in range(3)})
    steps.append({"t3": "sqrt(b30 * b30 + b31 * b31 + b32 * b32)"})
    steps.append({f"b3{d}": f"b3{d} / t3" for d in range(3)})
    steps.append({"b20": "b31 * b12 - b32 * b11", "b21": "b32 * b10 - b30 * b12", "b22": "b30 * b11 - b31 * b10"})
    index = {a: d for d, a in enumerate(AXES)}
    for v in ("1", "2"):
        terms = []
        for t in TRIPLES:
            n = {1: 1, 2: 3, 3: 6}[len(set(t))]
            terms.append(f"{n} * m{t} * " + " * ".join(f"b{v}{index[a]}" for a in t))
        steps.append({f"c{v}3": " + ".join(terms)})
        big = f"CASE WHEN abs(b{v}0) >= abs(b{v}1) - {gap} AND abs(b{v}0) >= abs(b{v}2) - {gap} THEN b{v}0 WHEN abs(b{v}1) >= abs(b{v}2) - {gap} THEN b{v}1 ELSE b{v}2 END"
        steps.append({f"g{v}": f"CASE WHEN abs(c{v}3) > {gap} * m * power(greatest(l1 / m, CAST(0 AS DOUBLE)), 1.5) THEN (CASE WHEN c{v}3 < 0 THEN -1 ELSE 1 END) ELSE (CASE WHEN {big} < 0 THEN -1 ELSE 1 END) END"})
    steps.append({f"r1{d + 1}": f"g1 * b1{d}" for d in range(3)} | {f"r2{d + 1}": f"g2 * b2{d}" for d in range(3)})
    steps.append({"r31": "r12 * r23 - r13 * r22", "r32": "r13 * r21 - r11 * r23", "r33": "r11 * r22 - r12 * r21"})
    steps.append({"e1": "l2 + l3", "e2": "l1 + l3", "e3": "l1 + l2"})
    return steps


ROTATION = [f"r{i}{j}" for i in (1, 2, 3) for j in (1, 2, 3)]


def principal_axes(moment_rows: DataFrame, gap: float = GAP, backend: str = "sql") -> DataFrame:
    """``structure_id, cx, cy, cw, e1..e3, r11..r33`` from :func:`moments`.

    ``sql`` is pure Column arithmetic in generated code; ``eigh`` is the check by numpy in Arrow batches.
    """
    if backend == "eigh":
        return moment_rows.mapInPandas(_eigh, "structure_id bigint, n_atoms bigint, m double, cx double, cy double, cw double, e1 double, e2 double, e3 double, " + ", ".join(f"{r} double" for r in ROTATION))
    out = moment_rows
    for step in axis_steps(gap):
        out = out.withColumns({k: F.expr(v) for k, v in step.items()})
    return out.select("structure_id", "n_atoms", "m", "cx", "cy", "cw", "e1", "e2", "e3", *ROTATION)


def _eigh(batches):
    import pandas as pd

    for t in batches:
        out = []
        for r in t.to_dict("records"):
            c = np.array([[r["mxx"], r["mxy"], r["mxw"]], [r["mxy"], r["myy"], r["myw"]], [r["mxw"], r["myw"], r["mww"]]])
            value, vector = np.linalg.eigh(c)
            rows = [vector[:, 2], vector[:, 1]]
            for i, v in enumerate(rows):
                cube = sum({1: 1, 2: 3, 3: 6}[len(set(k))] * r["m" + k] * np.prod([v[AXES.index(a)] for a in k]) for k in TRIPLES)
                rows[i] = v if cube >= 0 else -v
            rows.append(np.cross(rows[0], rows[1]))
            out.append([r["structure_id"], r["n_atoms"], r["m"], r["cx"], r["cy"], r["cw"], value[0] + value[1], value[0] + value[2], value[1] + value[2], *np.concatenate(rows)])
        yield pd.DataFrame(out, columns=["structure_id", "n_atoms", "m", "cx", "cy", "cw", "e1", "e2", "e3", *ROTATION])


def fix_signs(atoms: DataFrame, axes: DataFrame) -> DataFrame:
    """Axes whose third moment is clear keep its sign; otherwise the farthest atom decides (ties: heaviest).

    Atoms and axes are already dealt by structure, so the aggregate needs no further shuffle.
    """
    joined = atoms.join(axes, "structure_id")
    d = {a: F.col(a) - F.col(f"c{a}") for a in AXES}
    along = lambda i: sum((F.col(f"r{i}{j + 1}") * d[a] for j, a in enumerate(AXES)), F.lit(0.0))
    far = F.struct(F.round(d["x"] * d["x"] + d["y"] * d["y"] + d["w"] * d["w"], 9).alias("r2"), F.col("mass"))
    per = joined.groupBy("structure_id").agg(*(F.sum(F.col("mass") * F.pow(along(i), 3)).alias(f"_t{i}") for i in (1, 2)), *(F.max_by(along(i), far).alias(f"_f{i}") for i in (1, 2)), F.sum("mass").alias("_m"), F.max(far["r2"]).alias("_r2"))
    out = axes.join(per, "structure_id")
    for i in (1, 2):
        sign = F.when(F.abs(F.col(f"_t{i}")) > GAP * F.col("_m") * F.pow("_r2", 1.5), F.signum(f"_t{i}")).otherwise(F.when(F.col(f"_f{i}") < 0, F.lit(-1.0)).otherwise(F.lit(1.0)))
        out = out.withColumns({f"r{i}{j}": F.col(f"r{i}{j}") * sign for j in (1, 2, 3)})
    third = {"r31": F.expr("r12 * r23 - r13 * r22"), "r32": F.expr("r13 * r21 - r11 * r23"), "r33": F.expr("r11 * r22 - r12 * r21")}
    return out.withColumns(third).select(axes.columns)


def central_moments(centered: DataFrame) -> DataFrame:
    """Central moments of atoms that are centred already, added up in the order in which SQL multiplies.

    Raw sums less the centre's lose digits: in a flat structure an atom of the plane then leaves it by more than
    the 9 decimals that are kept, and falls into the next bin of the polar angle.
    """
    total = lambda key: F.sum(_times([F.col("mass"), *(F.col(a) for a in key)])).alias(f"m{key}")
    return centered.groupBy("structure_id").agg(F.count("*").alias("n_atoms"), F.sum("mass").alias("m"), *(F.lit(0.0).alias(f"c{a}") for a in AXES), *(total(k) for k in PAIRS + TRIPLES))


def orient(atoms: DataFrame, axes: DataFrame) -> DataFrame:
    """Atoms in the frame of their principal axes, about the centre."""
    keep = [k for k in atoms.columns if k not in AXES]
    joined = atoms.join(axes.drop("n_atoms", "m"), "structure_id")
    turned = [sum(((F.col(a) - F.col(f"c{a}")) * F.col(f"r{i + 1}{j + 1}") for j, a in enumerate(AXES)), F.lit(0.0)).alias(name) for i, name in enumerate(AXES)]
    return joined.select(*keep, *turned)


def pose(atoms: DataFrame, how: str = "mass") -> DataFrame:
    """Centre, take the moments of the centred atoms, and orient; the atoms are dealt by structure for all three."""
    centered = center(atoms, how)
    weighed = centered if how == "mass" else centered.withColumn("mass", F.lit(1.0))
    return orient(centered, principal_axes(central_moments(weighed)))


def to_spherical(atoms: DataFrame) -> DataFrame:
    """``r, polar, azimuth`` in place of the coordinates; at r = 0 both angles are 0; no negative zeros."""
    x, y, w = (F.round(F.col(a), 9) + F.lit(0.0) for a in AXES)
    keep = [k for k in atoms.columns if k not in AXES]
    out = atoms.select(*keep, x.alias("x"), y.alias("y"), w.alias("w")).withColumn("r", F.sqrt(F.expr("x * x + y * y + w * w")))
    polar = F.when(F.col("r") > 0, F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), F.col("w") / F.col("r"))))).otherwise(F.lit(0.0))
    azimuth = F.when((F.col("x") != 0) | (F.col("y") != 0), F.atan2("y", "x")).otherwise(F.lit(0.0))
    return out.select(*keep, "r", polar.alias("polar"), azimuth.alias("azimuth"))


def replicate_images(atoms: DataFrame, lattice: DataFrame, n: int = 1, radius: float | None = None) -> DataFrame:
    """Periodic images of the atoms, shifts -n..n along each lattice vector; (2n+1)^3 constant offsets.

    Far images are dropped before anything is shuffled.
    """
    spark = atoms.sparkSession
    side = list(range(-n, n + 1))
    offsets = spark.createDataFrame([(i, j, k) for i in side for j in side for k in side], "na int, nb int, nc int")
    joined = atoms.join(lattice, "structure_id").join(F.broadcast(offsets))
    shift = lambda d: sum((F.col(c) * F.get(F.get("lattice", F.lit(v)), F.lit(d)) for v, c in enumerate(("na", "nb", "nc"))), F.lit(0.0))
    keep = [k for k in atoms.columns if k not in AXES]
    out = joined.select(*keep, *((F.col(a) + shift(d)).alias(a) for d, a in enumerate(AXES)), "na", "nb", "nc")
    return out if radius is None else out.where(F.expr(f"x * x + y * y + w * w <= {float(radius) ** 2}"))
