"""Queries of the methods, alternatives, baselines and measures."""

from __future__ import annotations

from functools import reduce
from operator import and_

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import curves
from ..operators import curation, descriptors, encode, features, geometry, learn, lsi, metrics
from ..operators.encode import EncodeConfig
from ..session import fresh_path, written
from ..sources.tables import atoms_from_lineitem, lattice_of, load, points_from_embeddings
from . import experiments as ex
from . import sql
from .registry import query

ENERGIES = ["point", "ffsum", "lattice", "dispersion"]


def _atoms(spark: SparkSession, d: str, by: str = "part", ids: bool = True) -> DataFrame:
    return atoms_from_lineitem(spark, d, by, ids)


def _rounded(df: DataFrame, digits: int, *names: str) -> DataFrame:
    return df.withColumns({c: F.round(F.col(c), digits) + F.lit(0.0) for c in names})


def _r(digits: int, *names: str, expr: dict[str, str] | None = None) -> str:
    return ", ".join(f"round({(expr or {}).get(c, c)}, {digits}) + 0e0 AS {c}" for c in names)


def _steady(df: DataFrame, digits: int, *names: str) -> DataFrame:
    """Rounded just off the half steps, where sums in another order would fall to the other side."""
    return df.withColumns({c: F.round(F.col(c) + F.lit(1.3 * 10.0 ** -(digits + 1)), digits) + F.lit(0.0) for c in names})


def _s(digits: int, *names: str, expr: dict[str, str] | None = None) -> str:
    return ", ".join(f"round({(expr or {}).get(c, c)} + 1.3e{-(digits + 1)}, {digits}) + 0e0 AS {c}" for c in names)


# ---- curation -----------------------------------------------------------------------------------

_FACTS = """facts AS (SELECT l_partkey AS structure_id, bool_and(l_linenumber BETWEEN 1 AND 7) AS elements, avg(l_tax) AS tax, count(*) AS n_atoms, avg(CASE WHEN l_returnflag = 'R' THEN 1e0 ELSE 0e0 END) AS dis,
  bool_and(l_quantity IS NOT NULL AND l_extendedprice IS NOT NULL AND l_shipdate IS NOT NULL) AS coordinates, bool_or(l_discount >= 0.10e0 AND l_quantity = 50) AS charged FROM lineitem GROUP BY l_partkey),
checked AS (SELECT structure_id, elements, p_size <= 45 AS r_factor, tax <= 0.048e0 AS temperature, n_atoms <= 40 AS molecules, p_type <> 'PROMO' AS distinct_, dis <= 0.5e0 AS disorder, coordinates, charged FROM part JOIN facts ON p_partkey = structure_id)"""
_ALL_RULES = "elements AND r_factor AND temperature AND molecules AND distinct_ AND disorder AND coordinates"


@query("m1_curation_audit", f"WITH {_FACTS} SELECT count(*) AS \"all\", " + ", ".join(f"count(*) FILTER ({c}) AS {n}" for c, n in (("elements", "elements"), ("r_factor", "r_factor"), ("temperature", "temperature"), ("molecules", "molecules"), ("distinct_", '"distinct"'), ("disorder", "disorder"), ("coordinates", "coordinates"))) + f", count(*) FILTER ({_ALL_RULES}) AS rules, count(*) FILTER ({_ALL_RULES} AND NOT charged) AS kept FROM checked")
def m1_curation_audit(spark, d):
    return curation.curate(load(spark, d, "part"), load(spark, d, "lineitem"))[1]


@query("m1_curated", f"WITH {_FACTS} SELECT structure_id FROM checked WHERE {_ALL_RULES} AND NOT charged")
def m1_curated(spark, d):
    return curation.curate(load(spark, d, "part"), load(spark, d, "lineitem"))[0]


@query("m1a_exclude_charged", "SELECT p_partkey AS structure_id FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_discount >= 0.10e0 AND l_quantity = 50)")
def m1a(spark, d):
    return curation.exclude(load(spark, d, "part").select(F.col("p_partkey").alias("structure_id")), curation.charged_ids(load(spark, d, "lineitem")))


# ---- pose ---------------------------------------------------------------------------------------

_BASE = f"{sql.atoms()}, {sql.CENTERED}"


@query("m2_center", f"WITH {_BASE} SELECT structure_id, atom_id, {_s(6, 'x', 'y', 'w')} FROM centered")
def m2(spark, d):
    return _steady(geometry.center(_atoms(spark, d)), 6, "x", "y", "w").select("structure_id", "atom_id", "x", "y", "w")


@query("m2_center_centroid", f"WITH {sql.atoms()} SELECT structure_id, {_r(6, 'cx', 'cy', 'cw', expr={'cx': 'avg(x)', 'cy': 'avg(y)', 'cw': 'avg(w)'})} FROM atoms GROUP BY structure_id")
def m2b(spark, d):
    return _rounded(geometry.centers(_atoms(spark, d, ids=False), "centroid"), 6, "cx", "cy", "cw")


@query("m2_center_cell", f"WITH {sql.atoms()} SELECT structure_id, {_r(6, 'x', expr={'x': 'sum(x - 25e0)'})} FROM atoms GROUP BY structure_id")
def m2c(spark, d):
    a = _atoms(spark, d, ids=False)
    return geometry.center(a, "cell", lattice_of(a)).groupBy("structure_id").agg((F.round(F.sum("x"), 6) + F.lit(0.0)).alias("x"))


_IMAGES = "SELECT a.structure_id, count(*) AS images, {r} FROM centered a, (SELECT unnest(range(-1, 2)) AS na), (SELECT unnest(range(-1, 2)) AS nb), (SELECT unnest(range(-1, 2)) AS nc) WHERE power(x + 50e0 * na, 2) + power(y + 50e0 * nb, 2) + power(w + 50e0 * nc, 2) <= 3600e0 GROUP BY a.structure_id"


@query("m3_periodic_images", f"WITH {sql.atoms('order')}, {sql.CENTERED} " + _IMAGES.format(r="round(sum(x + 50e0 * na), 4) + 0e0 AS x"))
def m3(spark, d):
    a = _atoms(spark, d, "order", ids=False)
    images = geometry.replicate_images(geometry.center(a), lattice_of(a), 1, 60.0)
    return images.groupBy("structure_id").agg(F.count("*").alias("images"), (F.round(F.sum("x"), 4) + F.lit(0.0)).alias("x"))


_INERTIA = ("ixx", "iyy", "iww", "ixy", "ixw", "iyw")


@query("m4_inertia", f"WITH {_BASE} SELECT structure_id, " + _s(4, *_INERTIA, expr=dict(zip(_INERTIA, ("sum(mass * (y * y + w * w))", "sum(mass * (x * x + w * w))", "sum(mass * (x * x + y * y))", "-sum(mass * x * y)", "-sum(mass * x * w)", "-sum(mass * y * w)")))) + " FROM centered GROUP BY structure_id")
def m4(spark, d):
    return _steady(geometry.inertia(_atoms(spark, d, ids=False)), 4, *_INERTIA)


@query("m4_moments_one_pass", f"WITH {_BASE}, {sql.MOMENTS} SELECT structure_id, n_atoms, {_s(4, 'mxx', 'mxy', 'mww', 'mxxx', 'mxyw')} FROM moments")
def m4b(spark, d):
    return _steady(geometry.moments(_atoms(spark, d, ids=False)), 4, "mxx", "mxy", "mww", "mxxx", "mxyw").select("structure_id", "n_atoms", "mxx", "mxy", "mww", "mxxx", "mxyw")


@query("m5_principal_axes", f"WITH {_BASE}, {sql.MOMENTS}, {sql.AXES} SELECT structure_id, {_r(4, 'e1', 'e2', 'e3')}, {_r(6, *geometry.ROTATION)} FROM axes")
def m5(spark, d):
    axes = geometry.principal_axes(geometry.moments(_atoms(spark, d, ids=False)))
    return _rounded(_rounded(axes, 4, "e1", "e2", "e3"), 6, *geometry.ROTATION).select("structure_id", "e1", "e2", "e3", *geometry.ROTATION)


@query("m5_axes_against_eigh", f"WITH {_BASE}, {sql.MOMENTS}, {sql.AXES} SELECT structure_id, {_r(4, 'e1', 'e2', 'e3')}, {_r(5, *geometry.ROTATION)} FROM axes")
def m5_eigh(spark, d):
    """The library's eigenvectors, held against the closed form written in SQL."""
    axes = geometry.principal_axes(geometry.moments(_atoms(spark, d, ids=False)), backend="eigh")
    return _rounded(_rounded(axes, 4, "e1", "e2", "e3"), 5, *geometry.ROTATION).select("structure_id", "e1", "e2", "e3", *geometry.ROTATION)


_UNIT = "r11 * r11 + r12 * r12 + r13 * r13 + r21 * r21 + r22 * r22 + r23 * r23 + r31 * r31 + r32 * r32 + r33 * r33"


@query("m5a_degenerate_axes", f"WITH {sql.atoms('order')}, {sql.CENTERED}, {sql.MOMENTS}, {sql.AXES} SELECT structure_id, n_atoms, n_atoms = 1 OR e1 <= 1e-6 * e3 AS on_a_line, round({_UNIT}, 5) AS unit FROM axes WHERE n_atoms <= 2")
def m5a(spark, d):
    axes = geometry.principal_axes(geometry.moments(_atoms(spark, d, "order", ids=False))).where("n_atoms <= 2")
    return axes.select("structure_id", "n_atoms", F.expr("n_atoms = 1 OR e1 <= 1e-6D * e3").alias("on_a_line"), F.round(F.expr(_UNIT), 5).alias("unit"))


@query("m5b_fix_signs", f"WITH {_BASE}, {sql.MOMENTS}, {sql.AXES} SELECT structure_id, {_r(6, *geometry.ROTATION)} FROM axes")
def m5b(spark, d):
    """Axes turned over first, so that the sign rule has all of them to turn back (the third follows from two)."""
    a = _atoms(spark, d, ids=False)
    axes = geometry.principal_axes(geometry.moments(a))
    turned = axes.withColumns({c: -F.col(c) for c in geometry.ROTATION if c[1] in "12"})
    return _rounded(geometry.fix_signs(a, turned), 6, *geometry.ROTATION).select("structure_id", *geometry.ROTATION)


@query("m6_orient", f"WITH {_BASE}, {sql.MOMENTS}, {sql.AXES}, {sql.ORIENTED} SELECT structure_id, atom_id, {_r(5, 'x', 'y', 'w')} FROM oriented")
def m6(spark, d):
    return _rounded(geometry.pose(_atoms(spark, d)), 5, "x", "y", "w").select("structure_id", "atom_id", "x", "y", "w")


@query("m7_spherical", f"WITH {sql.atoms()}, {sql.POSE} SELECT structure_id, atom_id, {_r(5, 'r', 'polar', 'azimuth')} FROM spherical")
def m7(spark, d):
    return _rounded(geometry.to_spherical(geometry.pose(_atoms(spark, d))), 5, "r", "polar", "azimuth").select("structure_id", "atom_id", "r", "polar", "azimuth")


# ---- descriptors --------------------------------------------------------------------------------


@query("m8_d1_atomic_number", f"WITH {sql.atoms()} SELECT structure_id, atom_id, CAST(z AS DOUBLE) AS descriptor FROM atoms")
def m8(spark, d):
    return descriptors.descriptor_atomic_number(_atoms(spark, d)).select("structure_id", "atom_id", "descriptor")


_BONDS = f"{sql.PAIRS}, bonds AS (SELECT structure_id, atom_id, count(*) AS b FROM pairs WHERE d <= 10 GROUP BY structure_id, atom_id)"


def _d2(mode: str, value: str) -> None:
    @query(f"m9_d2_{mode}", f"WITH {sql.atoms()}, {_BONDS} SELECT structure_id, atom_id, CAST({value} AS DOUBLE) AS descriptor FROM atoms LEFT JOIN bonds USING (structure_id, atom_id)")
    def run(spark, d):
        return descriptors.descriptor_coordination(_atoms(spark, d), 10.0, mode).select("structure_id", "atom_id", "descriptor")


_d2("bonded", "z + coalesce(b, 0)")
_d2("double", "z + 2 * coalesce(b, 0)")
_d2("steric", "z + coalesce(b, 0) + CASE WHEN b > 0 AND z = 7 THEN 1 WHEN b > 0 AND z = 8 THEN 2 ELSE 0 END")


@query("m9a_bonds_by_radii", f"WITH {sql.atoms()}, {sql.PAIRS} SELECT structure_id, count(*) AS bonds FROM pairs WHERE d <= 13e0 * ((CASE z WHEN 1 THEN 0.31e0 WHEN 6 THEN 0.76e0 WHEN 7 THEN 0.71e0 ELSE 0 END) + (CASE z2 WHEN 1 THEN 0.31e0 WHEN 6 THEN 0.76e0 WHEN 7 THEN 0.71e0 ELSE 0 END)) GROUP BY structure_id")
def m9a(spark, d):
    return descriptors.neighbours(_atoms(spark, d), radii=descriptors.COVALENT_RADII, tolerance=13.0).groupBy("structure_id").agg(F.count("*").alias("bonds"))


_COULOMB = f"{sql.PAIRS}, charge AS (SELECT structure_id, atom_id, sum(z * z2 / d) AS c FROM pairs GROUP BY structure_id, atom_id)"
_D3_ORACLE = f"WITH {sql.atoms()}, {_COULOMB} SELECT structure_id, atom_id, round(coalesce(c, 0), 6) AS descriptor FROM atoms LEFT JOIN charge USING (structure_id, atom_id)"


@query("m10_d3_coulomb", _D3_ORACLE)
def m10(spark, d):
    return _rounded(descriptors.descriptor_coulomb(_atoms(spark, d)), 6, "descriptor").select("structure_id", "atom_id", "descriptor")


@query("m10_d3_coulomb_grouped", _D3_ORACLE)
def m10b(spark, d):
    return _rounded(descriptors.descriptor_coulomb_grouped(_atoms(spark, d)), 6, "descriptor").select("structure_id", "atom_id", "descriptor")


@query("m11_custom_descriptor", f"WITH {sql.atoms()} SELECT structure_id, atom_id, round(z * z + sqrt(abs(x)), 6) AS descriptor FROM atoms")
def m11(spark, d):
    made = descriptors.descriptor_custom(_atoms(spark, d), lambda: F.col("z") * F.col("z") + F.sqrt(F.abs(F.col("x"))))
    return _rounded(made, 6, "descriptor").select("structure_id", "atom_id", "descriptor")


# ---- grid and curves ----------------------------------------------------------------------------

_D1 = sql.d1()


@query("m12_quantize", f"WITH {_D1} SELECT structure_id, atom_id, q0, q1, q2, q3 FROM quantised")
def m12(spark, d):
    s = encode.spherical_atoms(_atoms(spark, d))
    return encode.quantize(encode.within_sphere(s), encode.spherical_grid()).select("structure_id", "atom_id", *(F.col(f"q{i}").cast("bigint").alias(f"q{i}") for i in range(4)))


@query("m12_quantize_clamped", f"WITH {sql.atoms()}, {sql.POSE} SELECT structure_id, atom_id, {sql.bin_of('r', '0e0', '30e0', 4)} AS q1 FROM spherical")
def m12b(spark, d):
    s = encode.spherical_atoms(_atoms(spark, d))
    return encode.quantize(s, encode.spherical_grid(radius=30.0)).select("structure_id", "atom_id", F.col("q1").cast("bigint").alias("q1"))


@query("m12a_fit_ranges", f"WITH {sql.atoms()}, {_COULOMB} SELECT round(min(coalesce(c, 0)), 6) AS lo, round(max(coalesce(c, 0)), 6) AS hi FROM atoms LEFT JOIN charge USING (structure_id, atom_id)")
def m12a(spark, d):
    lo, hi = encode.fit_ranges(descriptors.descriptor_coulomb(_atoms(spark, d)), "descriptor")
    return spark.createDataFrame([(round(lo, 6), round(hi, 6))], "lo double, hi double")


_GRID_LINE = "SELECT CAST(l_linenumber AS BIGINT) AS a, CAST(l_quantity AS BIGINT) % 16 AS b, l_partkey % 16 AS c, l_suppkey % 16 AS e FROM lineitem"


def _grid_line(spark, d):
    return load(spark, d, "lineitem").select(F.col("l_linenumber").cast("bigint").alias("a"), F.pmod(F.col("l_quantity").cast("bigint"), F.lit(16)).alias("b"), F.pmod("l_partkey", F.lit(16)).alias("c"), F.pmod("l_suppkey", F.lit(16)).alias("e"))


_FOUR = ["a", "b", "c", "e"]


@query("m13_morton_encode", f"WITH g AS ({_GRID_LINE}) SELECT {sql.interleaved(_FOUR, 4)} AS code, count(*) AS n FROM g GROUP BY 1")
def m13(spark, d):
    return _grid_line(spark, d).groupBy(curves.morton_encode(_FOUR, 4).alias("code")).agg(F.count("*").alias("n"))


@query("m13_morton_8_bits", f"WITH g AS (SELECT a * 31 AS a, b * 15 AS b, c * 16 AS c, e * 17 AS e FROM ({_GRID_LINE})) SELECT {sql.interleaved(_FOUR, 8)} AS code, count(*) AS n FROM g GROUP BY 1")
def m13_8(spark, d):
    g = _grid_line(spark, d).select((F.col("a") * 31).alias("a"), (F.col("b") * 15).alias("b"), (F.col("c") * 16).alias("c"), (F.col("e") * 17).alias("e"))
    return g.groupBy(curves.morton_encode(_FOUR, 8).alias("code")).agg(F.count("*").alias("n"))


@query("m13a_morton_decode", f"SELECT a, b, c, e, count(*) AS n FROM ({_GRID_LINE}) GROUP BY ALL")
def m13a(spark, d):
    coded = _grid_line(spark, d).select(curves.morton_encode(_FOUR, 4).alias("code"))
    return coded.select(*(c.alias(n) for c, n in zip(curves.morton_decode("code", 4, 4), _FOUR))).groupBy(*_FOUR).agg(F.count("*").alias("n"))


_KEYS = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]


@query("m13b_morton_wide", f"WITH g AS (SELECT DISTINCT l_orderkey, l_partkey, l_suppkey, CAST(l_linenumber AS BIGINT) AS l_linenumber FROM lineitem) SELECT *, {sql.interleaved([f'({c} >> 15)' for c in _KEYS], 9)} AS high, {sql.interleaved([f'({c} & 32767)' for c in _KEYS], 15)} AS low FROM g")
def m13b(spark, d):
    """24 bits of four columns: an index of 96 bits in two words, of all lines."""
    line = load(spark, d, "lineitem").select(*(F.col(c).cast("bigint").alias(c) for c in _KEYS)).distinct()
    wide = line.withColumn("words", curves.morton_encode_wide(_KEYS, 24))
    return wide.select(*_KEYS, F.get("words", F.lit(0)).alias("high"), F.get("words", F.lit(1)).alias("low"))


@query("m14_histogram", f"WITH {_D1} SELECT structure_id, cell, n FROM histogram")
def m14(spark, d):
    return encode.encode_structures(_atoms(spark, d, ids=False))


@query("m14a_sparse_vectors", f"WITH {_D1} SELECT structure_id, CAST(string_agg(cell || ':' || n, ' ' ORDER BY cell) AS VARCHAR) AS bins FROM histogram GROUP BY structure_id")
def m14a(spark, d):
    s = encode.to_sparse(encode.encode_structures(_atoms(spark, d, ids=False)))
    return s.select("structure_id", F.array_join(F.zip_with("cells", "counts", lambda c, n: F.concat(c.cast("string"), F.lit(":"), n.cast("string"))), " ").alias("bins"))


@query("m14b_traverse", f"WITH {_D1} SELECT cell, sum(n)::BIGINT AS n, count(*) AS structures FROM histogram GROUP BY cell")
def m14b(spark, d):
    t = encode.traverse(encode.encode_structures(_atoms(spark, d, ids=False)))
    return t.groupBy("cell").agg(F.sum("n").alias("n"), F.count("*").alias("structures"))


@query("m15_encode_d1_orders", f"WITH {sql.d1('order')} SELECT structure_id, cell, n FROM histogram")
def m15_orders(spark, d):
    """Numbered atoms: the sums of a structure then run in the order of SQL's, which flat orders are sensitive to."""
    return encode.encode_structures(_atoms(spark, d, "order"))


@query("m15_encode_d1_suppliers", f"WITH {sql.d1('supplier')} SELECT structure_id, cell, n FROM histogram")
def m15_suppliers(spark, d):
    return encode.encode_structures(_atoms(spark, d, "supplier", ids=False))


@query("m15_encode_d1_radius_30", f"WITH {sql.d1(radius=30.0)} SELECT structure_id, cell, n FROM histogram")
def m15_radius(spark, d):
    return encode.encode_structures(_atoms(spark, d, ids=False), EncodeConfig(radius=30.0))


@query("m15_encode_d2", f"WITH {sql.atoms()}, {_BONDS}, {sql.POSE}, described AS (SELECT s.*, CAST(s.z + coalesce(b, 0) AS DOUBLE) AS descriptor FROM spherical s LEFT JOIN bonds USING (structure_id, atom_id)), {sql.cells('descriptor', '0e0', '16e0', source='described')}, {sql.HISTOGRAM} SELECT structure_id, cell, n FROM histogram")
def m15_d2(spark, d):
    return encode.encode_structures(_atoms(spark, d), ex.CONFIGS["D2"])


_LO, _HI = "(SELECT min(descriptor) FROM described)", "(SELECT max(descriptor) FROM described)"


@query("m15_encode_d3", f"WITH {sql.atoms()}, {_COULOMB}, {sql.POSE}, described AS (SELECT s.*, coalesce(c, 0) AS descriptor FROM spherical s LEFT JOIN charge USING (structure_id, atom_id) WHERE r <= 60), {sql.cells('descriptor', _LO, _HI, source='described')}, {sql.HISTOGRAM} SELECT structure_id, cell, n FROM histogram")
def m15_d3(spark, d):
    return encode.encode_structures(_atoms(spark, d), ex.CONFIGS["D3"])


# ---- indexing -----------------------------------------------------------------------------------

_TF = "tf AS (SELECT structure_id, cell, n / sum(n) OVER (PARTITION BY structure_id) AS tf FROM histogram)"
_IDF = "idf AS (SELECT cell, count(*) AS df, ln((SELECT count(DISTINCT structure_id) FROM histogram) / count(*)) AS idf FROM histogram GROUP BY cell)"


@query("m16_term_frequency", f"WITH {_D1}, {_TF} SELECT structure_id, cell, round(tf, 9) AS tf FROM tf")
def m16(spark, d):
    return _rounded(lsi.term_frequency(encode.encode_structures(_atoms(spark, d, ids=False))), 9, "tf").select("structure_id", "cell", "tf")


@query("m17_idf", f"WITH {_D1}, {_IDF} SELECT cell, df, round(idf, 9) AS idf FROM idf")
def m17(spark, d):
    t = written(encode.encode_structures(_atoms(spark, d, ids=False)), "idf")
    return _rounded(lsi.idf(lsi.doc_frequency(t), t.select("structure_id").distinct().count()), 9, "idf")


@query("m18_tfidf", f"WITH {_D1}, {_TF}, {_IDF} SELECT structure_id, cell, round(tf * idf, 9) AS weight FROM tf JOIN idf USING (cell) WHERE idf > 0")
def m18(spark, d):
    return _rounded(lsi.tfidf(written(encode.encode_structures(_atoms(spark, d, ids=False)), "tfidf")), 9, "weight")


def _supplier_cells(spark, d, bits: int = 3):
    return written(encode.encode_structures(_atoms(spark, d, "supplier", ids=False), EncodeConfig(bits=bits)), "supplier-cells")


_SUPPLIERS = sql.d1("supplier", 3)
_ENERGIES = sql.energies(_SUPPLIERS, 5)


def _energies(spark, sigma) -> DataFrame:
    return _steady(spark.createDataFrame([(i + 1, float(np.log(s * s))) for i, s in enumerate(sigma)], "dim int, log_energy double"), 3, "log_energy")


def _svd(backend: str) -> None:
    @query(f"m19_svd_{backend}", f"{_ENERGIES} SELECT dim, {_s(3, 'log_energy', expr={'log_energy': 'ln(lam)'})} FROM energy")
    def run(spark, d):
        """Logarithms of the squared singular values; SQL finds them by power iteration on the Gram matrix."""
        return _energies(spark, lsi.fit_lsi(_supplier_cells(spark, d), 5, backend, tolerance=1e-9, passes=200).sigma)


for _b in ("gram", "subspace", "mllib"):
    _svd(_b)


@query("m19_svd_backends_agree", f"{_ENERGIES} SELECT backend, {_s(3, 'log_energy', expr={'log_energy': 'ln(e)'})} FROM (SELECT unnest(['gram', 'subspace', 'mllib']) AS backend, sum(lam) AS e FROM energy UNION ALL SELECT 'all', sum(weight * weight) FROM w)")
def m19_agree(spark, d):
    """Energy of the first five dimensions by backend, and of all dimensions, which is the matrix's."""
    t = _supplier_cells(spark, d)
    n = t.select("structure_id").distinct().count()
    found = {b: lsi.fit_lsi(t, 5, b, tolerance=1e-9, passes=200).sigma for b in ("gram", "subspace", "mllib")} | {"all": lsi.fit_lsi(t, n, "gram").sigma}
    rows = [(b, float(np.log((s**2).sum()))) for b, s in found.items()]
    return _steady(spark.createDataFrame(rows, "backend string, log_energy double"), 3, "log_energy")


@query("m20_reduce", f"{_ENERGIES} SELECT dim, (SELECT count(DISTINCT l_suppkey) FROM lineitem) AS structures, {_s(3, 'log_energy', expr={'log_energy': 'ln(lam)'})} FROM energy")
def m20(spark, d):
    """Squares of each reduced dimension, added over the structures: the energies."""
    t = _supplier_cells(spark, d)
    r = lsi.reduce_structures(t, lsi.fit_lsi(t, 5, "gram"), 5, t)
    each = r.select("structure_id", F.posexplode("vec").alias("i", "v")).groupBy((F.col("i") + 1).alias("dim")).agg(F.count("*").alias("structures"), F.log(F.sum(F.col("v") * F.col("v"))).alias("log_energy"))
    return _steady(each, 3, "log_energy")


_FOLD_IN = f"""{_SUPPLIERS}, known AS (SELECT * FROM histogram WHERE structure_id % 5 <> 0), new AS (SELECT *, n / sum(n) OVER (PARTITION BY structure_id) AS tf FROM histogram WHERE structure_id % 5 = 0),
idf AS (SELECT cell, ln((SELECT count(DISTINCT structure_id) FROM known) / count(*)) AS idf FROM known GROUP BY cell),
one AS (SELECT cell, tf * idf AS weight FROM (SELECT *, n / sum(n) OVER (PARTITION BY structure_id) AS tf FROM known) JOIN idf USING (cell) WHERE structure_id = (SELECT min(structure_id) FROM known)),
met AS (SELECT structure_id, sum(tf * idf * weight) AS product FROM new JOIN idf USING (cell) JOIN one USING (cell) GROUP BY 1),
lost AS (SELECT structure_id, sum(n) AS unseen FROM new WHERE cell NOT IN (SELECT cell FROM idf WHERE idf > 0) GROUP BY 1)
SELECT s.structure_id, {_s(3, 'product', expr={'product': '1e6 * coalesce(product, 0)'})}, CAST(coalesce(unseen, 0) AS BIGINT) AS unseen FROM (SELECT DISTINCT structure_id FROM new) s LEFT JOIN met USING (structure_id) LEFT JOIN lost USING (structure_id)"""


def _products(vectors: DataFrame, others: DataFrame) -> DataFrame:
    """Inner products of all vectors with that of the first of ``others``, in millionths."""
    first = others.orderBy("structure_id").limit(1).select(F.col("vec").alias("other"))
    product = F.aggregate(F.zip_with("vec", "other", lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    return _steady(vectors.join(F.broadcast(first)).select("structure_id", (product * 1e6).alias("product")), 3, "product")


@query("m20a_fold_in", f"WITH {_FOLD_IN}")
def m20a(spark, d):
    """Structures the fit has not seen, folded in: with all dimensions kept, their inner products with a fitted
    structure are those of the weights themselves, which SQL can state."""
    t = _supplier_cells(spark, d)
    train, test = t.where("structure_id % 5 <> 0"), t.where("structure_id % 5 = 0")
    model = lsi.fit_lsi(train, train.select("structure_id").distinct().count(), "gram")
    products = _products(lsi.reduce_structures(test, model, structures=test), lsi.reduce_structures(train, model))
    return products.join(lsi.unseen_cells(test, model), "structure_id", "left").select("structure_id", "product", F.coalesce("unseen", F.lit(0)).alias("unseen"))


@query("m20b_unscaled", f"WITH {sql.weighted(_SUPPLIERS)} SELECT j AS structure_id, {_s(3, 'product', expr={'product': '1e6 * g'})} FROM gram WHERE i = (SELECT min(i) FROM gram)")
def m20b(spark, d):
    """V^T alone, scaled by the squared values: with all dimensions kept, the inner products of the weights."""
    t = _supplier_cells(spark, d)
    model = lsi.fit_lsi(t, t.select("structure_id").distinct().count(), "gram")
    r = lsi.reduce_structures(t, model, structures=t, scale="vt")
    squares = F.lit([float(s * s) for s in model.sigma]).cast("array<double>")
    return _products(r, r.withColumn("vec", F.zip_with("vec", squares, lambda v, e: v * e)))


#: The matrix of events and their pairs of type and hour has one 1 a row: its squared singular values are the pairs' counts.
_CURVE_SQL = "s AS (SELECT row_number() OVER (ORDER BY n DESC) AS dim, sqrt(n) AS sigma FROM (SELECT count(*) AS n FROM events GROUP BY event_type, extract('hour' FROM ts)))"
_GRADIENT_SQL = "g AS (SELECT dim, sigma, CASE WHEN lag(sigma) OVER w IS NULL THEN lead(sigma) OVER w - sigma WHEN lead(sigma) OVER w IS NULL THEN sigma - lag(sigma) OVER w ELSE (lead(sigma) OVER w - lag(sigma) OVER w) / 2 END AS gradient FROM s WINDOW w AS (ORDER BY dim))"


def event_curve(spark, d) -> DataFrame:
    """``dim, sigma``: singular values of events by type and hour, descending; 120 rows at most."""
    n = load(spark, d, "events").groupBy("event_type", F.hour("ts")).agg(F.count("*").alias("n"))
    return n.select(F.row_number().over(Window.orderBy(F.desc("n"))).cast("bigint").alias("dim"), F.sqrt("n").alias("sigma"))


@query("m21_choose_k", f"WITH {_CURVE_SQL}, {_GRADIENT_SQL} SELECT greatest(coalesce(min(dim) FILTER (gradient >= -0.1e0) - 1, count(*)), 1) AS k FROM g")
def m21(spark, d):
    sigma = np.array([r.sigma for r in event_curve(spark, d).orderBy("dim").collect()])
    return spark.createDataFrame([(lsi.choose_k(sigma, threshold=-0.1),)], "k bigint")


@query("m21a_choose_k_cv")
def m21a(spark, d):
    curve = ex.k_curve(spark, d, ks=(2, 5, 10))
    return curve.orderBy("mean", "k").limit(1).select("k", "mean")


# ---- learning -----------------------------------------------------------------------------------

_W1, _B1, _W2, _B2 = [[0.5, -0.25], [0.1, 0.3], [-0.2, 0.05]], [0.1, -0.1], [[1.0, -2.0], [0.5, 0.25]], [0.0, 1.0]


@query("m23_mlp_forward", f"""WITH {sql.atoms()}, h AS (SELECT structure_id, atom_id, 1 / (1 + exp(-(0.5e0 * x / 25 + 0.1e0 * y / 25 - 0.2e0 * w / 25 + 0.1e0))) AS a, 1 / (1 + exp(-(-0.25e0 * x / 25 + 0.3e0 * y / 25 + 0.05e0 * w / 25 - 0.1e0))) AS b FROM atoms)
SELECT structure_id, atom_id, round(a + 0.5e0 * b, 6) AS p0, round(-2e0 * a + 0.25e0 * b + 1, 6) AS p1 FROM h""")
def m23(spark, d):
    model = learn.Mlp([(np.array(_W1), np.array(_B1)), (np.array(_W2), np.array(_B2))])
    rows = _atoms(spark, d).select("structure_id", "atom_id", F.array(*(F.col(c) / 25 for c in ("x", "y", "w"))).alias("vec"))
    return learn.mlp_predict(rows, model).select("structure_id", "atom_id", *(F.round(F.get("pred", F.lit(i)), 6).alias(f"p{i}") for i in range(2)))


def _small_table(spark, d):
    """Parts with three simple numbers as vectors: cheap input for the training variants."""
    a = _atoms(spark, d, ids=False).groupBy("structure_id").agg(F.array(F.sum("z").cast("double"), F.count("*").cast("double"), F.sum(F.col("z") * F.col("z")).cast("double")).alias("vec"))
    return written(ex.targets_of(spark, d).join(a, "structure_id"), "small-table")


def _errors(p: DataFrame) -> DataFrame:
    return metrics.fold_summary(metrics.fraction_error(p.where("split = 'test'"), ["target", "fold"]), ["target"])


def _training(name: str, **options) -> None:
    config = learn.MlpConfig(hidden=(16,), rate=0.01, batch=options.pop("batch", 64), epochs=options.pop("epochs", 30), optimiser=options.pop("optimiser", "adam"))
    targets = options.pop("targets", ENERGIES)

    @query(name)
    def run(spark, d):
        return _errors(learn.cross_predict(_small_table(spark, d), targets, config, **options))


_training("m24_mlp_multi_task")
_training("m24a_mlp_single_task", joint=False)
_training("m24b_mlp_full_batch", batch=None, epochs=150)
_training("m24_mlp_plain_descent", optimiser="plain", epochs=60)


@query("m24_mlp_distributed", f"WITH {sql.FOLDED} SELECT round(avg(abs((mu - t_point) / t_point)), 6) AS mean_error, TRUE AS beats_mean FROM folded, (SELECT avg(t_point) AS mu FROM folded)")
def m24_distributed(spark, d):
    t = _small_table(spark, d)
    model = learn.train_distributed(t, ["point"], learn.MlpConfig(hidden=(8,), rate=0.05, epochs=25))
    p = learn.mlp_predict(t, model).withColumn("e", F.abs((F.get("pred", F.lit(0)) - F.col("point")) / F.col("point")))
    mean = t.agg(F.avg("point")).first()[0]
    r = p.agg(F.avg("e").alias("mlp"), F.avg(F.abs((F.lit(mean) - F.col("point")) / F.col("point"))).alias("base"))
    return r.select(F.round("base", 6).alias("mean_error"), (F.col("mlp") < F.col("base")).alias("beats_mean"))


@query("m25_scaler", f"WITH {sql.FOLDED} SELECT structure_id, round((t_point - avg(t_point) OVER ()) / stddev_samp(t_point) OVER (), 6) + 0e0 AS point FROM folded")
def m25(spark, d):
    t = ex.targets_of(spark, d)
    return _rounded(learn.fit_scaler(t, ["point"]).apply(t), 6, "point").select("structure_id", "point")


@query("m25_scaler_minmax", f"WITH {sql.FOLDED} SELECT structure_id, round((t_point - min(t_point) OVER ()) / (max(t_point) OVER () - min(t_point) OVER ()), 6) + 0e0 AS point FROM folded")
def m25b(spark, d):
    t = ex.targets_of(spark, d)
    return _rounded(learn.fit_scaler(t, ["point"], "minmax").apply(t), 6, "point").select("structure_id", "point")


@query("m26_smbo_search")
def m26(spark, d):
    return ex.search(spark, d, n_trials=9)


@query("m26_random_search")
def m26r(spark, d):
    return ex.search(spark, d, n_trials=9, method="random")


@query("m26a_priors", "SELECT 20 * count(*) AS draws, TRUE AS in_range, TRUE AS log_median, TRUE AS quantised FROM supplier")
def m26a(spark, d):
    """Twenty draws of every prior for each supplier, from a generator that its key seeds."""
    s = learn.Space({"u": ("uniform", 0, 2), "l": ("loguniform", 1e-4, 1.0), "q": ("quniform", 0, 100, 5), "c": ("choice", ["a", "b"])})

    def drawn(batches):
        import pyarrow as pa

        for batch in batches:
            rows = [s.sample(rng) for key in batch.column(0).to_pylist() for rng in [np.random.default_rng(key)] for _ in range(20)]
            yield pa.RecordBatch.from_pylist(rows, pa.schema([("u", pa.float64()), ("l", pa.float64()), ("q", pa.int64()), ("c", pa.string())]))

    draws = load(spark, d, "supplier").select("s_suppkey").mapInArrow(drawn, "u double, l double, q bigint, c string")
    inside = F.col("u").between(0, 2) & F.col("l").between(1e-4, 1) & F.col("q").between(0, 100) & F.col("c").isin("a", "b")
    return draws.agg(F.count("*").alias("draws"), F.bool_and(inside).alias("in_range"), F.percentile("l", F.lit(0.5)).between(0.005, 0.02).alias("log_median"), F.bool_and(F.pmod("q", F.lit(5)) == 0).alias("quantised"))


@query("m27_kfold", f"SELECT p_partkey AS structure_id, {sql.FOLD.format(k=10).replace('structure_id', 'p_partkey')} AS fold FROM part")
def m27(spark, d):
    return learn.kfold(load(spark, d, "part").select(F.col("p_partkey").alias("structure_id")))


@query("m27_holdout", "SELECT p_partkey AS structure_id, CASE WHEN ((p_partkey % 2147483648) * 1103515245 + 12345) % 2147483648 // 65536 < 26214 THEN 'train' ELSE 'test' END AS split FROM part")
def m27h(spark, d):
    return learn.holdout(load(spark, d, "part").select(F.col("p_partkey").alias("structure_id")))


@query("m27_repeated_holdout", "SELECT fold, split, count(*) AS n FROM (SELECT CAST(f AS INT) AS fold, CASE WHEN ((p_partkey % 2147483648) * 1103515245 + 12345 + f * 518979584) % 2147483648 // 65536 < 26214 THEN 'train' ELSE 'test' END AS split FROM part, range(10) t(f)) GROUP BY ALL")
def m27r(spark, d):
    return learn.repeated_holdout(load(spark, d, "part").select(F.col("p_partkey").alias("structure_id"))).groupBy("fold", "split").agg(F.count("*").alias("n"))


@query("m28_funnel", f"WITH {sql.FOLDED}, a AS (SELECT * FROM folded ORDER BY t_lattice, structure_id LIMIT (SELECT CAST(ceil(count(*) * 0.3) AS BIGINT) FROM folded)), b AS (SELECT * FROM a ORDER BY t_point, structure_id LIMIT (SELECT CAST(ceil(count(*) * 0.5) AS BIGINT) FROM a)) SELECT structure_id FROM b")
def m28(spark, d):
    return metrics.funnel(written(ex.targets_of(spark, d), "funnel"), [("lattice", 30), ("point", 50)]).select("structure_id")


# ---- curves and other representations -----------------------------------------------------------

_H = sql.chain("g", ["h0", "h1", "h2", "h3"], curves.hilbert_steps(4, 4), "hil")


@query("k1_hilbert", f"WITH g AS (SELECT a AS h0, b AS h1, c AS h2, e AS h3 FROM ({_GRID_LINE})), {_H} SELECT {sql.interleaved(['h0', 'h1', 'h2', 'h3'], 4)} AS code, count(*) AS n FROM hil GROUP BY 1")
def k1(spark, d):
    return curves.hilbert_encode(_grid_line(spark, d), _FOUR, 4, "code").groupBy("code").agg(F.count("*").alias("n"))


@query("k1_hilbert_decode", f"SELECT a, b, c, e, count(*) AS n FROM ({_GRID_LINE}) GROUP BY ALL")
def k1d(spark, d):
    coded = curves.hilbert_encode(_grid_line(spark, d), _FOUR, 4, "code").select("code")
    return curves.hilbert_decode(coded, "code", 4, 4, _FOUR).groupBy(*_FOUR).agg(F.count("*").alias("n"))


def _peano_sql() -> str:
    dig = lambda c, k: f"(({c} // {3**k}) % 3)"
    code = "0"
    for k in (2, 1, 0):
        for i, c in enumerate(("a", "b")):
            o = "b" if c == "a" else "a"
            before = [dig(o, j) for j in range(k + 1, 3)] + ([dig("a", k)] if i else [])
            odd = f"(({' + '.join(before) or '0'}) % 2 = 1)"
            code = f"({code}) * 3 + CASE WHEN {odd} THEN 2 - {dig(c, k)} ELSE {dig(c, k)} END"
    return code


@query("k2_peano", f"WITH g AS ({_GRID_LINE}) SELECT CAST({_peano_sql()} AS BIGINT) AS code, count(*) AS n FROM g GROUP BY 1")
def k2(spark, d):
    return _grid_line(spark, d).groupBy(curves.peano_encode(["a", "b"], 3).alias("code")).agg(F.count("*").alias("n"))


@query("k3_rowmajor", f"WITH g AS ({_GRID_LINE}) SELECT a * 4096 + b * 256 + c * 16 + e AS code, count(*) AS n FROM g GROUP BY 1")
def k3(spark, d):
    return _grid_line(spark, d).groupBy(curves.rowmajor_encode(_FOUR, 4).alias("code")).agg(F.count("*").alias("n"))


@query("k4_rdf", f"WITH {sql.atoms()}, {sql.PAIRS} SELECT structure_id, CAST(floor(round(d / 1e0, 9)) AS BIGINT) AS bin, count(*) AS n FROM pairs WHERE d < 30 AND atom_id < atom_id2 GROUP BY 1, 2")
def k4(spark, d):
    return features.rdf(_atoms(spark, d))


@query("k5_coulomb_matrix", f"WITH {sql.atoms()}, {sql.PAIRS}, o AS (SELECT structure_id, atom_id, sum(power(z * z2 / d, 2)) AS s FROM pairs GROUP BY 1, 2), v AS (SELECT structure_id, sqrt(coalesce(s, 0) + power(0.5e0 * power(CAST(z AS DOUBLE), 2.4e0), 2)) AS norm FROM atoms LEFT JOIN o USING (structure_id, atom_id)) SELECT structure_id, round(max(norm), 6) AS top, round(sum(norm), 5) AS total FROM v GROUP BY structure_id")
def k5(spark, d):
    m = features.coulomb_matrix(_atoms(spark, d), 60)
    return m.select("structure_id", F.round(F.get("norms", F.lit(0)), 6).alias("top"), F.round(F.aggregate("norms", F.lit(0.0), lambda s, v: s + v), 5).alias("total"))


@query("k5_coulomb_eigenvalues", f"""WITH {sql.atoms()}, {sql.PAIRS}, off AS (SELECT structure_id, sum(power(z * z2 / d, 2)) AS o FROM pairs GROUP BY 1),
own AS (SELECT structure_id, sum(0.5e0 * power(CAST(z AS DOUBLE), 2.4e0)) AS t, sum(power(0.5e0 * power(CAST(z AS DOUBLE), 2.4e0), 2)) AS q FROM atoms GROUP BY 1)
SELECT structure_id, {_s(4, 'trace', 'squares', expr={'trace': 't', 'squares': 'q + coalesce(o, 0)'})} FROM own LEFT JOIN off USING (structure_id)""")
def k5e(spark, d):
    """The eigenvalues' sum and sum of squares: the matrix's trace and the sum of its squared entries."""
    e = features.coulomb_eigenvalues(_atoms(spark, d), 60)
    total = lambda f: F.aggregate("eigenvalues", F.lit(0.0), lambda s, v: s + f(v))
    return _steady(e.select("structure_id", total(lambda v: v).alias("trace"), total(lambda v: v * v).alias("squares")), 4, "trace", "squares")


@query("k6_flat_coordinates", f"WITH {sql.atoms()} SELECT structure_id, 249 AS width, round(150e0 + sum(z + x + y + w), 5) AS total FROM atoms GROUP BY structure_id")
def k6(spark, d):
    a = _atoms(spark, d)
    f = features.flat_coordinates(a, lattice_of(a), 60)
    return f.select("structure_id", F.size("flat").alias("width"), F.round(F.aggregate("flat", F.lit(0.0), lambda s, v: s + v), 5).alias("total"))


_COMPOSITION = ", ".join(f"count(*) FILTER (z = {i}) AS z{i}" for i in range(1, 8)) + ", " + ", ".join(f"count(*) FILTER (coalesce(b, 0) = {i}) AS deg{i}" for i in range(3)) + ", count(*) FILTER (b >= 3) AS deg3"


@query("k7_composition", f"WITH {sql.atoms()}, {_BONDS} SELECT structure_id, {_COMPOSITION} FROM atoms LEFT JOIN bonds USING (structure_id, atom_id) GROUP BY structure_id")
def k7(spark, d):
    return features.composition(_atoms(spark, d))


# ---- baselines ----------------------------------------------------------------------------------

_P = sql.PREDICTED


def _mean_errors(spark, d):
    return written(metrics.mean_predictions(ex.targets_of(spark, d), ENERGIES), "mean-predictions")


@query("b1_mean_predictor", f"WITH {_P} SELECT fold, target, round(pred, 5) AS pred FROM mean")
def b1(spark, d):
    return _rounded(metrics.mean_predictor(ex.targets_of(spark, d), ENERGIES), 5, "pred")


@query("b1_mean_predictor_errors", f"WITH {_P}, e AS (SELECT target, fold, avg(abs((pred - calc) / calc)) AS error FROM predicted GROUP BY 1, 2) SELECT target, round(avg(error), 6) AS mean, round(stddev_samp(error), 6) AS std, count(*) AS folds FROM e GROUP BY target")
def b1e(spark, d):
    return _rounded(metrics.fold_summary(metrics.fraction_error(_mean_errors(spark, d), ["target", "fold"]), ["target"]), 6, "mean", "std")


_RECALL = "ranked AS (SELECT *, row_number() OVER (PARTITION BY {by} ORDER BY {p}, structure_id) AS p, row_number() OVER (PARTITION BY {by} ORDER BY {t}, structure_id) AS t, ceil(count(*) OVER (PARTITION BY {by}) * 0.15e0 - 1e-9) AS k FROM {src}), recalls AS (SELECT {by}, count(*) FILTER (p <= k AND t <= k) / max(k) AS recall, CAST(max(k) AS BIGINT) AS top FROM ranked GROUP BY {by})"


@query("b2_lattice_ranking", f"WITH {sql.FOLDED}, {_RECALL.format(by='fold', p='t_lattice', t='t_point', src='folded')} SELECT fold, round(recall, 9) AS recall, top FROM recalls")
def b2(spark, d):
    return _rounded(metrics.proxy_ranking(ex.targets_of(spark, d), "lattice", "point", 15, ["fold"]), 9, "recall")


@query("b2_lattice_ranking_all", f"WITH {sql.FOLDED}, one AS (SELECT *, 1 AS g FROM folded), {_RECALL.format(by='g', p='t_lattice', t='t_point', src='one')} SELECT round(recall, 9) AS recall, top FROM recalls")
def b2a(spark, d):
    return _rounded(metrics.proxy_ranking(ex.targets_of(spark, d), "lattice", "point"), 9, "recall")


@query("b3_representations")
def b3(spark, d):
    return ex.error_table(spark, d, learner="ridge")


@query("b4_raw_histogram")
def b4(spark, d):
    """Linear regression on raw bins (sparse vectors) against the reduced ones: test fold 0 of the point energy."""
    from pyspark.ml.linalg import SparseVector, VectorUDT
    from pyspark.ml.regression import LinearRegression

    t = written(ex.targets_of(spark, d).select("structure_id", "fold", "point"), "raw-targets")
    triplets = written(ex.triplets_of(spark, d), "raw-cells")
    cells = encode.to_sparse(triplets)
    build = F.udf(lambda c, n: SparseVector(65536, c, n), VectorUDT())
    rows = written(t.join(cells, "structure_id").select("structure_id", "fold", "point", "cells", "counts"), "raw").withColumn("features", build("cells", "counts"))
    fit = LinearRegression(labelCol="point", regParam=0.1, maxIter=20, solver="l-bfgs").fit(rows.where("fold <> 0"))
    p = fit.transform(rows.where("fold = 0")).select(F.lit("raw").alias("features"), F.col("point").alias("calc"), F.col("prediction").alias("pred"))
    reduced, _ = ex.reduced_of(triplets, 7)
    q = learn.cross_predict(written(t.join(reduced, "structure_id"), "raw-reduced"), ["point"], learner="ridge", splits=("test",)).where("fold = 0").select(F.lit("reduced").alias("features"), "calc", "pred")
    return metrics.fraction_error(p.unionByName(q), ["features"])


@query("b5_direct_energies", f"WITH {sql.FOLDED} SELECT structure_id, round(t_point, 5) AS point, round(t_ffsum, 5) AS ffsum, round(t_lattice, 6) AS lattice, round(t_dispersion, 4) AS dispersion FROM folded")
def b5(spark, d):
    t = ex.targets_of(spark, d)
    return _rounded(_rounded(_rounded(t, 5, "point", "ffsum"), 6, "lattice"), 4, "dispersion").select("structure_id", *ENERGIES)


_DRAW = "((p_partkey % 2147483648) * 1103515245 + 12345) % 2147483648 // 65536"


@query("b6_random_recall", f"WITH src AS (SELECT p_partkey AS structure_id, p_brand AS brand, p_retailprice AS price, {_DRAW} AS draw FROM part), {_RECALL.format(by='brand', p='draw', t='price', src='src')} SELECT brand, round(recall, 9) AS recall, top, 0.15e0 AS expected FROM recalls")
def b6(spark, d):
    """Recall of an order by chance, by brand, beside the share that chance is expected to find."""
    parts = load(spark, d, "part").select(F.col("p_partkey").alias("structure_id"), F.col("p_brand").alias("brand"), F.col("p_retailprice").alias("price"), learn.draw("p_partkey").alias("draw"))
    return _rounded(metrics.recall_at(parts, 15, ["brand"], "draw", "price"), 9, "recall").withColumn("expected", F.lit(metrics.random_recall(15)))


# ---- measures -----------------------------------------------------------------------------------


@query("c1_fraction_error", f"WITH {_P} SELECT target, fold, round(avg(abs((pred - calc) / nullif(calc, 0))), 6) AS error, count(*) FILTER (calc = 0) AS undefined, count(*) AS n FROM predicted GROUP BY target, fold")
def c1(spark, d):
    return _rounded(metrics.fraction_error(_mean_errors(spark, d), ["target", "fold"]), 6, "error")


@query("c1_fraction_error_controls", f"WITH c AS (SELECT p_partkey AS structure_id, {sql.FOLD.format(k=10).replace('structure_id', 'p_partkey')} AS fold, p_retailprice AS calc FROM part), m AS (SELECT fold, (sum(sum(calc)) OVER () - sum(calc)) / (sum(count(*)) OVER () - count(*)) AS pred FROM c GROUP BY fold) SELECT fold, round(avg(abs((pred - calc) / calc)), 6) AS error FROM c JOIN m USING (fold) GROUP BY fold")
def c1c(spark, d):
    parts = learn.kfold(load(spark, d, "part").select(F.col("p_partkey").alias("structure_id"), F.col("p_retailprice").alias("price")))
    return _rounded(metrics.fraction_error(metrics.mean_predictions(parts, ["price"]), ["fold"]), 6, "error").select("fold", "error")


@query("c2_fold_summary", f"WITH {_P}, e AS (SELECT target, fold, avg(abs((pred - calc) / calc)) AS error FROM predicted GROUP BY 1, 2) SELECT target, round(avg(error), 6) AS mean, round(stddev_samp(error), 6) AS std, count(*) AS folds FROM e GROUP BY target")
def c2(spark, d):
    return b1e(spark, d)


def _ridge_sql() -> str:
    """Ridge of three numbers of a part by fold, from normal equations solved by cofactors; errors by split, target and fold."""
    f = ("f1", "f2", "f3")
    pairs = [(a, b) for i, a in enumerate(f) for b in f[i:]]
    scaled = ", ".join(f"(x.{a} - m.{a}) / s.{a} AS {a}" for a in f)
    sums = ", ".join(f"sum({a} * {b}) + {1 if a == b else 0} AS {a}{b}" for a, b in pairs)
    g = lambda a, b: f"{a}{b}" if a <= b else f"{b}{a}"

    def cofactor(i: int, j: int) -> str:
        r, c = [k for k in range(3) if k != i], [k for k in range(3) if k != j]
        minor = f"({g(f[r[0]], f[c[0]])} * {g(f[r[1]], f[c[1]])} - {g(f[r[0]], f[c[1]])} * {g(f[r[1]], f[c[0]])})"
        return minor if (i + j) % 2 == 0 else f"(-{minor})"

    det = " + ".join(f"{g(f[0], f[j])} * {cofactor(0, j)}" for j in range(3))
    beta = ", ".join("(" + " + ".join(f"{cofactor(i, j)} * y{j + 1}" for j in range(3)) + f") / ({det}) AS b{i + 1}" for i in range(3))
    return f"""{sql.FOLDED}, {sql.LONG},
x AS (SELECT structure_id, CAST(sum(z) AS DOUBLE) AS f1, CAST(count(*) AS DOUBLE) AS f2, CAST(sum(z * z) AS DOUBLE) AS f3 FROM atoms GROUP BY structure_id),
model AS (SELECT unnest(range(10)) AS model), part AS (SELECT model, structure_id, fold, x.* EXCLUDE (structure_id) FROM x JOIN folded USING (structure_id), model),
m AS (SELECT model, avg(f1) AS f1, avg(f2) AS f2, avg(f3) AS f3 FROM part WHERE fold <> model GROUP BY model),
s AS (SELECT model, stddev_samp(f1) AS f1, stddev_samp(f2) AS f2, stddev_samp(f3) AS f3 FROM part WHERE fold <> model GROUP BY model),
z AS MATERIALIZED (SELECT x.model, x.structure_id, x.fold, {scaled} FROM part x JOIN m USING (model) JOIN s USING (model)),
left_side AS (SELECT model, {sums} FROM z WHERE fold <> model GROUP BY model),
right_side AS (SELECT z.model, target, avg(calc) AS b0, sum(f1 * calc) AS y1, sum(f2 * calc) AS y2, sum(f3 * calc) AS y3 FROM z JOIN long USING (structure_id, fold) WHERE fold <> model GROUP BY z.model, target),
beta AS MATERIALIZED (SELECT model, target, b0, {beta} FROM left_side JOIN right_side USING (model)),
predicted AS (SELECT z.model AS fold, CASE WHEN z.fold = z.model THEN 'test' ELSE 'train' END AS split, target, calc, b0 + b1 * f1 + b2 * f2 + b3 * f3 AS pred FROM z JOIN long USING (structure_id, fold) JOIN beta USING (model, target))"""


_RIDGE = _ridge_sql()


def _linear_predictions(spark, d):
    return written(learn.cross_predict(_small_table(spark, d), ENERGIES, learner="ridge"), "linear")


@query("c3_train_and_test_errors", f"WITH {_RIDGE} SELECT split, target, {_s(5, 'error', expr={'error': 'avg(abs((pred - calc) / nullif(calc, 0)))'})}, count(*) FILTER (calc = 0) AS undefined, count(*) AS n FROM predicted GROUP BY split, target")
def c3(spark, d):
    return _steady(metrics.fraction_error(_linear_predictions(spark, d), ["split", "target"]), 5, "error")


@query("c4_recall", f"WITH {sql.FOLDED}, {_RECALL.format(by='fold', p='t_dispersion', t='t_ffsum DESC', src='folded').replace('t_dispersion, structure_id', 't_dispersion DESC, structure_id')} SELECT fold, round(recall, 9) AS recall, top FROM recalls")
def c4(spark, d):
    return _rounded(metrics.recall_at(ex.targets_of(spark, d), 15, ["fold"], "dispersion", "ffsum", "desc"), 9, "recall")


@query("c5_recall_summary", f"WITH {sql.FOLDED}, {_RECALL.format(by='fold', p='t_lattice', t='t_point', src='folded')} SELECT round(max(recall), 9) AS best, round(avg(recall), 9) AS mean, round(stddev_samp(recall), 9) AS std FROM recalls")
def c5(spark, d):
    return _rounded(metrics.recall_summary(metrics.proxy_ranking(ex.targets_of(spark, d), "lattice", "point", 15, ["fold"]), []), 9, "best", "mean", "std")


@query("c6_error_by_k")
def c6(spark, d):
    return ex.k_curve(spark, d, ks=(1, 5, 10))


@query("c7_spectrum", f"""{_ENERGIES}, v AS (SELECT dim, sqrt(lam) AS sigma FROM energy),
g AS (SELECT dim, sigma, CASE WHEN dim = 1 THEN lead(sigma) OVER w - sigma WHEN dim = 5 THEN sigma - lag(sigma) OVER w ELSE (lead(sigma) OVER w - lag(sigma) OVER w) / 2 END AS gradient FROM v WINDOW w AS (ORDER BY dim))
SELECT dim, {_s(3, 'sigma', 'gradient', expr={'sigma': 'sigma / max(sigma) OVER ()', 'gradient': 'gradient / max(sigma) OVER ()'})} FROM g""")
def c7(spark, d):
    """Singular values and their slope, as shares of the first value."""
    model = lsi.fit_lsi(_supplier_cells(spark, d), 5, "gram")
    shares = lsi.spectrum(model, spark).withColumns({c: F.col(c) / F.lit(float(model.sigma[0])) for c in ("sigma", "gradient")})
    return _steady(shares, 3, "sigma", "gradient")


@query("c8_paired_gain", f"WITH {_P}, b AS (SELECT target, fold, avg(abs((pred - calc) / calc)) AS error FROM predicted GROUP BY 1, 2), a AS (SELECT target, fold, avg(abs((pred * 1.01e0 - calc) / calc)) AS error FROM predicted GROUP BY 1, 2) SELECT target, round(avg(b.error - a.error), 6) + 0e0 AS gain, round(stddev_samp(b.error - a.error), 6) AS std, count(*) FILTER (b.error > a.error) AS better, count(*) AS folds FROM a JOIN b USING (target, fold) GROUP BY target")
def c8(spark, d):
    p = _mean_errors(spark, d)
    base = metrics.fraction_error(p, ["target", "fold"])
    other = metrics.fraction_error(p.withColumn("pred", F.col("pred") * 1.01), ["target", "fold"])
    return _rounded(metrics.paired_gain(other, base, ["target"]), 6, "gain", "std")


@query("c9_split_gap", f"""WITH {_RIDGE}, e AS (SELECT split, target, fold, avg(abs((pred - calc) / nullif(calc, 0))) AS error FROM predicted GROUP BY ALL),
t AS (SELECT target, avg(error) FILTER (split = 'train') AS train, avg(error) FILTER (split = 'test') AS test FROM e GROUP BY target)
SELECT target, {_s(5, 'train', 'test', 'gap', expr={'gap': 'test - train'})} FROM t""")
def c9(spark, d):
    errors = metrics.fraction_error(_linear_predictions(spark, d), ["split", "target", "fold"])
    return _steady(metrics.split_gap(errors, ["target"]), 5, "train", "test", "gap")


@query("c10_collision_rate", f"WITH {sql.d1('order')}, s AS (SELECT structure_id, string_agg(cell || ':' || n, ' ' ORDER BY cell) AS h FROM histogram GROUP BY 1), g AS (SELECT h, count(*) AS c FROM s GROUP BY h) SELECT CAST(sum(c) AS BIGINT) AS structures, count(*) AS histograms, round(sum(CASE WHEN c > 1 THEN c ELSE 0 END) / sum(c), 9) AS collision_rate FROM g")
def c10(spark, d):
    return _rounded(metrics.collision_rate(m15_orders(spark, d)), 9, "collision_rate")


def moved(atoms: DataFrame, seed: int = 0, shift: tuple[float, float, float] = (3.0, -2.0, 5.0)) -> DataFrame:
    """The atoms under one rigid motion: a random proper rotation and a shift."""
    q, r = np.linalg.qr(np.random.default_rng(seed).normal(size=(3, 3)))
    q = q * np.sign(np.diag(r))
    if np.linalg.det(q) < 0:
        q[:, 0] = -q[:, 0]
    turned = {a: sum((F.col(b) * F.lit(float(q[i, j])) for j, b in enumerate(geometry.AXES)), F.lit(float(shift[i]))) for i, a in enumerate(geometry.AXES)}
    return atoms.withColumns(turned)


@query("c11_invariance", f"WITH {_D1} SELECT structure_id, cell, n FROM histogram")
def c11(spark, d):
    """Histograms of the atoms after a rigid motion, against SQL's of the atoms as they are."""
    return encode.encode_structures(moved(_atoms(spark, d, ids=False)))


@query("c11_locality")
def c11l(spark, d):
    """Correlation of index gaps with distances, by curve, over neighbours in table order on the line grid."""
    g = _grid_line(spark, d).select(*_FOUR).distinct()
    coded = {"morton": g.withColumn("code", curves.morton_encode(_FOUR, 4)), "hilbert": written(curves.hilbert_encode(g, _FOUR, 4, "code"), "hilbert"), "rowmajor": g.withColumn("code", curves.rowmajor_encode(_FOUR, 4))}
    out = None
    for name, df in coded.items():
        a = df.select(F.expr("a * 16 + b").alias("block"), "c", "e", "code")
        b = a.select("block", *(F.col(k).alias(f"{k}2") for k in ("c", "e", "code")))
        pairs = a.join(b, "block").where("code < code2").select((F.col("code2") - F.col("code")).alias("index_gap"), F.expr("sqrt(power(c - c2, 2) + power(e - e2, 2))").alias("distance"))
        row = metrics.locality_report(pairs).withColumn("curve", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


@query("c12_scaling")
def c12(spark, d):
    return ex.scaling(spark, d, (3, 4, 6))


@query("c13_speedup")
def c13(spark, d):
    return ex.speed(spark, d)


_VALUES = f"{_P}, v AS (SELECT target, 'calc' AS kind, calc AS value FROM predicted UNION ALL SELECT target, 'pred', pred FROM predicted), b AS (SELECT target, kind, CAST(least(floor((value - min(value) OVER (PARTITION BY target)) / (max(value) OVER (PARTITION BY target) - min(value) OVER (PARTITION BY target)) * 20), 19) AS INT) AS bin FROM v)"


@query("c14_violin_bins", f"WITH {_VALUES} SELECT target, kind, bin, count(*) AS n, round(count(*) / sum(count(*)) OVER (PARTITION BY target, kind), 9) AS share FROM b GROUP BY target, kind, bin")
def c14(spark, d):
    p = _mean_errors(spark, d)
    v = p.select("target", F.lit("calc").alias("kind"), F.col("calc").alias("value")).union(p.select("target", F.lit("pred"), F.col("pred")))
    return _rounded(metrics.violin_bins(v), 9, "share")


@query("c14_distribution_overlap", f"WITH {_VALUES}, s AS (SELECT target, kind, bin, count(*) / sum(count(*)) OVER (PARTITION BY target, kind) AS share FROM b GROUP BY target, kind, bin), o AS (SELECT target, bin, least(coalesce(sum(share) FILTER (kind = 'calc'), 0), coalesce(sum(share) FILTER (kind = 'pred'), 0)) AS c FROM s GROUP BY target, bin) SELECT target, round(sum(c), 9) AS overlap FROM o GROUP BY target")
def c14o(spark, d):
    p = _mean_errors(spark, d)
    v = p.select("target", F.lit("calc").alias("kind"), F.col("calc").alias("value")).union(p.select("target", F.lit("pred"), F.col("pred")))
    return _rounded(metrics.distribution_overlap(metrics.violin_bins(v)), 9, "overlap")


@query("c15_sparsity", f"WITH {_D1}, p AS (SELECT structure_id, count(*) AS c FROM histogram GROUP BY 1) SELECT count(*) AS structures, CAST(sum(c) AS BIGINT) AS nonzeros, round(avg(c), 6) AS per_structure, round(1 - sum(c) / (count(*) * 65536e0), 9) AS zero_share FROM p")
def c15(spark, d):
    return _rounded(_rounded(metrics.sparsity(encode.encode_structures(_atoms(spark, d, ids=False)), 65536), 6, "per_structure"), 9, "zero_share")


@query("c16_regression_report", f"WITH {_P}, k AS (SELECT *, rank() OVER (PARTITION BY target ORDER BY pred) AS rp, rank() OVER (PARTITION BY target ORDER BY calc) AS rc, avg(calc) OVER (PARTITION BY target) AS mu FROM (SELECT target, round(calc, 6) AS calc, round(pred, 6) AS pred FROM predicted)) SELECT target, round(avg(abs(pred - calc)), 5) AS mae, round(sqrt(avg(power(pred - calc, 2))), 5) AS rmse, round(1 - sum(power(pred - calc, 2)) / sum(power(calc - mu, 2)), 6) + 0e0 AS r2, round(corr(rp, rc), 6) + 0e0 AS spearman FROM k GROUP BY target")
def c16(spark, d):
    return _rounded(_rounded(metrics.regression_report(_rounded(_mean_errors(spark, d), 6, "calc", "pred"), ["target"]), 5, "mae", "rmse"), 6, "r2", "spearman")


# ---- workloads ----------------------------------------------------------------------------------


@query("w1_curation", f"WITH {_FACTS} SELECT count(*) AS found, count(*) FILTER ({_ALL_RULES}) AS curated, count(*) FILTER ({_ALL_RULES} AND NOT charged) AS uncharged FROM checked")
def w1(spark, d):
    return m1_curation_audit(spark, d).select(F.col("all").alias("found"), F.col("rules").alias("curated"), F.col("kept").alias("uncharged"))


_ENCODED = {
    "D1": f"WITH {_D1}",
    "D2": f"WITH {sql.atoms()}, {_BONDS}, {sql.POSE}, described AS (SELECT s.*, CAST(s.z + coalesce(b, 0) AS DOUBLE) AS descriptor FROM spherical s LEFT JOIN bonds USING (structure_id, atom_id)), {sql.cells('descriptor', '0e0', '16e0', source='described')}, {sql.HISTOGRAM}",
    "D3": f"WITH {sql.atoms()}, {_COULOMB}, {sql.POSE}, described AS (SELECT s.*, coalesce(c, 0) AS descriptor FROM spherical s LEFT JOIN charge USING (structure_id, atom_id) WHERE r <= 60), {sql.cells('descriptor', _LO, _HI, source='described')}, {sql.HISTOGRAM}",
}


@query("w2_encode_summary", " UNION ALL ".join(f"SELECT * FROM ({q} SELECT '{rep}' AS rep, count(DISTINCT structure_id) AS structures, count(*) AS nonzeros, count(DISTINCT cell) AS cells, CAST(sum(n) AS BIGINT) AS atoms FROM histogram)" for rep, q in _ENCODED.items()))
def w2(spark, d):
    out = None
    for rep in ex.CONFIGS:
        t = ex.triplets_of(spark, d, rep)
        row = t.agg(F.countDistinct("structure_id").alias("structures"), F.count("*").alias("nonzeros"), F.countDistinct("cell").alias("cells"), F.sum("n").alias("atoms")).withColumn("rep", F.lit(rep))
        out = row if out is None else out.unionByName(row)
    return out


query("w3_k_curve")(lambda spark, d: ex.k_curve(spark, d))


@query("w4_singular_values")
def w4(spark, d):
    out = None
    for rep in ex.CONFIGS:
        model = lsi.fit_lsi(written(ex.triplets_of(spark, d, rep), "w4"), 40)
        s = lsi.spectrum(model, spark).withColumn("rep", F.lit(rep)).withColumn("k_slope", F.lit(lsi.choose_k(model.sigma))).withColumn("k_relative", F.lit(lsi.choose_k(model.sigma, relative=True)))
        out = s if out is None else out.unionByName(s)
    return out


query("w5_search")(lambda spark, d: ex.search(spark, d))
query("w6_error_table")(lambda spark, d: ex.error_table(spark, d))
query("w7_violin")(lambda spark, d: ex.violin(spark, d))
query("w8_recall_table")(lambda spark, d: ex.recall_table(spark, d))
query("w9_speed")(lambda spark, d: ex.speed(spark, d))
query("w10_scaling")(lambda spark, d: ex.scaling(spark, d))


@query("w11_vector_histograms", f"""WITH e AS (SELECT vec_id, unnest(range(16)) AS point, embedding FROM embeddings), p AS (SELECT vec_id, {', '.join(f'{sql.bin_of(f"CAST(embedding[point * 4 + {i + 1}] AS DOUBLE)", "-0.55e0", "0.55e0", 4)} AS q{i}' for i in range(4))} FROM e)
SELECT vec_id AS structure_id, {sql.interleaved(['q0', 'q1', 'q2', 'q3'], 4)} AS cell, count(*) AS n FROM p GROUP BY 1, 2""")
def w11(spark, d):
    grid = encode.GridSpec(tuple(encode.DimSpec(f"c{i}", -0.55, 0.55) for i in range(4)))
    q = encode.quantize(points_from_embeddings(spark, d), grid)
    return encode.histogram(q.select(F.col("vec_id").alias("structure_id"), curves.morton_encode(["q0", "q1", "q2", "q3"], 4).alias("cell")))


@query("w11_event_histograms", f"WITH {sql.EVENT_CELLS} SELECT structure_id, cell, count(*) AS n FROM event_cells GROUP BY 1, 2")
def w11e(spark, d):
    from ..streaming.streams import running_histogram

    return running_histogram(load(spark, d, "events"))


query("w12_document_quality")(lambda spark, d: ex.document_quality(spark, d))
query("w12_benchmark_fold_in")(lambda spark, d: ex.benchmark_fold_in(spark, d))


@query("w13_curve_ordered_box")
def w13(spark, d):
    """Rows of a box from a curve-ordered copy, with row groups that the scan had to read against all."""
    from ..operators.zorder import index_box_filter
    from ..sources.sinks import write_ordered

    grid = encode.GridSpec(tuple(encode.DimSpec(c, -25.0, 25.0, 6) for c in ("x", "y", "w")))
    a = encode.quantize(_atoms(spark, d, ids=False), grid)
    a = a.withColumn("cell", curves.morton_encode(["q0", "q1", "q2"], 6))
    copy = write_ordered(a, fresh_path(spark, "ordered"), "cell", 16)
    found = index_box_filter(copy, "cell", ["q0", "q1", "q2"], [8, 8, 8], [15, 15, 15], 6)
    named = lambda df: df.select(F.input_file_name().alias("file"))
    return named(found).agg(F.count("*").alias("found"), F.countDistinct("file").alias("files_read")).join(named(copy).agg(F.countDistinct("file").alias("files")))


@query("w14_funnel")
def w14(spark, d):
    """Lattice order first, then a learnt point energy, then the exact one: how much of the true top remains."""
    targets = written(ex.targets_of(spark, d), "funnel-targets")
    p = ex.predictions(spark, d, "D3", learner="ridge", targets=targets).where("split = 'test' AND target = 'point'").select("structure_id", "pred")
    t = written(targets.join(p, "structure_id"), "funnel-w14")
    kept = metrics.funnel(t, [("lattice", 60), ("pred", 50), ("point", 50)])
    top = t.orderBy("point", "structure_id").limit(max(1, int(t.count() * 0.15)))
    return kept.select("structure_id", "point").join(top.select("structure_id", F.lit(True).alias("in_top")), "structure_id", "left").agg(F.count("*").alias("kept"), F.count("in_top").alias("of_top"))


@query("w15_periodic_images", f"WITH {sql.atoms('order')}, {sql.CENTERED} SELECT count(*) AS atoms, count(DISTINCT a.structure_id) AS structures FROM centered a, (SELECT unnest(range(-1, 2)) AS na), (SELECT unnest(range(-1, 2)) AS nb), (SELECT unnest(range(-1, 2)) AS nc) WHERE power(x + 50e0 * na, 2) + power(y + 50e0 * nb, 2) + power(w + 50e0 * nc, 2) <= 3600e0")
def w15(spark, d):
    a = _atoms(spark, d, "order", ids=False)
    return geometry.replicate_images(geometry.center(a), lattice_of(a), 1, 60.0).agg(F.count("*").alias("atoms"), F.countDistinct("structure_id").alias("structures"))


_RESOLUTIONS = {f"bits={b}": (b, 60.0) for b in (2, 3, 4, 5, 6, 8)} | {f"radius={r}": (4, float(r)) for r in (30, 45)}
_GROUPED = "h AS (SELECT structure_id, string_agg(cell || ':' || n, ' ' ORDER BY cell) AS h FROM histogram GROUP BY 1), g AS (SELECT h, count(*) AS c FROM h GROUP BY h)"


@query("w16_resolution", " UNION ALL ".join(f"SELECT * FROM (WITH {sql.d1('part', b, r)}, {_GROUPED} SELECT '{name}' AS variant, (SELECT count(*) FROM histogram) AS nonzeros, (SELECT count(DISTINCT cell) FROM histogram) AS cells, (SELECT CAST(sum(n) AS BIGINT) FROM histogram) AS atoms, round(sum(CASE WHEN c > 1 THEN c ELSE 0 END) / sum(c), 9) AS collision_rate FROM g)" for name, (b, r) in _RESOLUTIONS.items()))
def w16_resolution(spark, d):
    """Cells seen, non-zeros, atoms and collisions of the parts by bits and by radius."""
    out = None
    for name, (b, r) in _RESOLUTIONS.items():
        t = written(ex.triplets_of(spark, d, config=EncodeConfig(bits=b, radius=r)), "resolution")
        row = t.agg(F.lit(name).alias("variant"), F.count("*").alias("nonzeros"), F.countDistinct("cell").alias("cells"), F.sum("n").alias("atoms")).crossJoin(_rounded(metrics.collision_rate(t), 9, "collision_rate").select("collision_rate"))
        out = row if out is None else out.unionByName(row)
    return out


query("w16_ablation")(lambda spark, d: ex.ablation(spark, d))
query("w16_fit_on")(lambda spark, d: ex.fit_on(spark, d))
