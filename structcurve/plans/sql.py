"""SQL fragments for the oracles: the same quantities in plain SQL over the given tables."""

from __future__ import annotations

import math

from ..operators import geometry
from ..sources.tables import EVENT_KINDS, STRUCTURE_KEYS

_LINE = "l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate"


def atoms(by: str = "part") -> str:
    key = STRUCTURE_KEYS[by]
    return f"""atoms AS (SELECT {key} AS structure_id, row_number() OVER (PARTITION BY {key} ORDER BY {_LINE}) AS atom_id, l_linenumber AS z, CAST(l_linenumber AS DOUBLE) AS mass,
  l_quantity - 25.5e0 AS x, l_extendedprice / 2100e0 - 25e0 AS y, date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) / 50e0 - 25e0 AS w FROM lineitem)"""


#: Two passes: centre first, then moments of the centred atoms.
CENTERED = """centre AS (SELECT structure_id, count(*) AS n_atoms, sum(mass) AS m, sum(mass * x) / sum(mass) AS cx, sum(mass * y) / sum(mass) AS cy, sum(mass * w) / sum(mass) AS cw FROM atoms GROUP BY structure_id),
centered AS (SELECT a.structure_id, a.atom_id, a.z, a.mass, a.x - cx AS x, a.y - cy AS y, a.w - cw AS w FROM atoms a JOIN centre USING (structure_id))"""

MOMENTS = (
    "moments AS (SELECT c.structure_id, any_value(n_atoms) AS n_atoms, any_value(m) AS m, any_value(cx) AS cx, any_value(cy) AS cy, any_value(cw) AS cw, "
    + ", ".join(f"sum(mass * {' * '.join(k)}) AS m{k}" for k in geometry.PAIRS + geometry.TRIPLES)
    + " FROM centered c JOIN centre USING (structure_id) GROUP BY c.structure_id)"
)


def chain(first: str, columns: list[str], steps: list[dict[str, str]], name: str) -> str:
    """Projections one after another; a column that is there already is replaced."""
    known, out, source = set(columns), [], first
    for i, step in enumerate(steps):
        again = [c for c in step if c in known]
        star = f"* EXCLUDE ({', '.join(again)})" if again else "*"
        target = f"{name}_{i}" if i < len(steps) - 1 else name
        kept = "MATERIALIZED " if target == name else ""  # what follows starts from rows, not from all steps again
        out.append(f"{target} AS {kept}(SELECT {star}, " + ", ".join(f"{v} AS {k}" for k, v in step.items()) + f" FROM {source})")
        known |= set(step)
        source = target
    return ", ".join(out)


_MOMENT_COLUMNS = ["structure_id", "n_atoms", "m", "cx", "cy", "cw", *(f"m{k}" for k in geometry.PAIRS + geometry.TRIPLES)]
AXES = chain("moments", _MOMENT_COLUMNS, geometry.axis_steps(), "axes")

ORIENTED = (
    "oriented AS MATERIALIZED (SELECT c.structure_id, c.atom_id, c.z, c.mass, "
    + ", ".join(" + ".join(f"c.{a} * r{i + 1}{j + 1}" for j, a in enumerate(geometry.AXES)) + f" AS {name}" for i, name in enumerate(geometry.AXES))
    + " FROM centered c JOIN axes USING (structure_id))"
)
SPHERICAL = """rounded AS (SELECT structure_id, atom_id, z, round(x, 9) + 0e0 AS x, round(y, 9) + 0e0 AS y, round(w, 9) + 0e0 AS w FROM oriented),
far AS (SELECT *, sqrt(x * x + y * y + w * w) AS r FROM rounded),
spherical AS (SELECT structure_id, atom_id, z, r, CASE WHEN r > 0 THEN acos(greatest(-1e0, least(1e0, w / r))) ELSE 0e0 END AS polar,
  CASE WHEN x <> 0 OR y <> 0 THEN atan2(y, x) ELSE 0e0 END AS azimuth FROM far)"""

POSE = f"{CENTERED}, {MOMENTS}, {AXES}, {ORIENTED}, {SPHERICAL}"

PAIRS = """pairs AS (SELECT a.structure_id, a.atom_id, a.z, b.atom_id AS atom_id2, b.z AS z2,
  greatest(sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) + (a.w - b.w) * (a.w - b.w)), 1e-6) AS d FROM atoms a JOIN atoms b ON a.structure_id = b.structure_id AND a.atom_id <> b.atom_id)"""


def bin_of(value: str, lo: str, hi: str, bits: int) -> str:
    n = 1 << bits
    return f"CAST(greatest(0, least({n - 1}, floor(round(({value} - ({lo})) / (({hi}) - ({lo})) * {n}e0, 9)))) AS BIGINT)"


def interleaved(cols: list[str], bits: int) -> str:
    n = len(cols)
    return " + ".join(f"((({c} >> {b}) & 1) << {b * n + n - 1 - d})" for d, c in enumerate(cols) for b in range(bits))


def cells(descriptor: str, lo: str, hi: str, bits: int = 4, radius: float = 60.0, source: str = "spherical") -> str:
    pi = repr(math.pi)
    q = [bin_of(descriptor, lo, hi, bits), bin_of("r", "0e0", f"{radius}e0", bits), bin_of("polar", "0e0", f"{pi}", bits), bin_of("azimuth", f"-{pi}", f"{pi}", bits)]
    return f"quantised AS (SELECT *, " + ", ".join(f"{e} AS q{i}" for i, e in enumerate(q)) + f" FROM {source} WHERE r <= {radius}), encoded AS (SELECT *, {interleaved(['q0', 'q1', 'q2', 'q3'], bits)} AS cell FROM quantised)"


HISTOGRAM = "histogram AS (SELECT structure_id, cell, count(*) AS n FROM encoded GROUP BY structure_id, cell)"


def d1(by: str = "part", bits: int = 4, radius: float = 60.0) -> str:
    return f"{atoms(by)}, {POSE}, {cells('CAST(z AS DOUBLE)', '0e0', f'{1 << bits}e0', bits, radius)}, {HISTOGRAM}"


TARGETS = f"""{PAIRS}, half AS (SELECT structure_id, sum(z * z2 / d) AS f, sum(1 / (1 + power(d / 6, 6))) AS l, sum(z * z2 / (power(d, 6) + 46656e0)) AS q FROM pairs WHERE atom_id < atom_id2 GROUP BY structure_id),
own AS (SELECT structure_id, round(-sum(0.5e0 * power(CAST(z AS DOUBLE), 2.4e0)), 9) AS t_point FROM atoms GROUP BY structure_id),
targets AS (SELECT structure_id, t_point, coalesce(f, 0) AS t_ffsum, -coalesce(l, 0) AS t_lattice, -1e6 * coalesce(q, 0) AS t_dispersion FROM own LEFT JOIN half USING (structure_id))"""

FOLD = "CAST((((structure_id % 2147483648) * 1103515245 + 12345) % 2147483648) // 65536 % {k} AS INT)"

FOLDED = f"{atoms()}, {TARGETS}, folded AS (SELECT *, {FOLD.format(k=10)} AS fold FROM targets)"
LONG = """long AS (SELECT structure_id, fold, 'point' AS target, t_point AS calc FROM folded UNION ALL SELECT structure_id, fold, 'ffsum', t_ffsum FROM folded
UNION ALL SELECT structure_id, fold, 'lattice', t_lattice FROM folded UNION ALL SELECT structure_id, fold, 'dispersion', t_dispersion FROM folded)"""
MEAN = """mean AS (SELECT fold, target, (sum(sum(calc)) OVER (PARTITION BY target) - sum(calc)) / (sum(count(*)) OVER (PARTITION BY target) - count(*)) AS pred FROM long GROUP BY fold, target),
predicted AS (SELECT structure_id, fold, target, calc, pred FROM long JOIN mean USING (fold, target))"""
#: Predictions of the mean, by fold: what the measures are checked on.
PREDICTED = f"{FOLDED}, {LONG}, {MEAN}"

EVENT_CODE = "coalesce(nullif(list_position([" + ", ".join(f"'{k}'" for k in EVENT_KINDS) + "], event_type), 0), 0)"
EVENT_CELLS = f"""points AS (SELECT event_id, ts, user_id AS structure_id, CAST({EVENT_CODE} AS DOUBLE) AS kind, CAST(extract('hour' FROM ts) AS DOUBLE) AS hour, value, CAST(json_extract_string(props, '$.k') AS DOUBLE) AS k FROM events),
cut AS (SELECT *, {bin_of('kind', '0e0', '16e0', 4)} AS q0, {bin_of('hour', '0e0', '24e0', 4)} AS q1, {bin_of('value', '0e0', '500e0', 4)} AS q2, {bin_of('k', '0e0', '100e0', 4)} AS q3 FROM points),
event_cells AS (SELECT event_id, ts, structure_id, {interleaved(['q0', 'q1', 'q2', 'q3'], 4)} AS cell FROM cut)"""

WORDS = r"""words AS (SELECT {id} AS structure_id, unnest(list_filter(string_split_regex(lower(coalesce({text}, '')), '[^\p{{L}}]+'), lambda w: w <> '')) AS token FROM {table}),
tokens AS (SELECT structure_id, token, count(*) AS n FROM words GROUP BY structure_id, token)"""


def weighted(histogram: str) -> str:
    """TF-IDF weights of a histogram as rows, and the matrix of structures' inner products as rows (``gram``)."""
    return f"""{histogram}, tf AS (SELECT structure_id, cell, n / sum(n) OVER (PARTITION BY structure_id) AS tf FROM histogram),
idf AS (SELECT cell, ln((SELECT count(DISTINCT structure_id) FROM histogram) / count(*)) AS idf FROM histogram GROUP BY cell),
w AS MATERIALIZED (SELECT structure_id, cell, tf * idf AS weight FROM tf JOIN idf USING (cell) WHERE idf > 0),
gram AS MATERIALIZED (SELECT a.structure_id AS i, b.structure_id AS j, sum(a.weight * b.weight) AS g FROM w a JOIN w b USING (cell) GROUP BY 1, 2)"""


def energies(histogram: str, k: int, steps: int = 300) -> str:
    """``energy (dim, lam)``: the k largest eigenvalues of the Gram matrix, by power iteration and deflation."""
    parts = [f"""WITH RECURSIVE {weighted(histogram)},
ids AS (SELECT DISTINCT structure_id AS i FROM w),
line AS (SELECT p.i, list(coalesce(g, 0e0) ORDER BY q.i) AS r FROM ids p CROSS JOIN ids q LEFT JOIN gram ON gram.i = p.i AND gram.j = q.i GROUP BY p.i),
m1 AS MATERIALIZED (SELECT list(r ORDER BY i) AS m, count(*) AS n FROM line)"""]
    for d in range(1, k + 1):
        image = "list_transform(m, lambda r: list_dot_product(r, v))"
        parts.append(f"""it{d} AS (SELECT 0 AS t, list_transform(range(1, n + 1), lambda i: 1e0 + ((i * 7919 + {d}) % 101) / 101e0) AS v FROM m{d} UNION ALL
  SELECT t + 1, list_transform(y, lambda x: x / size) FROM (SELECT t, y, sqrt(list_dot_product(y, y)) AS size FROM (SELECT t, {image} AS y FROM it{d}, m{d} WHERE t < {steps}))),
e{d} AS MATERIALIZED (SELECT v, list_dot_product(v, {image}) AS lam FROM it{d}, m{d} WHERE t = {steps}),
m{d + 1} AS MATERIALIZED (SELECT list_transform(m, lambda r, i: list_transform(r, lambda x, j: x - lam * v[i] * v[j])) AS m, n FROM m{d}, e{d})""")
    rows = " UNION ALL ".join(f"SELECT {d} AS dim, lam FROM e{d}" for d in range(1, k + 1))
    return ", ".join(parts) + f", energy AS (SELECT CAST(dim AS INT) AS dim, lam FROM ({rows}))"
