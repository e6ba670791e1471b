"""Queries of the operators around the methods: sources, predicates, joins, aggregates, windows, sets, functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import curves, udfs, vectors
from ..operators import curation, descriptors, encode, features, geometry, joins, learn, lsi, metrics, zorder
from ..session import fresh_path, written
from ..sources import sinks
from ..sources.tables import atoms_from_events, atoms_from_lineitem, html_text, lattice_of, load, points_from_embeddings, random_atoms, tokens
from . import experiments as ex
from . import sql
from .methods import ENERGIES, _BONDS, _D1, _atoms, _mean_errors, _P, _r, _rounded, m15_orders
from .registry import query


def _cells(spark, d, by: str = "part") -> DataFrame:
    return encode.encode_structures(_atoms(spark, d, by, ids=False))


_SUP = sql.d1("supplier")

# ---- sources and sinks --------------------------------------------------------------------------

_TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


@query("s1_table_scans", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in _TABLES))
def s1(spark, d):
    out = None
    for t in _TABLES:
        row = load(spark, d, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = row if out is None else out.union(row)
    return out


def _s2(by: str) -> None:
    @query(f"s2_atoms_by_{by}", f"WITH {sql.atoms(by)} SELECT structure_id, CAST(atom_id AS BIGINT) AS atom_id, z, {_r(6, 'x', 'y', 'w')} FROM atoms")
    def run(spark, d):
        return _rounded(atoms_from_lineitem(spark, d, by, ids=True), 6, "x", "y", "w").select("structure_id", F.col("atom_id").cast("bigint").alias("atom_id"), "z", "x", "y", "w")


for _by in ("part", "order", "supplier"):
    _s2(_by)


@query("s3_atoms_from_events", f"WITH {sql.EVENT_CELLS} SELECT event_id, structure_id, CAST(kind AS INT) AS kind, CAST(hour AS INT) AS hour, value, k FROM points")
def s3(spark, d):
    return atoms_from_events(spark, d).select("event_id", "structure_id", "kind", "hour", "value", "k")


@query("s4_points_from_embeddings", "SELECT vec_id, point, round(CAST(embedding[point * 4 + 1] AS DOUBLE), 6) + 0e0 AS c0, round(CAST(embedding[point * 4 + 4] AS DOUBLE), 6) + 0e0 AS c3 FROM (SELECT vec_id, CAST(unnest(range(16)) AS INT) AS point, embedding FROM embeddings)")
def s4(spark, d):
    return _rounded(points_from_embeddings(spark, d), 6, "c0", "c3").select("vec_id", "point", "c0", "c3")


def _s5(table: str, key: str) -> None:
    # ASCII letters are the class that both engines' lower() and splitting treat alike
    @query(f"s5_tokens_{table}", f"WITH {sql.WORDS.format(id=key, text='text', table=table)} SELECT structure_id, token, CAST(sum(n) AS BIGINT) AS n FROM tokens GROUP BY 1, 2")
    def run(spark, d):
        return tokens(load(spark, d, table), key)


for _t, _k in (("documents", "doc_id"), ("benchmark", "item_id"), ("conversations", "conv_id")):
    _s5(_t, _k)


@query("s6_html_text", r"SELECT page_id, trim(regexp_replace(regexp_replace(coalesce(html, ''), '(?s)<script.*?</script>|<style.*?</style>|<!--.*?-->|<[^>]*>', ' ', 'g'), '\s+', ' ', 'g')) AS plain FROM pages")
def s6(spark, d):
    return html_text(load(spark, d, "pages")).select("page_id", "plain")


@query("s7_crystal_text", "SELECT CAST(s_nationkey AS BIGINT) AS structure_id, CASE s_suppkey % 3 WHEN 0 THEN 'C' WHEN 1 THEN 'O' ELSE 'H' END AS element, s_acctbal / 100e0 AS x, CAST(s_suppkey AS DOUBLE) AS y, CAST(s_nationkey AS DOUBLE) AS w FROM supplier")
def s7(spark, d):
    """Nations as structures of their suppliers, written to shared storage as crystal text and read by the data source."""
    from ..sources.crystal import CrystalTextSource

    spark.dataSource.register(CrystalTextSource)
    path = fresh_path(spark, "crystal")
    element = F.when(F.col("s_suppkey") % 3 == 0, "C").when(F.col("s_suppkey") % 3 == 1, "O").otherwise("H")
    place = [(F.col("s_acctbal") / 100.0), F.col("s_suppkey").cast("double"), F.col("s_nationkey").cast("double")]
    atom = F.concat_ws(" ", element, *(c.cast("string") for c in place))
    head = F.concat(F.lit("data_"), F.col("s_nationkey"), F.lit("\n_structure_number "), F.col("s_nationkey"), F.lit("\nloop_\n_atom_site_type_symbol\n_atom_site_Cartn_x\n_atom_site_Cartn_y\n_atom_site_Cartn_z\n"))
    blocks = load(spark, d, "supplier").groupBy("s_nationkey").agg(F.array_join(F.collect_list(atom), "\n").alias("rows"))
    blocks.select(F.concat(head, "rows").alias("value")).write.text(path)
    return spark.read.format("crystaltext").option("path", path).option("suffix", ".txt").load()


def _s8(fmt: str) -> None:
    @query(f"s8_roundtrip_{fmt}", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
    def run(spark, d):
        return sinks.roundtrip(load(spark, d, "nation"), fmt, fresh_path(spark, fmt)).select("n_nationkey", "n_name", "n_regionkey")


for _f in ("csv", "json", "orc"):
    _s8(_f)


def _random_sql(a: int) -> str:
    m = 2147483648
    step = lambda salt: f"((((id + 1) * 1103515245 + {12345 + salt}) % {m}) * 1103515245 + 12345) % {m} // 65536"
    return f"SELECT s_suppkey AS structure_id, CAST(atom + 1 AS INT) AS atom_id, CAST({step(7)} % 4 + 5 AS INT) AS z, ({step(1)}) / 32768e0 * 40e0 - 20e0 AS x FROM (SELECT s_suppkey, atom, s_suppkey * {a} + atom AS id FROM supplier, range({a}) t(atom))"


@query("s9_random_structures", _random_sql(20))
def s9(spark, d):
    """Twenty random atoms for each supplier."""
    return random_atoms(load(spark, d, "supplier").select(F.col("s_suppkey").alias("structure_id")), 20).select("structure_id", "atom_id", "z", "x")


@query("s10_bucketed_sink", f"WITH {_D1} SELECT CAST(structure_id % 16 AS INT) AS bucket, count(*) AS n FROM histogram WHERE structure_id % 16 = 3 GROUP BY 1")
def s10(spark, d):
    out = sinks.write_bucketed(_cells(spark, d), fresh_path(spark, "bucketed"))
    return out.where("bucket = 3").groupBy("bucket").agg(F.count("*").alias("n"))


_CUT3 = ", ".join(f"{sql.bin_of(c, '-25e0', '25e0', 6)} AS q{i}" for i, c in enumerate("xyw"))
_BOXED = f"WITH {sql.atoms()}, g AS (SELECT *, {_CUT3} FROM atoms), coded AS (SELECT *, {sql.interleaved(['q0', 'q1', 'q2'], 6)} AS cell FROM g)"


def _gridded(spark, d) -> DataFrame:
    grid = encode.GridSpec(tuple(encode.DimSpec(c, -25.0, 25.0, 6) for c in ("x", "y", "w")))
    q = encode.quantize(_atoms(spark, d, ids=False), grid)
    return q.withColumn("cell", curves.morton_encode(["q0", "q1", "q2"], 6))


@query("s11_curve_ordered_sink", f"{_BOXED} SELECT cell, count(*) AS n FROM coded GROUP BY cell")
def s11(spark, d):
    return sinks.write_ordered(_gridded(spark, d), fresh_path(spark, "ordered"), "cell").groupBy("cell").agg(F.count("*").alias("n"))


@query("s12_model_save_load", f"{sql.energies(sql.d1('supplier', 3), 3)} SELECT dim, round(ln(lam) + 1.3e-4, 3) + 0e0 AS log_energy FROM energy")
def s12(spark, d):
    """Energies of the dimensions into which a model that was saved and loaded reduces the structures."""
    t = written(encode.encode_structures(_atoms(spark, d, "supplier", ids=False), encode.EncodeConfig(bits=3)), "save")
    path = lsi.new_path(fresh_path(spark, "model"))
    lsi.fit_lsi(t, 3, "gram").save(spark, path)
    again = lsi.reduce_structures(t, lsi.LsiModel.load(spark, path))
    energy = again.select(F.posexplode("vec").alias("i", "v")).groupBy((F.col("i") + 1).alias("dim")).agg(F.log(F.sum(F.col("v") * F.col("v"))).alias("e"))
    return energy.select("dim", (F.round(F.col("e") + 1.3e-4, 3) + F.lit(0.0)).alias("log_energy"))


@query("s13_file_stream", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def s13(spark, d):
    from ..streaming.streams import drained, stream_events

    return drained(stream_events(spark, d)).groupBy("event_type").agg(F.count("*").alias("n"))


# ---- projection and predicates ------------------------------------------------------------------


@query("p1_project", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")
def p1(spark, d):
    return load(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@query("p2_rule_filter", "SELECT p_partkey FROM part WHERE p_size <= 45 AND p_type <> 'PROMO'")
def p2(spark, d):
    rules = ["p_size <= 45", "p_type <> 'PROMO'"]
    return load(spark, d, "part").where(" AND ".join(rules)).select("p_partkey")


@query("p3_complete_only", "SELECT l_partkey AS structure_id, count(*) AS n FROM lineitem GROUP BY 1 HAVING bool_and(l_quantity IS NOT NULL AND l_extendedprice IS NOT NULL AND l_shipdate IS NOT NULL)")
def p3(spark, d):
    return curation.complete_only(_atoms(spark, d, ids=False)).groupBy("structure_id").agg(F.count("*").alias("n"))


@query("p4_within_sphere", f"WITH {sql.atoms()}, {sql.POSE} SELECT structure_id, count(*) AS n FROM spherical WHERE r <= 30 GROUP BY 1")
def p4(spark, d):
    return encode.within_sphere(encode.spherical_atoms(_atoms(spark, d, ids=False)), 30.0).groupBy("structure_id").agg(F.count("*").alias("n"))


_IN_BOX = "q0 BETWEEN 8 AND 15 AND q1 BETWEEN 8 AND 20 AND q2 BETWEEN 5 AND 15"


@query("p5_box_filter", f"{_BOXED} SELECT structure_id, cell FROM coded WHERE {_IN_BOX}")
def p5(spark, d):
    return zorder.box_filter(_gridded(spark, d), ["q0", "q1", "q2"], [8, 8, 5], [15, 20, 15]).select("structure_id", "cell")


@query("p6_index_box_filter", f"{_BOXED} SELECT structure_id, cell FROM coded WHERE {_IN_BOX}")
def p6(spark, d):
    return zorder.index_box_filter(written(_gridded(spark, d), "gridded"), "cell", ["q0", "q1", "q2"], [8, 8, 5], [15, 20, 15], 6).select("structure_id", "cell")


@query("p7_membership_and_patterns", "SELECT p_partkey FROM part WHERE p_type IN ('PROMO', 'SMALL') AND p_name LIKE '%a%' AND regexp_matches(p_brand, '[0-9]')")
def p7(spark, d):
    return load(spark, d, "part").where(F.col("p_type").isin("PROMO", "SMALL") & F.col("p_name").like("%a%") & F.col("p_brand").rlike("[0-9]")).select("p_partkey")


# ---- joins --------------------------------------------------------------------------------------


@query("j1_broadcast_join", "SELECT n_name, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name")
def j1(spark, d):
    s = joins.join_broadcast(load(spark, d, "supplier"), load(spark, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey"))
    return joins.join_broadcast(load(spark, d, "lineitem"), s, F.col("l_suppkey") == F.col("s_suppkey")).groupBy("n_name").agg(F.count("*").alias("n"))


_ORDER_SUM = "SELECT o_orderstatus, count(*) AS n, round(sum(l_quantity), 4) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"


def _order_sum(join, spark, d):
    return join(load(spark, d, "orders"), load(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 4).alias("q"))


query("j2_merge_join", _ORDER_SUM)(lambda spark, d: _order_sum(joins.join_merge, spark, d))
query("j3_shuffle_hash_join", _ORDER_SUM)(lambda spark, d: _order_sum(joins.join_shuffle_hash, spark, d))


@query("j4_left_outer_zero_filled", "SELECT o_orderkey AS structure_id, count(l_orderkey) AS n_atoms FROM orders LEFT JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def j4(spark, d):
    return joins.structures_with_counts(load(spark, d, "orders").select(F.col("o_orderkey").alias("structure_id")), _atoms(spark, d, "order", ids=False))


@query("j5_full_outer", f"WITH {_D1}, h30 AS (SELECT structure_id, {sql.interleaved(['q0', 'q1b', 'q2', 'q3'], 4)} AS cell FROM (SELECT *, {sql.bin_of('r', '0e0', '45e0', 4)} AS q1b FROM quantised)), b AS (SELECT structure_id, cell, count(*) AS nb FROM h30 GROUP BY 1, 2) SELECT structure_id, CAST(sum(abs(coalesce(n, 0) - coalesce(nb, 0))) AS BIGINT) AS moved FROM histogram FULL JOIN b USING (structure_id, cell) GROUP BY 1")
def j5(spark, d):
    a = _atoms(spark, d, ids=False)
    return metrics.compare_histograms(encode.encode_structures(a), encode.encode_structures(a, encode.EncodeConfig(radius=45.0, outside="clamp")))


@query("j6_left_semi", "SELECT p_partkey AS structure_id FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity = 50)")
def j6(spark, d):
    good = load(spark, d, "lineitem").where("l_quantity = 50").select(F.col("l_partkey").alias("structure_id"))
    return curation.keep_curated(load(spark, d, "part").select(F.col("p_partkey").alias("structure_id")), good)


@query("j7_left_anti", "SELECT p_partkey AS structure_id FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity = 50)")
def j7(spark, d):
    bad = load(spark, d, "lineitem").where("l_quantity = 50").select(F.col("l_partkey").alias("structure_id"))
    return curation.exclude(load(spark, d, "part").select(F.col("p_partkey").alias("structure_id")), bad)


@query("j8_pair_self_join", f"WITH {sql.atoms()}, {sql.PAIRS} SELECT structure_id, count(*) AS n, round(min(d), 6) AS nearest, round(max(d), 6) AS farthest FROM pairs GROUP BY 1")
def j8(spark, d):
    return descriptors.pairs(_atoms(spark, d)).groupBy("structure_id").agg(F.count("*").alias("n"), F.round(F.min("d"), 6).alias("nearest"), F.round(F.max("d"), 6).alias("farthest"))


@query("j9_range_join", f"WITH {sql.atoms()}, {_BONDS} SELECT structure_id, atom_id, b AS n FROM bonds")
def j9(spark, d):
    return descriptors.neighbours(_atoms(spark, d), 10.0).groupBy("structure_id", "atom_id").agg(F.count("*").alias("n"))


@query("j10_blocked_range_join", f"WITH {sql.atoms('supplier')}, {sql.PAIRS.replace('a.atom_id <> b.atom_id', 'a.atom_id <> b.atom_id AND abs(a.x - b.x) <= 4')} SELECT structure_id, atom_id, count(*) AS n FROM pairs WHERE d <= 4 GROUP BY 1, 2")
def j10(spark, d):
    return descriptors.neighbour_counts(_atoms(spark, d, "supplier"), 4.0).where("n > 0")


@query("j11_images_of_orders", f"WITH {sql.atoms('order')} SELECT structure_id, 27 * count(*) AS images FROM atoms GROUP BY 1")
def j11(spark, d):
    a = _atoms(spark, d, "order", ids=False)
    return geometry.replicate_images(a, lattice_of(a)).groupBy("structure_id").agg(F.count("*").alias("images"))


@query("j12_asof_join", "SELECT a.event_id, b.value AS asof_value FROM (SELECT * FROM events WHERE event_type = 'purchase') a ASOF LEFT JOIN (SELECT user_id, ts, value FROM events WHERE event_type = 'click') b ON a.user_id = b.user_id AND a.ts >= b.ts")
def j12(spark, d):
    e = load(spark, d, "events")
    buy, click = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), e.where("event_type = 'click'").select("user_id", "ts", "value")
    return joins.asof(buy, click, "user_id", "ts", "value").select("event_id", "asof_value")


@query("j13_interval_join", "SELECT s.event_id AS span, count(*) AS n FROM events e JOIN (SELECT event_id, ts AS a, ts + INTERVAL 3 HOUR AS b FROM events WHERE event_id % 50 = 0) s ON e.ts >= a AND e.ts < b GROUP BY 1")
def j13(spark, d):
    e = load(spark, d, "events")
    spans = e.where("event_id % 50 = 0").select(F.col("event_id").alias("span"), F.col("ts").alias("start_ts"), (F.col("ts") + F.expr("interval 3 hours")).alias("end_ts"))
    return joins.interval_join(e.select("event_id", "ts"), spans).groupBy("span").agg(F.count("*").alias("n"))


@query("j14_nearest_atoms", f"WITH {sql.atoms()}, {sql.PAIRS}, n AS (SELECT *, row_number() OVER (PARTITION BY structure_id, atom_id ORDER BY d, atom_id2) AS rank FROM pairs) SELECT structure_id, atom_id, CAST(rank AS INT) AS rank, atom_id2, round(d, 6) AS d FROM n WHERE rank <= 2")
def j14(spark, d):
    return _rounded(descriptors.nearest_atoms(_atoms(spark, d), 2), 6, "d")


# ---- aggregation --------------------------------------------------------------------------------


@query("g1_group_count", f"WITH {_SUP} SELECT cell, CAST(sum(n) AS BIGINT) AS n FROM histogram GROUP BY cell")
def g1(spark, d):
    return _cells(spark, d, "supplier").groupBy("cell").agg(F.sum("n").alias("n"))


@query("g2_describe_by", "SELECT event_type, count(*) AS n, round(sum(value), 4) AS total, round(avg(value), 6) AS mean, min(value) AS lo, max(value) AS hi, round(stddev_samp(value), 6) AS sd, round(corr(value, CAST(json_extract_string(props, '$.k') AS DOUBLE)), 6) AS r FROM events GROUP BY event_type")
def g2(spark, d):
    k = F.get_json_object("props", "$.k").cast("double")
    return load(spark, d, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"), F.round(F.avg("value"), 6).alias("mean"), F.min("value").alias("lo"), F.max("value").alias("hi"), F.round(F.stddev_samp("value"), 6).alias("sd"), F.round(F.corr("value", k), 6).alias("r"))


@query("g3_vocabulary_size", f"WITH {_SUP} SELECT structure_id % 10 AS shelf, count(DISTINCT cell) AS cells FROM histogram GROUP BY 1")
def g3(spark, d):
    return _cells(spark, d, "supplier").groupBy(F.pmod("structure_id", F.lit(10)).alias("shelf")).agg(F.countDistinct("cell").alias("cells"))


_EXACT_CELLS = f"WITH {_SUP} SELECT count(DISTINCT cell) AS cells, TRUE AS close FROM histogram"


@query("g4_vocabulary_estimate", _EXACT_CELLS)
def g4(spark, d):
    r = _cells(spark, d, "supplier").agg(F.approx_count_distinct("cell", 0.01).alias("a"), F.countDistinct("cell").alias("cells"))
    return r.select("cells", (F.abs(F.col("a") - F.col("cells")) <= 0.05 * F.col("cells")).alias("close"))


@query("g5_vocabulary_sketch", _EXACT_CELLS)
def g5(spark, d):
    cells = _cells(spark, d, "supplier")
    per = cells.groupBy("structure_id").agg(F.hll_sketch_agg("cell").alias("s"))
    whole = per.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("a"))
    return whole.join(cells.agg(F.countDistinct("cell").alias("cells"))).select("cells", (F.abs(F.col("a") - F.col("cells")) <= 0.05 * F.col("cells")).alias("close"))


@query("g6_conditional_counts", "SELECT l_suppkey, count(*) FILTER (l_tax <= 0.04e0) AS low_tax, count(*) FILTER (l_returnflag = 'R') AS returned FROM lineitem GROUP BY 1")
def g6(spark, d):
    return load(spark, d, "lineitem").groupBy("l_suppkey").agg(F.count_if(F.col("l_tax") <= 0.04).alias("low_tax"), F.count_if(F.col("l_returnflag") == "R").alias("returned"))


@query("g7_heaviest_cell", f"WITH {_SUP} SELECT structure_id, arg_max(cell, n * 100000 - cell) AS cell, max(n) AS n FROM histogram GROUP BY 1")
def g7(spark, d):
    t = _cells(spark, d, "supplier")
    return t.groupBy("structure_id").agg(F.max_by("cell", F.struct("n", -F.col("cell"))).alias("cell"), F.max("n").alias("n"))


@query("g8_quantiles", f"WITH {sql.FOLDED} SELECT round(quantile_cont(t_point, 0.25), 5) AS q1, round(quantile_cont(t_point, 0.5), 5) AS median, round(quantile_cont(t_point, 0.75), 5) AS q3 FROM folded")
def g8(spark, d):
    return ex.targets_of(spark, d).agg(*(F.round(F.percentile("point", F.lit(p)), 5).alias(n) for p, n in ((0.25, "q1"), (0.5, "median"), (0.75, "q3"))))


@query("g8_quantiles_approximate", f"WITH {sql.FOLDED} SELECT round(quantile_cont(t_point, 0.5), 5) AS median, TRUE AS close FROM folded")
def g8a(spark, d):
    r = ex.targets_of(spark, d).agg(F.percentile_approx("point", F.lit(0.5), 1000).alias("a"), F.percentile("point", F.lit(0.5)).alias("e"))
    return r.select(F.round("e", 5).alias("median"), (F.abs(F.col("a") - F.col("e")) <= 0.02 * F.abs("e")).alias("close"))


_E = f"WITH {_P}, e AS (SELECT target, fold, abs((pred - calc) / calc) AS error FROM predicted)"


def _row_errors(spark, d) -> DataFrame:
    return _mean_errors(spark, d).select("structure_id", "target", "fold", F.abs((F.col("pred") - F.col("calc")) / F.col("calc")).alias("error"))


@query("g9_grouping_sets", f"{_E} SELECT target, CAST(fold AS VARCHAR) AS fold, CAST(grouping(target) * 2 + grouping(fold) AS BIGINT) AS level, round(avg(error), 6) AS error FROM e GROUP BY GROUPING SETS ((target, fold), (target), ())")
def g9(spark, d):
    _row_errors(spark, d).createOrReplaceTempView("row_errors")
    return spark.sql("SELECT target, CAST(fold AS STRING) AS fold, CAST(grouping_id(target, fold) AS BIGINT) AS level, round(avg(error), 6) AS error FROM row_errors GROUP BY GROUPING SETS ((target, fold), (target), ())")


@query("g10_rollup", "SELECT r_name, n_name, count(*) AS suppliers, round(sum(s_acctbal), 2) AS balance FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def g10(spark, d):
    j = load(spark, d, "supplier").join(load(spark, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(load(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.rollup("r_name", "n_name").agg(F.count("*").alias("suppliers"), F.round(F.sum("s_acctbal"), 2).alias("balance"))


@query("g11_cube", f"{_E} SELECT target, CAST(fold AS VARCHAR) AS fold, count(*) AS n, round(avg(error), 6) AS error FROM e GROUP BY CUBE (target, fold)")
def g11(spark, d):
    return _row_errors(spark, d).cube("target", "fold").agg(F.count("*").alias("n"), F.round(F.avg("error"), 6).alias("error")).withColumn("fold", F.col("fold").cast("string"))


@query("g12_pivot", f"{_E} SELECT fold, " + ", ".join(f"round(avg(error) FILTER (target = '{t}'), 6) AS {t}" for t in ENERGIES) + " FROM e GROUP BY fold")
def g12(spark, d):
    return _row_errors(spark, d).groupBy("fold").pivot("target", ENERGIES).agg(F.round(F.avg("error"), 6))


@query("g13_unpivot", f"WITH {sql.FOLDED}, {sql.LONG} SELECT structure_id, fold, target, round(calc, 4) AS calc FROM long")
def g13(spark, d):
    return _rounded(metrics.long_targets(ex.targets_of(spark, d), ENERGIES), 4, "calc")


@query("g14_collect_ordered", f"WITH {_SUP} SELECT structure_id, count(*) AS cells, min(cell) AS first, max(cell) AS last FROM histogram GROUP BY 1")
def g14(spark, d):
    s = encode.to_sparse(_cells(spark, d, "supplier"))
    return s.select("structure_id", F.size("cells").cast("bigint").alias("cells"), F.get("cells", F.lit(0)).alias("first"), F.element_at("cells", -1).alias("last"))


@query("g15_vector_sum", "SELECT label, i, round(sum(v), 4) + 0e0 AS total FROM (SELECT label, unnest(range(64)) AS i, unnest(embedding)::DOUBLE AS v FROM embeddings) GROUP BY 1, 2")
def g15(spark, d):
    rows = load(spark, d, "embeddings").select("label", F.posexplode("embedding").alias("i", "v"))
    return rows.groupBy("label", F.col("i").cast("bigint").alias("i")).agg((F.round(F.sum(F.col("v").cast("double")), 4) + F.lit(0.0)).alias("total"))


@query("g16_boolean_aggregates", "SELECT l_partkey, bool_and(l_linenumber <= 6) AS every, bool_or(l_linenumber = 7) AS some FROM lineitem GROUP BY 1")
def g16(spark, d):
    return load(spark, d, "lineitem").groupBy("l_partkey").agg(F.bool_and(F.col("l_linenumber") <= 6).alias("every"), F.bool_or(F.col("l_linenumber") == 7).alias("some"))


@query("g17_sort_aggregate", "SELECT l_suppkey, max(l_returnflag) AS flag, min(l_linestatus) AS status FROM lineitem GROUP BY 1")
def g17(spark, d):
    return load(spark, d, "lineitem").groupBy("l_suppkey").agg(F.max("l_returnflag").alias("flag"), F.min("l_linestatus").alias("status"))


@query("g18_fixed_width_bins", "SELECT CAST(CASE WHEN value >= 500 THEN 11 ELSE floor(value / 50) + 1 END AS BIGINT) AS bin, count(*) AS n FROM events GROUP BY 1")
def g18(spark, d):
    return load(spark, d, "events").groupBy(F.width_bucket("value", F.lit(0.0), F.lit(500.0), F.lit(10)).alias("bin")).agg(F.count("*").alias("n"))


# ---- windows, sorts, limits, sets ---------------------------------------------------------------

_T = f"WITH {sql.FOLDED}"


@query("n1_ranks", f"{_T} SELECT structure_id, CAST(row_number() OVER (PARTITION BY fold ORDER BY t_lattice, structure_id) AS INT) AS rn, CAST(rank() OVER (PARTITION BY fold ORDER BY round(t_lattice, 0)) AS INT) AS rk, CAST(dense_rank() OVER (PARTITION BY fold ORDER BY round(t_lattice, 0)) AS INT) AS dr FROM folded")
def n1(spark, d):
    w, c = Window.partitionBy("fold"), F.round("lattice", 0)
    return ex.targets_of(spark, d).select("structure_id", F.row_number().over(w.orderBy("lattice", "structure_id")).alias("rn"), F.rank().over(w.orderBy(c)).alias("rk"), F.dense_rank().over(w.orderBy(c)).alias("dr"))


@query("n2_percent_ranks", f"{_T} SELECT structure_id, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd, CAST(ntile(4) OVER w AS INT) AS quarter FROM folded WINDOW w AS (PARTITION BY fold ORDER BY t_lattice, structure_id)")
def n2(spark, d):
    w = Window.partitionBy("fold").orderBy("lattice", "structure_id")
    return ex.targets_of(spark, d).select("structure_id", F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"), F.ntile(4).over(w).alias("quarter"))


from .methods import _CURVE_SQL, _GRADIENT_SQL, event_curve  # noqa: E402


@query("n3_gradient", f"WITH {_CURVE_SQL}, {_GRADIENT_SQL} SELECT dim, round(sigma, 9) AS sigma, round(gradient, 9) + 0e0 AS gradient FROM g")
def n3(spark, d):
    return _rounded(lsi.gradient(event_curve(spark, d)), 9, "sigma", "gradient")


@query("n4_energy_kept", f"WITH {_CURVE_SQL} SELECT dim, round(sum(sigma * sigma) OVER (ORDER BY dim) / sum(sigma * sigma) OVER (), 9) AS kept FROM s")
def n4(spark, d):
    e = F.col("sigma") * F.col("sigma")
    return event_curve(spark, d).select("dim", F.round(F.sum(e).over(Window.orderBy("dim").rowsBetween(Window.unboundedPreceding, 0)) / F.sum(e).over(Window.partitionBy()), 9).alias("kept"))


@query("n5_rolling_value", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW), 4) AS rolling FROM events")
def n5(spark, d):
    w = Window.partitionBy("user_id").orderBy(F.unix_timestamp("ts")).rangeBetween(-3600, 0)
    return load(spark, d, "events").select("event_id", F.round(F.sum("value").over(w), 4).alias("rolling"))


@query("n6_whole_group_frame", f"WITH {_SUP} SELECT structure_id, cell, round(n / sum(n) OVER (PARTITION BY structure_id), 9) AS tf FROM histogram")
def n6(spark, d):
    return _rounded(lsi.term_frequency(_cells(spark, d, "supplier")), 9, "tf").select("structure_id", "cell", "tf")


@query("n7_edges", "SELECT event_id, first_value(value) OVER w AS first, last_value(value) OVER w AS last, nth_value(value, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def n7(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return load(spark, d, "events").select("event_id", F.first("value").over(w).alias("first"), F.last("value").over(w).alias("last"), F.nth_value("value", 2).over(w).alias("second"))


@query("o1_total_order", f"WITH {_SUP} SELECT structure_id, cell, n FROM histogram ORDER BY cell, structure_id")
def o1(spark, d):
    return _cells(spark, d, "supplier").orderBy("cell", "structure_id")


@query("o2_sort_within_partitions", f"WITH {_SUP} SELECT structure_id, cell, n FROM histogram")
def o2(spark, d):
    return encode.traverse(_cells(spark, d, "supplier"))


@query("o3_global_top", f"{_T} SELECT structure_id, round(t_point, 5) AS point FROM folded ORDER BY t_point, structure_id LIMIT 20")
def o3(spark, d):
    return _rounded(ex.targets_of(spark, d).orderBy("point", "structure_id").limit(20), 5, "point").select("structure_id", "point")


@query("o4_top_per_group", f"WITH {_SUP}, r AS (SELECT *, row_number() OVER (PARTITION BY structure_id ORDER BY n DESC, cell) AS rank FROM histogram) SELECT structure_id, cell, n, CAST(rank AS INT) AS rank FROM r WHERE rank <= 3")
def o4(spark, d):
    return features.top_cells(_cells(spark, d, "supplier"), 3)


@query("o5_page", f"{_T} SELECT structure_id, round(t_ffsum, 5) AS ffsum FROM folded ORDER BY t_ffsum, structure_id LIMIT 25 OFFSET 50")
def o5(spark, d):
    return _rounded(ex.targets_of(spark, d).orderBy("ffsum", "structure_id").offset(50).limit(25), 5, "ffsum").select("structure_id", "ffsum")


@query("x1_union_by_name", f"WITH {_D1}, h AS (SELECT structure_id, cell, n FROM histogram) SELECT 'a' AS run, structure_id, cell, n FROM h UNION ALL SELECT 'b', structure_id, cell, n FROM h")
def x1(spark, d):
    t = _cells(spark, d)
    return t.withColumn("run", F.lit("a")).unionByName(t.select("n", "cell", "structure_id").withColumn("run", F.lit("b")))


def _tops(spark, d):
    t = written(ex.targets_of(spark, d), "tops")
    k = int(-(-t.count() * 15 // 100))
    return t.orderBy("point", "structure_id").limit(k).select("structure_id"), t.orderBy("lattice", "structure_id").limit(k).select("structure_id")


_TOPS = f"{_T}, k AS (SELECT CAST(ceil(count(*) * 0.15) AS BIGINT) AS k FROM folded), a AS (SELECT structure_id FROM folded ORDER BY t_point, structure_id LIMIT (SELECT k FROM k)), b AS (SELECT structure_id FROM folded ORDER BY t_lattice, structure_id LIMIT (SELECT k FROM k))"


@query("x2_intersect", f"{_TOPS} SELECT structure_id FROM a INTERSECT SELECT structure_id FROM b")
def x2(spark, d):
    a, b = _tops(spark, d)
    return a.intersect(b)


@query("x3_except", f"{_TOPS} SELECT structure_id FROM a EXCEPT SELECT structure_id FROM b")
def x3(spark, d):
    a, b = _tops(spark, d)
    return a.exceptAll(b)


@query("x4_unique_histograms", f"WITH {sql.d1('order')}, s AS (SELECT structure_id, string_agg(cell || ':' || n, ' ' ORDER BY cell) AS h FROM histogram GROUP BY 1) SELECT count(DISTINCT h) AS histograms FROM s")
def x4(spark, d):
    s = encode.to_sparse(m15_orders(spark, d)).select("cells", "counts").dropDuplicates()
    return s.agg(F.count("*").alias("histograms"))


# ---- functions ----------------------------------------------------------------------------------


@query("f1_math", f"WITH {sql.atoms()} SELECT structure_id, atom_id, round(sqrt(abs(x)) + cos(y) + exp(-abs(w)) + cbrt(abs(x)) + ln(1 + abs(y)) + sign(w) + floor(x) + atan2(y, w) + acos(y / 100) + power(abs(x), 1.5e0), 6) AS v FROM atoms")
def f1(spark, d):
    v = F.sqrt(F.abs("x")) + F.cos("y") + F.exp(-F.abs("w")) + F.cbrt(F.abs("x")) + F.log(1 + F.abs("y")) + F.signum("w") + F.floor("x") + F.atan2("y", "w") + F.acos(F.col("y") / 100) + F.pow(F.abs("x"), 1.5)
    return _atoms(spark, d).select("structure_id", "atom_id", F.round(v, 6).alias("v"))


@query("f2_bits", f"WITH {_SUP} SELECT structure_id, cell, cell & 255 AS low, cell | 1 AS odd, xor(cell, 4369) AS flipped, cell >> 8 AS high, CAST(bit_count(cell) AS INT) AS ones, lpad(CAST(to_base(cell, 2) AS VARCHAR), 16, '0') AS bits FROM histogram")
def f2(spark, d):
    c = F.col("cell")
    return _cells(spark, d, "supplier").select("structure_id", "cell", c.bitwiseAND(255).alias("low"), c.bitwiseOR(1).alias("odd"), c.bitwiseXOR(4369).alias("flipped"), F.shiftright(c, 8).alias("high"), F.bit_count(c).alias("ones"), F.lpad(F.bin(c), 16, "0").alias("bits"))


@query("f3_dates", "SELECT event_id, CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INT) AS day, CAST(extract('hour' FROM ts) AS INT) AS hour, strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M') AS hour_start, epoch_us(ts) // 1000000 AS unix FROM events")
def f3(spark, d):
    return load(spark, d, "events").select("event_id", F.datediff("ts", F.lit("2024-01-01").cast("date")).alias("day"), F.hour("ts").alias("hour"), F.date_format(F.date_trunc("hour", "ts"), "yyyy-MM-dd HH:mm").alias("hour_start"), F.unix_timestamp("ts").alias("unix"))


@query("f4_strings", r"SELECT doc_id, length(text) AS chars, len(string_split(text, ' ')) AS parts, length(regexp_replace(text, '[^a-z]+', '', 'g')) AS letters, substr(lower(text), 1, 12) AS head FROM documents")
def f4(spark, d):
    t = F.col("text")
    return load(spark, d, "documents").select("doc_id", F.length(t).cast("bigint").alias("chars"), F.size(F.split(t, " ")).cast("bigint").alias("parts"), F.length(F.regexp_replace(t, "[^a-z]+", "")).cast("bigint").alias("letters"), F.substring(F.lower(t), 1, 12).alias("head"))


@query("f5_arrays", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE) * 2)), 5) + 0e0 AS doubled, len(list_filter(embedding, lambda v: v > 0)) AS positive, round(CAST(list_max(embedding) AS DOUBLE), 6) AS top, round(list_sum(list_transform(embedding[1:4], lambda v: CAST(v AS DOUBLE))), 6) + 0e0 AS head FROM embeddings")
def f5(spark, d):
    add = lambda a: F.aggregate(a, F.lit(0.0), lambda s, v: s + v)
    e = F.col("embedding")
    return load(spark, d, "embeddings").select("vec_id", (F.round(add(F.transform(e, lambda v: v.cast("double") * 2)), 5) + F.lit(0.0)).alias("doubled"), F.size(F.filter(e, lambda v: v > 0)).cast("bigint").alias("positive"), F.round(F.array_max(e).cast("double"), 6).alias("top"), (F.round(add(F.transform(F.slice(e, 1, 4), lambda v: v.cast("double"))), 6) + F.lit(0.0)).alias("head"))


@query("f6_maps", f"WITH {_SUP} SELECT structure_id, count(*) AS bins, max(n) FILTER (cell = c0) AS first_n FROM histogram JOIN (SELECT structure_id, min(cell) AS c0 FROM histogram GROUP BY 1) USING (structure_id) GROUP BY 1")
def f6(spark, d):
    s = encode.to_sparse(_cells(spark, d, "supplier"))
    return s.select("structure_id", F.cardinality("bins").cast("bigint").alias("bins"), F.element_at("bins", F.array_min(F.map_keys("bins"))).alias("first_n"))


@query("f7_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
def f7(spark, d):
    return load(spark, d, "events").select("event_id", F.from_json("props", "k int").getField("k").alias("k"))


@query("f8_structs", f"WITH {sql.atoms()} SELECT structure_id, atom_id, i, round(CASE i WHEN 0 THEN x WHEN 1 THEN y ELSE w END, 6) + 0e0 AS v FROM atoms, (SELECT CAST(unnest(range(3)) AS INT) AS i)")
def f8(spark, d):
    rows = F.array(*(F.struct(F.lit(i).alias("i"), F.col(c).alias("v")) for i, c in enumerate("xyw")))
    return _rounded(_atoms(spark, d).select("structure_id", "atom_id", F.inline(rows)), 6, "v")


_UNIT = "list_transform(embedding, lambda v: CAST(v AS DOUBLE))"


@query("f9_vector_functions", f"WITH e AS (SELECT vec_id, {_UNIT} AS v FROM embeddings), f AS (SELECT v AS f FROM e WHERE vec_id = 0) SELECT vec_id, round(list_dot_product(v, f), 5) + 0e0 AS dot, round(sqrt(list_dot_product(v, v)), 5) AS norm, round(list_cosine_similarity(v, f), 5) + 0e0 AS cosine, round(list_distance(v, f), 4) AS distance FROM e, f")
def f9(spark, d):
    e = load(spark, d, "embeddings").select("vec_id", F.col("embedding").alias("v"))
    one = e.where("vec_id = 0").select(F.col("v").alias("f"))
    j = e.join(F.broadcast(one))
    return _rounded(_rounded(j.select("vec_id", vectors.dot("v", "f").alias("dot"), vectors.norm("v").alias("norm"), vectors.cosine("v", "f").alias("cosine"), vectors.euclidean("v", "f").alias("distance")), 5, "dot", "norm", "cosine"), 4, "distance")


@query("f10_nearest_exact", f"WITH e AS (SELECT vec_id, {_UNIT} AS v FROM embeddings), s AS (SELECT q.vec_id AS qid, p.vec_id AS pid, round(list_dot_product(q.v, p.v), 6) AS similarity FROM e q, e p WHERE q.vec_id % 50 = 0 AND q.vec_id <> p.vec_id), r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY similarity DESC, pid) AS rank FROM s) SELECT qid, CAST(rank AS INT) AS rank, pid, similarity FROM r WHERE rank <= 5")
def f10(spark, d):
    e = load(spark, d, "embeddings")
    return joins.knn_exact(e.where("vec_id % 50 = 0").select(F.col("vec_id").alias("qid"), F.col("embedding").alias("vec")), e.select(F.col("vec_id").alias("pid"), F.col("embedding").alias("vec")), 5)


def _queries_and_points(spark, d):
    e = load(spark, d, "embeddings")
    return e.where("vec_id % 50 = 0").select(F.col("vec_id").alias("qid"), F.col("embedding").alias("vec")), e.select(F.col("vec_id").alias("pid"), F.col("embedding").alias("vec"))


@query("f11_nearest_by_curve")
def f11(spark, d):
    """Neighbours by curves at a recall of 0.9 or more; the exact way where no number of curves reaches it."""
    queries, points = _queries_and_points(spark, d)
    return joins.knn_measured(points, queries)[0]


@query("f11_recall", "SELECT count(*) AS queries, TRUE AS enough FROM embeddings WHERE vec_id % 50 = 0")
def f11r(spark, d):
    """Queries answered by the search above and whether it finds nine in ten of the brute-force neighbours."""
    queries, points = _queries_and_points(spark, d)
    found, _, _ = joins.knn_measured(points, queries)
    truth = written(joins.knn_exact(queries, points, 5), "truth")
    hits = found.join(truth, ["qid", "pid"], "left_semi").count()
    return truth.agg(F.countDistinct("qid").alias("queries"), (F.lit(float(hits)) >= F.count("*") * 0.9).alias("enough"))


@query("f12_logistic", f"WITH {sql.atoms()} SELECT structure_id, atom_id, round(1 / (1 + exp(-x / 10)), 9) AS v FROM atoms")
def f12(spark, d):
    return _atoms(spark, d).select("structure_id", "atom_id", F.round(vectors.logistic(F.col("x") / 10), 9).alias("v"))


# ---- streaming ----------------------------------------------------------------------------------


def _stream(spark, d):
    from ..streaming.streams import stream_events

    return stream_events(spark, d)


@query("st1_stateless_encode", f"WITH {sql.EVENT_CELLS} SELECT event_id, structure_id, cell FROM event_cells")
def st1(spark, d):
    from ..streaming.streams import drained, encoded_events

    return drained(encoded_events(_stream(spark, d))).select("event_id", "structure_id", "cell")


@query("st2_tumbling_windows", "SELECT user_id, strftime(time_bucket(INTERVAL 6 HOUR, ts), '%Y-%m-%d %H:%M') AS start, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def st2(spark, d):
    from ..streaming.streams import drained, windowed

    return _started(drained(windowed(_stream(spark, d), "6 hours"), "complete")).select("user_id", "start", "n", "total")


def _started(df: DataFrame) -> DataFrame:
    return df.withColumn("start", F.date_format("start_ts", "yyyy-MM-dd HH:mm"))


@query("st3_sliding_windows", "SELECT user_id, strftime(time_bucket(INTERVAL 1 HOUR, ts) - i * INTERVAL 1 HOUR, '%Y-%m-%d %H:%M') AS start, count(*) AS n, round(sum(value), 4) AS total FROM events, range(2) t(i) GROUP BY 1, 2")
def st3(spark, d):
    from ..streaming.streams import drained, windowed

    return _started(drained(windowed(_stream(spark, d), "2 hours", "1 hour"), "complete")).select("user_id", "start", "n", "total")


@query("st4_session_windows", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM g) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M') AS start, count(*) AS n FROM s GROUP BY user_id, s")
def st4(spark, d):
    from ..streaming.streams import drained, sessions

    return _started(drained(sessions(_stream(spark, d)), "complete")).select("user_id", "start", "n")


@query("st5_late_rows", "SELECT count(DISTINCT (date_trunc('hour', ts), user_id)) AS late FROM events WHERE ts < TIMESTAMP '2024-01-10' AND (SELECT max(ts) FROM events) > TIMESTAMP '2024-01-20'")
def st5(spark, d):
    """Groups of rows that came too late, as the state operator counts them: rows are first added up by window and user."""
    from ..streaming.streams import late_rows

    e = load(spark, d, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), "value")
    new, old = e.where("ts >= '2024-01-20'"), e.where("ts < '2024-01-10'")
    n = late_rows(spark, lambda s: s.groupBy(F.window("ts", "1 hour"), "user_id").count(), new, old)
    return spark.createDataFrame([(n,)], "late bigint")


@query("st6_deduplicated", "SELECT DISTINCT event_id, user_id FROM events")
def st6(spark, d):
    from ..streaming.streams import deduplicated, drained

    s = _stream(spark, d)
    return drained(deduplicated(s.union(s))).select("event_id", "user_id")


@query("st7_running_histogram", f"WITH {sql.EVENT_CELLS} SELECT structure_id, cell, count(*) AS n FROM event_cells GROUP BY 1, 2")
def st7(spark, d):
    from ..streaming.streams import drained, running_histogram

    return drained(running_histogram(_stream(spark, d)), "complete")


@query("st8_frequency_upkeep", f"WITH {sql.EVENT_CELLS} SELECT cell, count(DISTINCT structure_id) AS df FROM event_cells GROUP BY 1")
def st8(spark, d):
    from ..streaming.streams import frequency_upkeep

    return frequency_upkeep(spark, _stream(spark, d))[0]


@query("st9_scored_stream", f"WITH {sql.EVENT_CELLS}, w AS (SELECT cell, ln((SELECT count(DISTINCT structure_id) FROM event_cells) / count(DISTINCT structure_id)) AS idf FROM event_cells GROUP BY 1) SELECT event_id, cell, round(idf, 6) + 0e0 AS idf FROM event_cells JOIN w USING (cell)")
def st9(spark, d):
    from ..streaming.streams import drained, running_histogram, scored

    t = running_histogram(load(spark, d, "events"))
    weights = written(lsi.idf(lsi.doc_frequency(t), t.select("structure_id").distinct().count()), "weights")
    return _rounded(drained(scored(_stream(spark, d), weights.select("cell", "idf"))), 6, "idf")


@query("st10_click_then_purchase", "SELECT c.user_id, c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR")
def st10(spark, d):
    from ..streaming.streams import click_then_purchase, drained

    return drained(click_then_purchase(_stream(spark, d)))


@query("st11_replay_equality", f"WITH {sql.EVENT_CELLS} SELECT structure_id, cell, count(*) AS first, count(*) AS second FROM event_cells GROUP BY 1, 2")
def st11(spark, d):
    """The same stream run twice: events by user and cell in each run, against SQL's over the table."""
    from ..streaming.streams import drained, encoded_events

    one, two = (drained(encoded_events(_stream(spark, d))).withColumn("run", F.lit(i)) for i in range(2))
    return one.unionByName(two).groupBy("structure_id", "cell").agg(F.count_if(F.col("run") == 0).alias("first"), F.count_if(F.col("run") == 1).alias("second"))


# ---- user-defined surface -----------------------------------------------------------------------


@query("u1_sql_function", f"WITH {_D1} SELECT structure_id, cell, n FROM histogram")
def u1(spark, d):
    udfs.register_sql_functions(spark)
    s = encode.quantize(encode.within_sphere(encode.spherical_atoms(_atoms(spark, d, ids=False))), encode.spherical_grid())
    return s.select("structure_id", F.expr("morton4(q0, q1, q2, q3)").alias("cell")).groupBy("structure_id", "cell").agg(F.count("*").alias("n"))


@query("u2_vectorised_eigenvalues", f"WITH {sql.atoms()}, {sql.CENTERED}, {sql.MOMENTS}, {sql.AXES} SELECT structure_id, round(e3, 4) AS e3 FROM axes")
def u2(spark, d):
    i = geometry.inertia(_atoms(spark, d, ids=False))
    return i.select("structure_id", F.round(udfs.eigenvalues_udf()("ixx", "iyy", "iww", "ixy", "ixw", "iyw"), 4).alias("e3"))


@query("u3_grouped_map", f"WITH {sql.atoms('supplier')}, {sql.CENTERED} SELECT structure_id, round(sqrt(sum(mass * (x * x + y * y + w * w)) / sum(mass)), 6) AS gyration FROM centered GROUP BY 1")
def u3(spark, d):
    import pandas as pd

    def one(t):
        p, m = t[["x", "y", "w"]].to_numpy(), t["mass"].to_numpy()
        p = p - (p * m[:, None]).sum(0) / m.sum()
        return pd.DataFrame({"structure_id": [t["structure_id"].iloc[0]], "gyration": [float((m * (p**2).sum(1)).sum() / m.sum()) ** 0.5]})

    out = _atoms(spark, d, "supplier", ids=False).groupBy("structure_id").applyInPandas(one, "structure_id bigint, gyration double")
    return _rounded(out, 6, "gyration")


@query("u4_vector_mean", "SELECT label, CAST(i AS INT) AS i, round(avg(CAST(embedding[i + 1] AS DOUBLE)), 6) + 0e0 AS mean FROM (SELECT label, embedding, unnest(range(64)) AS i FROM embeddings) GROUP BY 1, 2")
def u4(spark, d):
    m = load(spark, d, "embeddings").select("label", F.col("embedding").cast("array<double>").alias("v")).groupBy("label").agg(udfs.mean_vector_udf()("v").alias("m"))
    return _rounded(m.select("label", F.posexplode("m").alias("i", "mean")), 6, "mean")


@query("u5_table_function_images", "SELECT CAST(a AS INT) AS na, CAST(b AS INT) AS nb, CAST(c AS INT) AS nc, count(*) AS n, CAST(sum(s_suppkey) AS BIGINT) AS keys FROM supplier, range(-2, 3) t(a), range(-2, 3) u(b), range(-2, 3) v(c) WHERE greatest(abs(a), abs(b), abs(c)) <= s_nationkey % 3 GROUP BY ALL")
def u5(spark, d):
    """Images of every supplier, none to two cells each way by its nation: the table function joined to the table's rows."""
    s = load(spark, d, "supplier").select("s_suppkey", F.pmod("s_nationkey", F.lit(3)).alias("reach"))
    images = s.lateralJoin(udfs.image_offsets_udtf()(F.col("reach").outer()))
    return images.groupBy("na", "nb", "nc").agg(F.count("*").alias("n"), F.sum("s_suppkey").alias("keys"))


@query("u5_table_function_ranges", f"""WITH box AS (SELECT {sql.interleaved(['x', 'y', 'w'], 4)} AS c FROM (SELECT unnest(range(2, 8)) AS x), (SELECT unnest(range(2, 8)) AS y), (SELECT unnest(range(2, 8)) AS w)),
runs AS (SELECT c, c - row_number() OVER (ORDER BY c) AS run FROM box) SELECT min(c) AS first, max(c) AS last FROM runs GROUP BY run""")
def u5r(spark, d):
    """Index ranges of a box that lies across the curve's octants, against the runs of its cells in SQL."""
    return udfs.box_ranges_udtf()(F.lit(2), F.lit(7), F.lit(4))


@query("u6_iterator_map", f"WITH {_SUP} SELECT CAST(sum(n) AS BIGINT) AS atoms FROM histogram")
def u6(spark, d):
    import pyarrow as pa
    import pyarrow.compute as pc

    def total(batches):
        n = sum(pc.sum(b.column(0)).as_py() or 0 for b in batches)
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], ["n"])

    return _cells(spark, d, "supplier").select("n").mapInArrow(total, "n bigint").agg(F.sum("n").alias("atoms"))


@query("u7_descriptor_plugin", f"WITH {sql.atoms()} SELECT structure_id, round(sum(z * 1.5e0), 6) AS total FROM atoms GROUP BY 1")
def u7(spark, d):
    registry = dict(descriptors.REGISTRY) | {"scaled": lambda a: descriptors.descriptor_custom(a, lambda: F.col("z") * 1.5)}
    return registry["scaled"](_atoms(spark, d, ids=False)).groupBy("structure_id").agg(F.round(F.sum("descriptor"), 6).alias("total"))


@query("u8_observed_metrics", f"WITH {sql.atoms()}, {sql.POSE} SELECT count(*) FILTER (r <= 30) AS kept, count(*) FILTER (r > 30) AS dropped FROM spherical")
def u8(spark, d):
    s = encode.spherical_atoms(_atoms(spark, d, ids=False))
    watched, seen = udfs.observed(s, "sphere", dropped=F.count_if(F.col("r") > 30))
    kept = encode.within_sphere(watched, 30.0).agg(F.count("*").alias("kept")).collect()[0].kept
    return spark.createDataFrame([(kept, seen.get["dropped"])], "kept bigint, dropped bigint")
