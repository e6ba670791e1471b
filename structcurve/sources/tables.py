"""Readers that turn the given tables into atoms, points and tokens (long form, one row per atom)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Declared schemas: scans never infer, and Parquet prunes to the columns a plan uses.
SCHEMAS = {
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
}

#: Fixed order of event types; a type's code is its place, from 1.
EVENT_KINDS = ("click", "error", "purchase", "signup", "view")
STRUCTURE_KEYS = {"part": "l_partkey", "order": "l_orderkey", "supplier": "l_suppkey"}
_LINE = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table by name; with a declared schema where one is fixed."""
    path = f"{sf_dir}/{name}.parquet"
    return spark.read.schema(SCHEMAS[name]).parquet(path) if name in SCHEMAS and name not in ("lineitem",) else spark.read.parquet(path)


def atoms_from_lineitem(spark: SparkSession, sf_dir: str, by: str = "part", ids: bool = False) -> DataFrame:
    """Atoms ``structure_id, [atom_id,] z, mass, x, y, w`` of parts, orders or suppliers.

    ``ids`` numbers a structure's atoms by all line columns (the order key and line number alone are
    no key); that costs a sort per structure, so only pair joins ask for it.
    """
    line = load(spark, sf_dir, "lineitem")
    key = F.col(STRUCTURE_KEYS[by]).alias("structure_id")
    columns = [
        F.col("l_linenumber").alias("z"),
        F.col("l_linenumber").cast("double").alias("mass"),
        (F.col("l_quantity") - 25.5).alias("x"),
        (F.col("l_extendedprice") / 2100.0 - 25.0).alias("y"),
        (F.datediff("l_shipdate", F.lit("1995-01-01").cast("date")) / 50.0 - 25.0).alias("w"),
    ]
    if not ids:
        return line.select(key, *columns)
    order = Window.partitionBy(STRUCTURE_KEYS[by]).orderBy(*_LINE)
    return line.select(key, F.row_number().over(order).alias("atom_id"), *columns)


def atoms_from_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Event points of users: ``structure_id, kind, hour, value, k`` (type code, hour of day, value, JSON field)."""
    e = load(spark, sf_dir, "events")
    return event_points(e)


def event_points(events: DataFrame) -> DataFrame:
    """The same for any frame of events, streams included; an unknown type has code 0."""
    code = F.coalesce(F.array_position(F.array(*(F.lit(k) for k in EVENT_KINDS)), F.col("event_type")), F.lit(0)).cast("int")
    return events.select("event_id", "ts", F.col("user_id").alias("structure_id"), code.alias("kind"), F.hour("ts").alias("hour"), "value", F.coalesce(F.get_json_object("props", "$.k").cast("double"), F.lit(0.0)).alias("k"))


def points_from_embeddings(spark: SparkSession, sf_dir: str, n_dims: int = 4) -> DataFrame:
    """``vec_id, point, c0..``: each vector cut into points of ``n_dims`` numbers."""
    e = load(spark, sf_dir, "embeddings")
    cut = F.transform(F.sequence(F.lit(0), F.floor(F.size("embedding") / n_dims).cast("int") - 1), lambda i: F.slice("embedding", i * n_dims + 1, n_dims))
    rows = e.select("vec_id", F.posexplode(cut).alias("point", "p"))
    return rows.select("vec_id", "point", *(F.get("p", F.lit(i)).cast("double").alias(f"c{i}") for i in range(n_dims)))


def tokens(df: DataFrame, id_col: str, text_col: str = "text") -> DataFrame:
    """``structure_id, token, n``: lower-case runs of letters and their counts."""
    words = F.filter(F.split(F.lower(F.coalesce(text_col, F.lit(""))), "[^\\p{L}]+"), lambda w: w != "")
    return df.select(F.col(id_col).alias("structure_id"), F.explode(words).alias("token")).groupBy("structure_id", "token").agg(F.count("*").alias("n"))


def html_text(df: DataFrame, html_col: str = "html") -> DataFrame:
    """Adds ``plain``: the page without scripts, styles, comments and tags, white space folded."""
    bare = F.regexp_replace(F.coalesce(html_col, F.lit("")), "(?s)<script.*?</script>|<style.*?</style>|<!--.*?-->|<[^>]*>", " ")
    return df.withColumn("plain", F.trim(F.regexp_replace(bare, "\\s+", " ")))


def random_structures(spark: SparkSession, structures: int, atoms: int, seed: int = 1) -> DataFrame:
    """The random atoms of structures 0, 1, ..."""
    return random_atoms(spark.range(structures).withColumnRenamed("id", "structure_id"), atoms, seed)


def random_atoms(structures: DataFrame, atoms: int, seed: int = 1) -> DataFrame:
    """``atoms`` atoms a structure at reproducible positions in a cube of side 40, by arithmetic on the structure's and the atom's number."""
    m = 1 << 31
    step = lambda c, salt: F.pmod(F.pmod(c * F.lit(1103515245) + F.lit(12345 + salt), F.lit(m)) * F.lit(1103515245) + F.lit(12345), F.lit(m))
    unit = lambda salt: F.floor(step(F.col("id") + F.lit(seed), salt) / 65536) / F.lit(32768.0) * 40.0 - 20.0
    rows = structures.select("structure_id", F.explode(F.sequence(F.lit(1), F.lit(atoms))).alias("atom_id")).withColumn("id", F.col("structure_id") * atoms + F.col("atom_id") - 1)
    z = (F.pmod(F.floor(step(F.col("id") + F.lit(seed), 7) / 65536), F.lit(4)) + 5).cast("int")
    return rows.select("structure_id", "atom_id", z.alias("z"), z.cast("double").alias("mass"), unit(1).alias("x"), unit(2).alias("y"), unit(3).alias("w"))


def lattice_of(structures: DataFrame, a: float = 50.0) -> DataFrame:
    """The same cubic cell for every structure: ``structure_id, lattice`` (three vectors)."""
    cell = F.array(*(F.array(*(F.lit(a if i == j else 0.0) for j in range(3))) for i in range(3)))
    return structures.select("structure_id").distinct().withColumn("lattice", cell)
