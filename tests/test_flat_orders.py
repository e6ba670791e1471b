"""Orders whose three atoms lie on a plane: where an atom's bin hangs on the last digits of the moments."""

import datetime

import duckdb
from structcurve.plans import catalogue, methods

LINE = "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp"


def test_an_atom_of_the_plane_stays_in_its_bin(spark, tmp_path):
    rows = [
        (33852, 10934, 93, 4, 5.0, 7209.73, 0.02, 0.08, "R", "O", datetime.datetime(1997, 3, 9)),
        (33852, 4856, 653, 7, 34.0, 66480.32, 0.09, 0.07, "A", "F", datetime.datetime(1999, 2, 27)),
        (33852, 19420, 204, 2, 48.0, 95207.88, 0.09, 0.0, "A", "O", datetime.datetime(2000, 3, 5)),
    ]
    spark.createDataFrame(rows, LINE).coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet/*.parquet'")
    want = sorted(con.execute(catalogue.ORACLES["m15_encode_d1_orders"]).fetchall())
    assert sorted(map(tuple, methods.m15_orders(spark, str(tmp_path)).select("structure_id", "cell", "n").collect())) == want
