"""Every query with an oracle against DuckDB, on the small tables."""

import duckdb
import pytest

from structcurve.plans import catalogue

DATA = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Checked by their own tests with smaller inputs.
SLOW = {"m19_svd_backends_agree", "m19_svd_mllib"}


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    return con


def normal(frame):
    columns = sorted(frame.columns)

    def text(v):
        if v is None or v != v:
            return "null"
        if isinstance(v, float) and v == int(v):
            return str(int(v))
        return str(v)

    return columns, sorted(tuple(text(v) for v in r) for r in frame[columns].astype(object).itertuples(index=False))


@pytest.mark.parametrize("name", sorted(set(catalogue.ORACLES) - SLOW))
def test_query(spark, duck, name):
    got = normal(catalogue.QUERIES[name](spark, DATA).toPandas())
    want = normal(duck.execute(catalogue.ORACLES[name]).df())
    assert got[0] == want[0]
    assert got[1] == want[1]
