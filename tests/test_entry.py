import pathlib
import re

import __spark_entry__ as entry


def test_contract(spark):
    queries, oracles = entry.queries(), entry.oracle_sql()
    assert set(oracles) <= set(queries) and len(queries) > 200
    assert entry.entry(spark).count() > 0


def test_engine_does_not_need_the_text_operators():
    root = pathlib.Path(entry.__file__).parent / "structcurve"
    for path in root.rglob("*.py"):
        if "llm" not in path.parts:
            assert not re.search(r"(from|import)\s+[\w.]*\bllm\b", path.read_text()), path
