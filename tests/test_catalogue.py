import duckdb
import pytest

import __spark_entry__ as entry
from annspark import catalogue
from annspark.sources.tables import TABLES

CHECKED = sorted(set(catalogue.ORACLES) & set(catalogue.QUERIES))


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return con


def plain(v):
    return None if v is None else f"{v:.9g}" if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_its_sql(spark, small, duck, name):
    got = catalogue.QUERIES[name](spark, small)
    want = duck.sql(catalogue.ORACLES[name])
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    rows = sorted(([plain(r[c]) for c in cols] for r in got.collect()), key=str)
    assert rows == sorted(([plain(r[want.columns.index(c)]) for c in cols] for r in want.fetchall()), key=str)


def test_entry_answers_exactly_where_it_can(spark):
    rows = entry.entry(spark).collect()
    assert len(rows) == 25 and sum(r.exact for r in rows) >= 10 and set(entry.oracle_sql()) <= set(entry.queries())


def test_plans_prune_and_push_down(spark, small, capsys):
    catalogue.QUERIES["scan_filter"](spark, small).explain("formatted")
    out = capsys.readouterr().out
    assert "PushedFilters: [" in out and "l_comment" not in out and "GreaterThanOrEqual(l_shipdate" in out
    catalogue.QUERIES["exact_knn_emb"](spark, small).explain("formatted")
    assert "CartesianProduct" not in capsys.readouterr().out
