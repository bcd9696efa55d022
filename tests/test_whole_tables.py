"""Surrounding operators over whole tables, with DuckDB beside them."""

import duckdb
import pytest

import __spark_entry__ as E

WHOLE = {"project_expr": "lineitem", "fn_bits": "orders", "fn_date": "orders", "fn_json": "events", "join_outer": None}


@pytest.mark.parametrize("name", WHOLE)
def test_every_row_is_computed(spark, sf, name):
    con = duckdb.connect()
    for t in ("lineitem", "orders", "events", "customer"):
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    out = con.execute(E.oracle_sql()[name])
    names = [c[0] for c in out.description]
    want = sorted(out.fetchall(), key=repr)
    assert sorted((tuple(r[c] for c in names) for r in E.queries()[name](spark, sf).collect()), key=repr) == want
    if WHOLE[name]:
        assert len(want) == con.execute(f"select count(*) from {WHOLE[name]}").fetchone()[0]
    else:
        assert dict((w[0], w[2]) for w in want)["left"] == con.execute("select count(c_nationkey) from customer").fetchone()[0]
