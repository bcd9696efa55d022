"""What was published of the seventy queries, by the SQL that computes every sketch anew (Spark's results are held against it)."""

import duckdb

import __spark_entry__ as E


def test_variants_by_size(sf):
    con = duckdb.connect()
    for t in ("customer", "supplier", "part", "orders", "lineitem", "events"):
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    out = con.execute(E.oracle_sql()["rf_by_variant_and_size"])
    names = [c[0] for c in out.description]
    rows = {(r["variant"], r["preset"]): r for r in (dict(zip(names, x, strict=True)) for x in out.fetchall())}
    assert len(rows) == 8
    for preset in ("large", "small"):
        own = {v: rows[v, preset] for v in ("chained", "hybrid", "bloomattr", "plain")}
        assert min(own, key=lambda v: own[v]["bits"]) == "bloomattr" == max(own, key=lambda v: own[v]["fpr_binned"])
        assert max(own, key=lambda v: own[v]["bits"]) == "plain" and own["bloomattr"]["bits"] < own["hybrid"]["bits"] < own["chained"]["bits"]
        assert all(r["rf_exact"] <= r["rf_sketch"] < r["rf_keyonly"] for r in own.values())
    assert all(rows[v, "large"]["fpr_binned"] < rows[v, "small"]["fpr_binned"] and rows[v, "small"]["bits"] < 0.7 * rows[v, "large"]["bits"] for v in own)
    assert rows["chained", "large"]["fpr_binned"] < 0.02
