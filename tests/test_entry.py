"""The driver's contract on the smallest tables, with DuckDB beside it."""

import importlib
import math
import sys

import duckdb
import pytest

import __spark_entry__ as E

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = ["chained_probe_eq", "hybrid_probe_eq", "bloomattr_probe_eq", "star_example3", "star_join_result", "cooccurrence_gap", "range_probe_dyadic", "fp_blame", "predicted_entries_bottomk", "stream_tumbling", "udf_contains", "join_asof", "join_interval"]


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, sf, name):
    df = E.queries()[name](spark, sf)
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    out = con.execute(E.oracle_sql()[name])
    names = [c[0] for c in out.description]
    round_ = lambda v: float(f"{v:.9g}") if isinstance(v, float) and not math.isnan(v) else v
    want = sorted((tuple(map(round_, r)) for r in out.fetchall()), key=repr)
    assert sorted((tuple(round_(r[c]) for c in names) for r in df.collect()), key=repr) == want


def test_registry():
    assert set(E.oracle_sql()) <= set(E.queries())


def test_entry(spark):
    assert E.entry(spark).count() == 3


def test_without_the_text_operators(monkeypatch):
    for name in [m for m in sys.modules if m.startswith("keysieve.llm") or m == "corpus_pipeline"]:
        monkeypatch.delitem(sys.modules, name)
    real = importlib.import_module

    def gone(name, *a):
        if name.startswith(("keysieve.llm", "corpus_pipeline")):
            raise ModuleNotFoundError(name=name)
        return real(name, *a)

    monkeypatch.setattr(E.importlib, "import_module", gone)
    names = E.queries()
    assert "star70_large" in names and "pipeline" not in names and not any(n.startswith("op1_") for n in names)
