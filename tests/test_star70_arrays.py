"""The seventy queries on all sketches at once: rows are dealt once, whatever the number of sketches."""

import duckdb
import numpy as np
import pytest

import __spark_entry__ as E
from keysieve.config import SMALL
from keysieve.operators import arrays, chains
from keysieve.operators import pairs as P
from keysieve.queries import star_queries
from keysieve.workloads import star70, star70_arrays
from keysieve.workloads.fixtures import relation, spec_for

LITTLE = SMALL.with_(hash_family="portable", m=64, l_max=3)


@pytest.fixture(scope="module")
def odd(sf, tmp_path_factory):
    """The tables with null keys and values, numbers below zero, a key of many lines, lines without orders, orders without lines."""
    path, con = tmp_path_factory.mktemp("odd"), duckdb.connect()
    for t in ("customer", "supplier", "part", "events"):
        con.execute(f"copy (select * from '{sf}/{t}.parquet') to '{path}/{t}.parquet' (format parquet)")
    con.execute(
        f"""copy (select case when i % 17 = 0 then null when i % 19 = 0 then 5 when i % 23 = 0 then l_orderkey + 100000 when i % 71 = 0 then -l_orderkey else l_orderkey end as l_orderkey,
        case when i % 7 = 0 then null else l_partkey end as l_partkey, case when i % 5 = 0 then null when i % 11 = 0 then -l_suppkey else l_suppkey end as l_suppkey,
        case when i % 13 = 0 then null else l_linenumber end as l_linenumber, case when i % 6 = 0 then null else l_quantity end as l_quantity, case when i % 8 = 0 then null else l_discount end as l_discount,
        case when i % 9 = 0 then null when i % 10 = 0 then '' else l_linestatus end as l_linestatus, * exclude (i, l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_discount, l_linestatus)
        from (select *, row_number() over () as i from '{sf}/lineitem.parquet')) to '{path}/lineitem.parquet' (format parquet)"""
    )
    con.execute(
        f"""copy (select case when i % 17 = 0 then null when i % 71 = 0 then -o_orderkey else o_orderkey end as o_orderkey, case when i % 6 = 0 then null else o_orderstatus end as o_orderstatus,
        case when i % 7 = 0 then null when i % 5 = 0 then o_orderdate - interval 9 year else o_orderdate end as o_orderdate, * exclude (i, o_orderkey, o_orderstatus, o_orderdate)
        from (select *, row_number() over () as i from '{sf}/orders.parquet') where i % 3 > 0) to '{path}/orders.parquet' (format parquet)"""
    )
    return str(path)


def _by_sql(name, d):
    con = duckdb.connect()
    for t in ("customer", "supplier", "part", "orders", "lineitem", "events"):
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet'")
    out = con.execute(E.oracle_sql()[name])
    names = sorted(c[0] for c in out.description if c[0] != "load")  # ties of the sixth place are rounded otherwise
    at = [[c[0] for c in out.description].index(n) for n in names]
    return sorted(tuple(float(r[i]) if isinstance(r[i], float) else r[i] for i in at) for r in out.fetchall())


def _by_spark(spark, name, d):
    return sorted(tuple(r[c] for c in sorted(r.asDict()) if c != "load") for r in E.queries()[name](spark, d).collect())


@pytest.mark.parametrize("name", ["rf_by_variant_and_size", "star70_shapes", "star70_small", *(f"star70_{v}_small" for v in ("chained", "hybrid", "bloomattr", "plain"))])
def test_odd_rows_equal_their_sql(spark, odd, name):  # F1
    assert _by_spark(spark, name, odd) == _by_sql(name, odd)


def test_all_variants_and_sizes_take_few_jobs(spark, sf):  # F1
    star_queries._made.clear()
    star70._counted.clear()
    spark.sparkContext.setJobGroup("all sizes", "")
    assert len(E.queries()["rf_by_variant_and_size"](spark, sf).collect()) == 8
    jobs = len(spark.sparkContext.statusTracker().getJobIdsForGroup("all sizes"))
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert jobs < 100


def test_rows_are_dealt_once_for_all_sketches(spark, sf):  # F1
    bases = [star70.specs(LITTLE.with_(variant=v, key_bits=k)) for v in ("chained", "hybrid", "bloomattr", "plain") for k in (7, 12)]
    plan = star70_arrays.instances(spark, sf, star70_arrays.by_prints(spark, sf), bases)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning(kappa") == 1 and plan.count("Exchange hashpartitioning") == 2


def test_packed_rows_are_the_rows(spark, odd):  # F1
    rows, bases = star70_arrays.by_prints(spark, odd), [star70.specs(LITTLE), star70.specs(LITTLE.with_(variant="hybrid", key_bits=12))]
    slices = star70_arrays.packed(rows, 50)
    assert slices.filter("blob is not null").count() > 100 and star70_arrays.duplicates(slices) == star70_arrays.duplicates(rows)
    one, two = (sorted(map(tuple, star70_arrays.instances(spark, odd, x, bases).collect())) for x in (rows, slices))
    assert one == two and one


@pytest.mark.parametrize("variant", ["chained", "hybrid", "bloomattr", "plain"])
def test_arrays_hold_what_builders_build(spark, sf, variant):  # F1
    spec = spec_for("supp", LITTLE, small_values=True, m=16, key_bits=4, variant=variant)
    part = star70_arrays.Part(star70_arrays.by_prints(spark, sf).toArrow())
    slot, kappas = part.slots(spec)
    of = part.distinct("supp")[0]
    entries = P.build(relation(spark, sf, "supp"), "k", spec).entries
    if variant == "bloomattr":
        at, masks = arrays.bloom_entries(slot[of], part.masks("supp", spec))
        assert sorted(zip(at % 16, kappas[at // 16], masks, strict=True)) == sorted((r["pair_id"], r["kappa"], r["mask"]) for r in entries.collect())
        return
    make = (lambda *a: arrays.chained_entries(*a, kappas, spec)) if variant == "chained" else (lambda *a: arrays.vectors(*a, len(kappas) * spec.m, spec))
    at, (a, b) = make(slot[of], part.prints("supp", spec))
    found = sorted(zip(at % 16, kappas[at // 16], a, b, strict=True))
    if variant == "hybrid":
        entries, counts = P.vectors(relation(spark, sf, "supp"), "k", spec), entries
        masks = arrays.print_masks([a, b], len(at), spec)
        whole = {}
        for s, m in zip(at.tolist(), masks.tolist(), strict=True):
            whole[s] = whole.get(s, 0) | m
        assert sorted((s % 16, kappas[s // 16], m) for s, m in whole.items() if (at == s).sum() > spec.d) == sorted((r["pair_id"], r["kappa"], r["mask"]) for r in counts.filter("is_bloom").collect())
    assert found == sorted((r["pair_id"], r["kappa"], r["a_0"], r["a_1"]) for r in entries.collect())


def test_rounds_over_numbers_equal_those_over_columns():  # F1
    draw, kappas = np.random.default_rng(5), np.arange(8)
    for d, hops in ((3, 4), (2, 3), (1, 1)):
        spec = SMALL.with_(hash_family="portable", m=16, d=d, l_max=hops)
        pair, code = draw.integers(0, 8 * 16, 900), draw.integers(-1, 40, 900)
        found = chains.settled(pair, code, np.ones(900, np.int64), kappas, spec)
        far = chains.settled(pair, code * (1 << 55), np.ones(900, np.int64), kappas, spec)  # beyond what one number holds
        assert sorted(zip(*found, strict=True)) == sorted(zip(far[0], far[1] >> 55, far[2], strict=True))


def test_other_keys_go_by_plans(spark, sf, monkeypatch):  # F1
    name, want = "star70_bloomattr_small", _by_sql("star70_bloomattr_small", sf)
    assert _by_spark(spark, name, sf) == want
    for made in (star_queries._made, star70._counted):
        made.clear()
    monkeypatch.setattr(star70_arrays, "whole", lambda *a: False)
    monkeypatch.setattr(star70_arrays, "by_prints", lambda *a: pytest.fail("arrays of what is no number"))
    assert _by_spark(spark, name, sf) == want


def test_prints_without_lines_or_orders(spark, sf):  # F1
    rows, told = star70_arrays.by_prints(spark, sf).toArrow(), star70._told(spark, sf)
    bases = [star70.specs(LITTLE.with_(variant=v)) for v in ("chained", "hybrid", "bloomattr", "plain")]
    is_order = rows["code"].to_numpy() >> 56 == 1
    for some in (is_order, ~is_order):
        (found,) = star70_arrays.counter(told, star70._fields(told), bases)(iter(rows.filter(some).to_batches()))
        assert sum(found.column("m_pred").to_pylist()) > 0 == sum(found.column("m_exact").to_pylist())
