"""What larger tables brought out: work that has to follow the rows, not their products with queries or copies."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from keysieve.config import SMALL, Predicate
from keysieve.functions import md5
from keysieve.operators import chains, places, relational
from keysieve.operators import packed as K
from keysieve.operators import pairs as P
from keysieve.operators import probe as R
from keysieve.plans import sizing
from keysieve.queries import catalog, experiments
from keysieve.workloads import multiset, star70
from keysieve.workloads.fixtures import relation, spec_for

LITTLE = SMALL.with_(hash_family="portable", m=64, l_max=3)


def test_one_row_for_each_group_however_many_queries_it_meets(spark, sf):
    spec = spec_for("qty", LITTLE, small_values=True)
    live = star70.live_masks(spark, sf, "qty", spec)
    assert live.count() == live.select(*P.GROUP).distinct().count()
    told = [t["q"] for t in star70.queries(10, 200) if "qty" in t["satellites"]]
    closed = R.close(P.build(relation(spark, sf, "qty"), "k", spec))
    full = closed.filter("saturated").join(live, P.GROUP).select("l0", "l1").distinct().collect()
    assert [tuple(r) for r in full] == [star70.halves(told)]


def test_sketches_of_the_workload_are_not_cut(spark):
    keys = spark.range(1000).select(F.col("id").alias("k"), F.lit(3).alias("dupes"))
    cut, whole = sizing.shape(keys, LITTLE, shard=500), sizing.shape(keys, LITTLE, shard=None)
    assert cut.shards == 6 and whole.shards == 1 and whole.m * whole.b >= 3000


def test_rounds_by_print_equal_those_by_windows(spark, sf, monkeypatch):
    spec = spec_for("supp", LITTLE, m=16, key_bits=4)
    by_print = P.build_chained(relation(spark, sf, "supp"), "k", spec)
    found = [sorted(map(tuple, by_print.entries.collect())), sorted(map(tuple, by_print.discarded.collect()))]
    monkeypatch.setattr(chains, "suits", lambda s: False)
    by_windows = P.build_chained(relation(spark, sf, "supp"), "k", spec)
    assert found == [sorted(map(tuple, by_windows.entries.collect())), sorted(map(tuple, by_windows.discarded.collect()))] and found[1]


def test_multimap_grows_until_all_values_have_a_place():  # F1
    table = K.CuckooMultiMap(2, 6)
    for i in range(3000):
        table.put_value(i % 100, i)
    assert all(sorted(table.values(k)) == list(range(k, 3000, 100)) for k in range(100))


def test_copies_are_drawn_without_comparing_all_cuts(spark, sf):  # F4
    df = experiments.multiset_input_zipf(spark, sf)
    assert "filter(array" not in df._jdf.queryExecution().executedPlan().toString()
    assert df.filter("copies < 1 or copies > 500").count() == 0


def test_packed_filters_are_made_where_the_groups_are(spark, sf, monkeypatch):  # F5
    monkeypatch.setattr(type(spark.sparkContext), "broadcast", lambda *a: pytest.fail("a filter of the whole sketch on the driver"))
    found = experiments.packed_equals_pairs(spark, sf).collect()
    assert found and all(r["differ"] == 0 and r["passed"] > 0 for r in found)


def test_intervals_end_at_their_microsecond(spark):  # F24
    rows = spark.createDataFrame([(1, "2024-01-01 00:00:00.2", "2024-01-02 00:00:00.2"), (2, "2024-01-01 00:00:00.2", "2024-01-02 00:00:00.9"), (3, "2024-01-01 00:00:00.9", "2024-01-01 00:00:00.2")], "k int, a string, b string")
    a, b = (rows.select("k", F.to_timestamp(c).alias(f"t{c}")) for c in "ab")
    assert [r["k"] for r in relational.interval_join(a, b, "k", "ta", "tb", 1).collect()] == [1]


@pytest.mark.parametrize("name", ["base_linear_probing", "bit_efficiency", "bits_per_item_table", "join_cross", "multiset_constant", "multiset_grid", "multiset_load_factor", "multiset_zipf", "sizing_hash_counts", "sketch_sizes", "star_transitive"])
def test_experiments_read_given_tables(spark, sf, name):  # F27 to F38
    assert catalog.QUERIES[name](spark, sf).inputFiles()


def test_runs_draw_their_keys_by_hash_whatever_the_partitions(spark):
    keys = spark.range(500).select(F.col("id").alias("k"))
    one, many = ({r["run"]: list(r["keys"]) for r in multiset.drawn(keys.repartition(n), 3, 20).collect()} for n in (1, 7))
    assert one == many and all(k == sorted(range(500), key=lambda x, r=r: K.mix(x, r, 17))[:20] for r, k in one.items())


def test_known_predicates_need_no_payloads_along_chains(spark, sf):  # F18
    spec = spec_for("qty", LITTLE, small_values=True)
    sketch, pred = P.build(relation(spark, sf, "qty"), "k", spec), Predicate({"qty": (17,)})
    live = R.derive_key_filter(sketch, pred)
    assert "collect_list" not in live._jdf.queryExecution().executedPlan().toString()
    assert sorted(map(tuple, live.collect())) == sorted(map(tuple, R.derive_key_filter(sketch, pred, R.close(sketch)).collect()))


@pytest.mark.parametrize("variant", ["hybrid", "bloomattr"])
def test_masks_of_a_relation_come_from_one_scan(spark, sf, variant):  # F14
    spec = spec_for("supp", LITTLE, small_values=True, variant=variant)
    live = star70.live_masks(spark, sf, "supp", spec)
    assert live._jdf.queryExecution().optimizedPlan().toString().count("parquet") == 1
    found, told = live.collect(), [t for t in star70.queries(10, 200) if "supp" in t["satellites"]]
    sketch = P.build(relation(spark, sf, "supp"), "k", spec)
    for t in told[:2]:
        kept = R.derive_key_filter(sketch, Predicate({a: (v,) for a, v in t["satellites"]["supp"].items()}))
        half, bit = ("l0", t["q"]) if t["q"] < star70.HALF else ("l1", t["q"] - star70.HALF)
        assert sorted((r["shard"], r["pair_id"], r["kappa"]) for r in found if r[half] >> bit & 1) == sorted(map(tuple, kept.collect()))


def test_batches_are_hashed_as_expressions_hash_rows(spark, sf, monkeypatch):  # F7 to F20
    rows = relation(spark, sf, "hdr")
    odd = spark.createDataFrame([(None, "F", 1), (7, None, None), (10**17, "", -3), (-5, "x", 300)], "k long, status string, bin long")
    rows = rows.select("k", "status", "bin").unionByName(odd)
    spec = spec_for("hdr", LITTLE, small_values=True, shards=3, salt=2)

    def both():
        return [sorted(map(tuple, x.collect())) for x in (P.vectors(rows, "k", spec), P.build_bloomattr(rows, "k", spec).entries)]

    found = both()
    monkeypatch.setattr(places, "suits", lambda *a: False)
    assert found == both() and found[0]
    numbers = np.array([0, 9, 10, 10**17, 10**18, 2**63 - 1])
    assert md5.numbers("key:0:", numbers).tolist() == [md5.h60_of(f"key:0:{n}") for n in numbers.tolist()]
    assert md5.numbers("chain:0:", numbers, numbers[::-1]).tolist() == [md5.h60_of(f"chain:0:{a}:{b}") for a, b in zip(numbers.tolist(), numbers[::-1].tolist(), strict=True)]


def test_chained_masks_of_the_workload_need_one_exchange(spark, sf, monkeypatch):  # F7 to F12, F15
    spec = spec_for("supp", LITTLE, small_values=True, m=16, key_bits=4)
    monkeypatch.setattr(chains, "ROWS", 64)
    live = star70.live_masks(spark, sf, "supp", spec)
    assert live._jdf.queryExecution().executedPlan().toString().count("Exchange ") == 1
    found = sorted(map(tuple, live.collect()))
    monkeypatch.setattr(places, "suits", lambda *a: False)
    monkeypatch.setattr(chains, "suits", lambda *a: False)
    assert found == sorted(map(tuple, star70.live_masks(spark, sf, "supp", spec).collect())) and found


def test_a_hot_group_sends_few_rows(spark):  # F7 to F12, F15
    rows = spark.range(0, 20000, 1, 2).select(F.lit(1).alias("k"), F.col("id").alias("qty"))
    spec = spec_for("qty", LITTLE.with_(attr_bits=12))
    sent = P.arrivals(rows, "k", spec)
    assert sent.count() <= 2 * spec.d * spec.l_max
