"""Queries on sketch building and probing, each with SQL that computes the sketch anew."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..config import LARGE, SMALL, AttrSpec, Predicate
from ..functions import attrs as A
from ..functions import binning, hashing
from ..operators import pairs as P
from ..operators import probe as R
from ..sources import tables as S
from ..workloads.fixtures import relation, relation_sql, spec_for
from . import sql as Q
from .registry import Registry

reg = Registry()
BASE = LARGE.with_(hash_family="portable", m=8192)
TINY = SMALL.with_(hash_family="portable", m=8192)
ORDERS = "select o_orderkey as k from orders"
DISC4 = {"disc": (4,)}


def orders(spark, d):
    return S.table(spark, d, "orders", ["o_orderkey"]).withColumnRenamed("o_orderkey", "k")


# --- hashes and places

ROLES = ("bucket", "key", "pair", "chain", "attr0", "bloom0", "shard")


@reg.add("hash_roles", "select k, " + ", ".join(f"{Q.h('k', r)} as h_{r}" for r in ROLES) + f" from ({ORDERS})")
def hash_roles(spark, d):
    return orders(spark, d).select("k", *(hashing.h60("k", r, 0, "portable").alias(f"h_{r}") for r in ROLES))


@reg.add("locate_pairs", f"select k, cast(kappa as int) as kappa, pair_id from ({Q.located(ORDERS, BASE)})")
def locate_pairs(spark, d):
    return hashing.locate(orders(spark, d), "k", BASE).select("k", "kappa", "pair_id")


KEYONLY = BASE.with_(variant="keyonly")
LINES = "select l_orderkey as k from lineitem"


def lines(spark, d):
    return S.table(spark, d, "lineitem", ["l_orderkey"]).withColumnRenamed("l_orderkey", "k")


@reg.add("keyonly_pairs", f"select distinct pair_id, cast(kappa as int) as kappa from ({Q.located(LINES, KEYONLY)})")
def keyonly_pairs(spark, d):
    return P.build_keyonly(lines(spark, d), "k", KEYONLY).entries.select("pair_id", "kappa")


@reg.add("keyonly_probe", f"with live as (select distinct pair_id, kappa from ({Q.located(LINES, KEYONLY)})) {Q.probe(ORDERS, KEYONLY)}")
def keyonly_probe(spark, d):
    return R.contains_key(orders(spark, d), "k", P.build_keyonly(lines(spark, d), "k", KEYONLY)).select("k")


@reg.add("counting_pairs", f"select pair_id, cast(kappa as int) as kappa, count(*) as n from ({Q.located(LINES, KEYONLY)}) group by all")
def counting_pairs(spark, d):
    return P.build_counting(lines(spark, d), "k", KEYONLY).entries.select("pair_id", "kappa", "n")


@reg.add(
    "keyonly_delete",
    f"with c as (select pair_id, kappa, count(*) as n, count(*) filter (k % 7 = 0) as gone from ({Q.located(LINES, KEYONLY)}) group by all) select pair_id, cast(kappa as int) as kappa, n - gone as n from c where n > gone",
)
def keyonly_delete(spark, d):
    rows = lines(spark, d)
    return P.delete_keys(P.build_counting(rows, "k", KEYONLY), rows.filter("k % 7 = 0"), "k").entries.select("pair_id", "kappa", "n")


# --- vectors

SUPP = spec_for("supp", BASE)
DISC = spec_for("disc", BASE)


@reg.add("attr_vectors", f"select distinct k, {Q.a_print('supp', 0, SUPP, False)} as a_0, {Q.a_print('lstatus', 1, SUPP, False)} as a_1 from ({relation_sql('supp')})")
def attr_vectors(spark, d):
    df = relation(spark, d, "supp")
    return df.select("k", *(c.cast("bigint").alias(n) for n, c in A.vector(df, SUPP).items())).distinct()


SMALLV = spec_for("qty", TINY, small_values=True)


@reg.add("attr_small_values", f"select distinct qty, {Q.a_print('qty', 0, SMALLV, True)} as a_0 from ({relation_sql('qty')})")
def attr_small_values(spark, d):
    df = relation(spark, d, "qty")
    return df.select("qty", A.vector(df, SMALLV)["a_0"].cast("bigint").alias("a_0")).distinct()


def _as_big(df, spec):
    return df.select("pair_id", "kappa", *(F.col(c).cast("bigint").alias(c) for c in P.prints(spec)))


@reg.add("plain_pairs", f"select pair_id, cast(kappa as int) as kappa, {Q.cols(SUPP)} from ({Q.vectors(relation_sql('supp'), SUPP)})")
def plain_pairs(spark, d):
    return _as_big(P.build_plain(relation(spark, d, "supp"), "k", SUPP).entries, SUPP)


SP = spec_for("sp", BASE, b=6)


@reg.add("plain_overflow", f"select pair_id, cast(kappa as int) as kappa, count(*) as n from ({Q.vectors(relation_sql('sp'), SP)}) group by all having count(*) > {2 * SP.b}")
def plain_overflow(spark, d):
    return P.build_plain(relation(spark, d, "sp"), "k", SP).failed.select("pair_id", "kappa", "n")


# --- chains

CH1, CH3 = DISC.with_(l_max=1), DISC.with_(l_max=3)


def chained(spark, d, spec, name="disc"):
    return P.build_chained(relation(spark, d, name), "k", spec)


for _name, _spec in (("chained_pairs_l1", CH1), ("chained_pairs_l3", CH3)):

    @reg.add(_name, f"with {Q.chained(relation_sql('disc'), _spec)} select pair_id, cast(kappa as int) as kappa, {Q.cols(_spec)} from entries")
    def _pairs(spark, d, spec=_spec):
        return _as_big(chained(spark, d, spec).entries, spec)


@reg.add(
    "chained_discarded",
    f"with {Q.chained(relation_sql('disc'), CH3)}, {Q.closed(CH3)} select (select count(*) from entries) as entries, (select count(*) from over_) as discarded, (select count(*) from saturated) as saturated",
)
def chained_discarded(spark, d):
    sketch = chained(spark, d, CH3)
    closed = R.close(sketch)
    one = sketch.entries.agg(F.count("*").alias("entries"))
    return one.crossJoin(sketch.discarded.agg(F.count("*").alias("discarded"))).crossJoin(closed.filter("saturated").agg(F.count("*").alias("saturated")))


@reg.add("chained_probe_eq", f"with {Q.chained(relation_sql('disc'), CH3)}, {Q.closed(CH3)}, {Q.live_chained(DISC4, CH3)} {Q.probe(ORDERS, CH3)}")
def chained_probe_eq(spark, d):
    return R.contains(orders(spark, d), "k", Predicate(DISC4), chained(spark, d, CH3)).select("k")


@reg.add("chained_probe_key", f"with {Q.chained(relation_sql('disc'), CH3)}, live as (select distinct pair_id, kappa from entries) {Q.probe(ORDERS, CH3)}")
def chained_probe_key(spark, d):
    return R.contains_key(orders(spark, d), "k", chained(spark, d, CH3)).select("k")


@reg.add("chained_pred_only", f"with {Q.chained(relation_sql('disc'), CH3)}, {Q.closed(CH3)}, {Q.live_chained(DISC4, CH3)} select distinct pair_id, cast(kappa as int) as kappa from live")
def chained_pred_only(spark, d):
    """The marked form: entries keep their prints, and chains are followed over marks."""
    sketch = chained(spark, d, CH3)
    return R.probe_marked(R.derive_marked(sketch, Predicate(DISC4)), sketch).select("pair_id", "kappa")


def _misses(spark, d, name, pred, live, spec):
    """(false negatives, keys asked): keys with a matching row whose probe is false."""
    rows = relation(spark, d, name)
    cond = F.lit(True)
    for c, values in pred.items():
        cond = cond & F.col(c).isin(list(values))
    keys = rows.filter(cond).select("k").distinct()
    hit = R.semi(keys, "k", live, spec).select(F.lit(1).alias("hit"))
    return keys.agg(F.count("*").alias("asked")).crossJoin(hit.agg(F.count("*").alias("found"))).select((F.col("asked") - F.col("found")).alias("false_negatives"), "asked")


def _zero(name: str, where: str) -> str:
    return f"select 0::bigint as false_negatives, count(distinct k) as asked from ({relation_sql(name)}) where {where}"


@reg.add("chained_no_false_neg", _zero("disc", "disc = 4"))
def chained_no_false_neg(spark, d):
    return _misses(spark, d, "disc", DISC4, R.derive_key_filter(chained(spark, d, CH3), Predicate(DISC4)), CH3)


CYC = DISC.with_(m=16, l_max=4, key_bits=7)


@reg.add(
    "chain_cycles",
    f"with g as (select distinct pair_id as p0, kappa from ({Q.located(relation_sql('disc'), CYC)})), a as (select *, {Q.next_pair('p0', 'kappa', CYC)} as p1 from g), "
    f"b as (select *, {Q.next_pair('p1', 'kappa', CYC)} as p2 from a), c as (select *, {Q.next_pair('p2', 'kappa', CYC)} as p3 from b) "
    "select p0 as pair_id, cast(kappa as int) as kappa, cast(len(list_distinct([p0, p1, p2, p3])) as bigint) as plain_pairs from c",
)
def chain_cycles(spark, d):
    """How many different pairs a chain of four has without cycle breaking."""
    groups = P.build_keyonly(relation(spark, d, "disc"), "k", CYC).entries
    return groups.select("pair_id", "kappa", F.size(F.array_distinct(hashing.chain_pairs(F.col("pair_id"), F.col("kappa"), CYC, 4))).cast("bigint").alias("plain_pairs"))


_PAIRS_OF_FOUR = ", ".join(f"c{t + 1} as (select kappa, list_append(seen, coalesce({Q.onward('seen', 'kappa', CYC)}, {Q.next_pair('seen[-1]', 'kappa', CYC)})) as seen from c{t})" for t in range(3))


@reg.add("chain_cycles_broken", f"with c0 as (select kappa, [pair_id] as seen from (select distinct pair_id, kappa from ({Q.located(relation_sql('disc'), CYC)}))), {_PAIRS_OF_FOUR} select seen[1] as pair_id, cast(kappa as int) as kappa, seen[2] as second, seen[3] as third, seen[4] as fourth, len(list_distinct(seen)) as pairs from c3")
def chain_cycles_broken(spark, d):
    """Chains of four with cycle breaking, and how many different pairs they have."""
    groups = P.build_keyonly(relation(spark, d, "disc"), "k", CYC).entries
    chain = hashing.chain_pairs(F.col("pair_id"), F.col("kappa"), CYC.with_(cycle_break=True), 4)
    at = lambda i: F.element_at("chain", i)
    return groups.withColumn("chain", chain).select("pair_id", "kappa", at(2).alias("second"), at(3).alias("third"), at(4).alias("fourth"), F.size(F.array_distinct("chain")).cast("bigint").alias("pairs"))


UNCAP = spec_for("co", BASE, l_max=None)
FEW = spec_for("disc", BASE, l_max=None, m=16, key_bits=6, attr_bits=3, d=2)


def _uncapped_sql(name: str, s, rounds: int) -> str:
    return f"select * from (with {Q.uncapped(relation_sql(name), s, rounds)} select (select count(*) from entries) as entries, (select count(*) from over_) as discarded, (select count(*) from late_) as moving)"


for _name, _rel, _spec, _rounds in (("chained_uncapped_size", "co", UNCAP, 24), ("chained_uncapped_cycles", "disc", FEW, 10)):

    @reg.add(_name, _uncapped_sql(_rel, _spec, _rounds))
    def _uncapped(spark, d, rel=_rel, spec=_spec):
        """Entries of chains without cap, and vectors whose chain ran out of new pairs; nothing moves any more."""
        sketch = P.build_chained(relation(spark, d, rel), "k", spec)
        out = sketch.entries.agg(F.count("*").alias("entries")).crossJoin(sketch.discarded.agg(F.count("*").alias("discarded")))
        return out.withColumn("moving", F.lit(0).cast("bigint"))


# --- Bloom attribute sketches

BLOOM = spec_for("supp", BASE, variant="bloomattr")
SUPP7 = {"supp": (7,), "lstatus": ("O",)}


@reg.add("bloomattr_pairs", f"with {Q.bloom(relation_sql('supp'), BLOOM)} select pair_id, cast(kappa as int) as kappa, mask from entries")
def bloomattr_pairs(spark, d):
    return P.build_bloomattr(relation(spark, d, "supp"), "k", BLOOM).entries.select("pair_id", "kappa", "mask")


_BLOOM_LIVE = f"with {Q.bloom(relation_sql('supp'), BLOOM)}, live as (select pair_id, kappa from entries where {Q.want_mask(SUPP7, BLOOM)})"


@reg.add("bloomattr_probe_eq", f"{_BLOOM_LIVE} {Q.probe(ORDERS, BLOOM)}")
def bloomattr_probe_eq(spark, d):
    return R.contains(orders(spark, d), "k", Predicate(SUPP7), P.build_bloomattr(relation(spark, d, "supp"), "k", BLOOM)).select("k")


@reg.add("bloomattr_pred_only", f"{_BLOOM_LIVE} select pair_id, cast(kappa as int) as kappa from live")
def bloomattr_pred_only(spark, d):
    return R.derive_key_filter(P.build_bloomattr(relation(spark, d, "supp"), "k", BLOOM), Predicate(SUPP7)).select("pair_id", "kappa")


@reg.add("bloomattr_no_false_neg", _zero("supp", "supp = 7 and lstatus = 'O'"))
def bloomattr_no_false_neg(spark, d):
    sketch = P.build_bloomattr(relation(spark, d, "supp"), "k", BLOOM)
    return _misses(spark, d, "supp", SUPP7, R.derive_key_filter(sketch, Predicate(SUPP7)), BLOOM)


# --- hybrid

HYB = spec_for("supp", BASE, variant="hybrid")
HB, HH = P.hybrid_bits(HYB), P.hybrid_hashes(HYB)


@reg.add("hybrid_pairs", f"with {Q.hybrid(relation_sql('supp'), HYB, HB, HH)} select pair_id, cast(kappa as int) as kappa, n > {HYB.d} as is_bloom, case when n > {HYB.d} then 0 else n end as n_vectors, mask from entries")
def hybrid_pairs(spark, d):
    e = P.build_hybrid(relation(spark, d, "supp"), "k", HYB).entries
    return e.select("pair_id", "kappa", "is_bloom", F.size("vectors").cast("bigint").alias("n_vectors"), "mask")


_HYB = f"with {Q.hybrid(relation_sql('supp'), HYB, HB, HH)}, {Q.live_hybrid(SUPP7, HYB, HB, HH)}"


@reg.add("hybrid_probe_eq", f"{_HYB} {Q.probe(ORDERS, HYB)}")
def hybrid_probe_eq(spark, d):
    return R.contains(orders(spark, d), "k", Predicate(SUPP7), P.build_hybrid(relation(spark, d, "supp"), "k", HYB)).select("k")


@reg.add("hybrid_pred_only", f"{_HYB} select pair_id, cast(kappa as int) as kappa from live")
def hybrid_pred_only(spark, d):
    return R.derive_key_filter(P.build_hybrid(relation(spark, d, "supp"), "k", HYB), Predicate(SUPP7)).select("pair_id", "kappa")


@reg.add("hybrid_no_false_neg", _zero("supp", "supp = 7 and lstatus = 'O'"))
def hybrid_no_false_neg(spark, d):
    sketch = P.build_hybrid(relation(spark, d, "supp"), "k", HYB)
    return _misses(spark, d, "supp", SUPP7, R.derive_key_filter(sketch, Predicate(SUPP7)), HYB)


# --- other shapes of use

@reg.add("attr_compression_gain")
def attr_compression_gain(spark, d):
    """Distinct vectors left when 8-bit prints become 4-bit ones by balanced codes, against 4-bit hashes."""
    wide = P.build_plain(relation(spark, d, "qty"), "k", spec_for("qty", BASE)).entries
    short = A.compress(wide, ["a_0"], 4)
    direct = P.build_plain(relation(spark, d, "qty"), "k", spec_for("qty", BASE, attr_bits=4)).entries
    parts = [df.agg(F.count("*").alias(n)) for df, n in ((wide, "wide"), (short, "balanced"), (direct, "hashed"))]
    return parts[0].crossJoin(parts[1]).crossJoin(parts[2])


HDR = spec_for("hdr", BASE, variant="chained", l_max=1)
HDR_BINS = {"bin": tuple(range(6, 10))}


@reg.add("bins_orderdate", "select cast(floor(((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1) / 5) as bigint) as bin, count(*) as n from orders group by all")
def bins_orderdate(spark, d):
    month = (F.year("o_orderdate") - 1995) * 12 + F.month("o_orderdate") - 1
    return S.table(spark, d, "orders", ["o_orderdate"]).groupBy(binning.width_bin(month, 0, 79, 16).alias("bin")).agg(F.count("*").alias("n"))


@reg.add("bins_depth", "with v as (select distinct l_quantity as q from lineitem), n as (select q, ntile(16) over (order by q) - 1 as bin from v) select cast(bin as int) as bin, min(q) as lo, max(q) as hi from n group by all")
def bins_depth(spark, d):
    return binning.depth_edges(S.table(spark, d, "lineitem", ["l_quantity"]), "l_quantity", 16)


@reg.add("range_probe_binned", f"with {Q.chained(relation_sql('hdr'), HDR)}, {Q.closed(HDR)}, {Q.live_chained(HDR_BINS, HDR)} {Q.probe('select distinct l_orderkey as k from lineitem', HDR)}")
def range_probe_binned(spark, d):
    """Lines whose order's month lies in 30..49, by the bins that the range touches."""
    pred = Predicate.isin("bin", binning.width_inlist(30, 49, 0, 79, 16))
    return R.contains(lines(spark, d).distinct(), "k", pred, P.build_chained(relation(spark, d, "hdr"), "k", HDR)).select("k")


DYA = BASE.with_(variant="chained", attrs=(AttrSpec("node", True),), l_max=3, attr_bits=8)
_DYA_ROWS = "select k, unnest([" + ", ".join(f"({1 << i} + (mon >> {7 - i}))" for i in range(8)) + "]) as node from (select o_orderkey as k, cast((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 as bigint) as mon from orders)"
DYA_COVER = {"node": tuple(binning.dyadic_cover(30, 49, 7))}


@reg.add("range_probe_dyadic", f"with {Q.chained(_DYA_ROWS, DYA)}, {Q.closed(DYA)}, {Q.live_chained(DYA_COVER, DYA)} {Q.probe('select distinct l_orderkey as k from lineitem', DYA)}")
def range_probe_dyadic(spark, d):
    month = ((F.year("o_orderdate") - 1995) * 12 + F.month("o_orderdate") - 1).cast("bigint")
    rows = S.table(spark, d, "orders", ["o_orderkey", "o_orderdate"]).select(F.col("o_orderkey").alias("k"), F.explode(binning.dyadic_items(month, 7)).alias("node"))
    return R.contains(lines(spark, d).distinct(), "k", Predicate(DYA_COVER), P.build_chained(rows, "k", DYA)).select("k")


@reg.add("sketch_union", f"with {Q.bloom(relation_sql('supp'), BLOOM)} select pair_id, cast(kappa as int) as kappa, mask from entries")
def sketch_union(spark, d):
    """Sketches of two halves of a table, merged: the sketch of the table."""
    rows = relation(spark, d, "supp")
    halves = [P.build_bloomattr(rows.filter(f"supp % 2 = {i}"), "k", BLOOM) for i in (0, 1)]
    return P.merge(*halves).entries.select("pair_id", "kappa", "mask")


UNION_H = spec_for("supp", BASE, variant="hybrid")
UNION_C = spec_for("disc", BASE, l_max=3, key_bits=8)


@reg.add("sketch_union_hybrid", f"with {Q.hybrid(relation_sql('supp'), UNION_H, P.hybrid_bits(UNION_H), P.hybrid_hashes(UNION_H))} select pair_id, cast(kappa as int) as kappa, n > {UNION_H.d} as is_bloom, case when n > {UNION_H.d} then 0 else n end as held, mask from entries")
def sketch_union_hybrid(spark, d):
    """Hybrid sketches of two halves, merged: the sketch of the table."""
    rows = relation(spark, d, "supp")
    halves = [P.build_hybrid(rows.filter(f"supp % 2 = {i}"), "k", UNION_H) for i in (0, 1)]
    return P.merge(*halves).entries.select("pair_id", "kappa", "is_bloom", F.size("vectors").cast("bigint").alias("held"), "mask")


DISC = relation_sql("disc")


def _half_sql(i: int) -> str:
    return f"select pair_id, kappa, {Q.cols(UNION_C)} from (with {Q.chained(f'select * from ({DISC}) where disc % 2 = {i}', UNION_C)} select * from entries)"


@reg.add("sketch_union_chained", f"with {Q.rounds(f'{_half_sql(0)} union {_half_sql(1)}', UNION_C)} select pair_id, cast(kappa as int) as kappa, {Q.cols(UNION_C)} from entries")
def sketch_union_chained(spark, d):
    """Chained sketches of two halves, merged: their entries through the rounds anew."""
    rows = relation(spark, d, "disc")
    halves = [P.build_chained(rows.filter(f"disc % 2 = {i}"), "k", UNION_C) for i in (0, 1)]
    return _as_big(P.merge(*halves).entries, UNION_C)


EV_PRED = {"kind": ("click",), "day": (5,)}
EV_B = spec_for("ev", BASE, variant="bloomattr", m=256)
EV_H = spec_for("ev", BASE, variant="hybrid", m=256)
EV_C = spec_for("ev", BASE, variant="chained", m=256, l_max=24)
EHB, EHH = P.hybrid_bits(EV_H), P.hybrid_hashes(EV_H)
USERS = "select distinct user_id as k from events"


@reg.add(
    "cooccurrence_gap",
    f"with exact_ as (select count(distinct k) as exact from ({relation_sql('ev')}) where kind = 'click' and day = 5), both_ as (select count(*) as apart from (select k from ({relation_sql('ev')}) group by k having bool_or(kind = 'click') and bool_or(day = 5))), "
    f"bl as (with {Q.bloom(relation_sql('ev'), EV_B)}, live as (select pair_id, kappa from entries where {Q.want_mask(EV_PRED, EV_B)}) select count(*) as bloomattr from ({Q.probe(USERS, EV_B)})), "
    f"hy as (with {Q.hybrid(relation_sql('ev'), EV_H, EHB, EHH)}, {Q.live_hybrid(EV_PRED, EV_H, EHB, EHH)} select count(*) as hybrid from ({Q.probe(USERS, EV_H)})) select exact, apart, bloomattr, hybrid from exact_, both_, bl, hy",
)
def cooccurrence_gap(spark, d):
    """Users with a click on day 5: exactly, with both values on any rows, by Bloom masks, by the hybrid."""
    rows = relation(spark, d, "ev")
    keys = rows.select("k").distinct()
    exact = rows.filter("kind = 'click' and day = 5").select("k").distinct().agg(F.count("*").alias("exact"))
    apart = rows.groupBy("k").agg((F.max(F.col("kind") == "click") & F.max(F.col("day") == 5)).alias("both")).filter("both").agg(F.count("*").alias("apart"))
    out = exact.crossJoin(apart)
    for spec in (EV_B, EV_H):
        hit = R.contains(keys, "k", Predicate(EV_PRED), P.build(rows, "k", spec))
        out = out.crossJoin(hit.agg(F.count("*").alias(spec.variant)))
    return out


SP_B = spec_for("sp", BASE, variant="bloomattr", m=256)
SP_H = spec_for("sp", BASE, variant="hybrid", m=256)
SP_C = spec_for("sp", BASE, variant="chained", m=256, l_max=4)
SHB, SHH = P.hybrid_bits(SP_H), P.hybrid_hashes(SP_H)
SP_PRED = {"part": (1500,)}
SUPPLIERS = "select s_suppkey as k from supplier"


@reg.add(
    "heavy_dupes",
    f"with ex as (select count(distinct k) as exact from ({relation_sql('sp')}) where part = 1500), "
    f"bl as (with {Q.bloom(relation_sql('sp'), SP_B)}, live as (select pair_id, kappa from entries where {Q.want_mask(SP_PRED, SP_B)}) select count(*) as bloomattr from ({Q.probe(SUPPLIERS, SP_B)})), "
    f"hy as (with {Q.hybrid(relation_sql('sp'), SP_H, SHB, SHH)}, {Q.live_hybrid(SP_PRED, SP_H, SHB, SHH)} select count(*) as hybrid from ({Q.probe(SUPPLIERS, SP_H)})), "
    f"ch as (with {Q.chained(relation_sql('sp'), SP_C)}, {Q.closed(SP_C)}, {Q.live_chained(SP_PRED, SP_C)} select count(*) as chained from ({Q.probe(SUPPLIERS, SP_C)})) select exact, bloomattr, hybrid, chained from ex, bl, hy, ch",
)
def heavy_dupes(spark, d):
    """Suppliers of one part when a supplier has hundreds of parts: masks fill up and chains saturate."""
    rows = relation(spark, d, "sp")
    keys = S.table(spark, d, "supplier", ["s_suppkey"]).withColumnRenamed("s_suppkey", "k")
    out = rows.filter("part = 1500").select("k").distinct().agg(F.count("*").alias("exact"))
    for spec in (SP_B, SP_H, SP_C):
        out = out.crossJoin(R.contains(keys, "k", Predicate(SP_PRED), P.build(rows, "k", spec)).agg(F.count("*").alias(spec.variant)))
    return out


@reg.add("sketch_store_roundtrip", f"with {Q.chained(relation_sql('disc'), CH3)} select pair_id, cast(kappa as int) as kappa, {Q.cols(CH3)} from entries")
def sketch_store_roundtrip(spark, d):
    return _as_big(S.stored(chained(spark, d, CH3)).entries, CH3)


@reg.add("derived_filter_roundtrip", f"{_BLOOM_LIVE} select pair_id, cast(kappa as int) as kappa from live")
def derived_filter_roundtrip(spark, d):
    live = R.derive_key_filter(P.build_bloomattr(relation(spark, d, "supp"), "k", BLOOM), Predicate(SUPP7))
    return S.save_filter(live, f"{S.shared_dir(spark)}/filter").select("pair_id", "kappa")


@reg.add("columnar_probe_plan", f"select distinct pair_id, cast(kappa as int) as kappa from ({Q.vectors(relation_sql('supp'), SUPP)}) where {Q.match({'lstatus': ('O',)}, SUPP)}")
def columnar_probe_plan(spark, d):
    """A stored sketch asked for one attribute reads that attribute's column only."""
    sketch = S.stored(P.build_plain(relation(spark, d, "supp"), "k", SUPP.with_(variant="plain")))
    return R.derive_key_filter(sketch, Predicate({"lstatus": ("O",)})).select("pair_id", "kappa")


