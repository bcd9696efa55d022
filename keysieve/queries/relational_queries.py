"""Queries on the surrounding operators: scans, filters, joins, aggregates, windows, set operations and functions."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..config import Predicate
from ..functions.hashing import h60
from ..operators import relational as O
from ..sources import tables as S
from . import sql as Q
from .registry import Registry

reg = Registry()
T = S.table


def n():
    return F.count("*").alias("n")


def keep(df, pred: Predicate):
    """Rows that match a predicate exactly, as the own scan does."""

    def one(p: Predicate):
        out = F.lit(True)
        for c, values in p.allowed.items():
            out = out & F.col(c).isin(list(values))
        return out & F.expr(p.residual) if p.residual else out

    if pred.options:
        out = F.lit(False)
        for p in pred.options:
            out = out | one(p)
        return df.filter(out)
    return df.filter(one(pred))


# --- scans and formats


@reg.add("scan_lineitem", "select l_orderkey, l_suppkey, l_quantity from lineitem where l_quantity >= 49")
def scan_lineitem(spark, d):
    return T(spark, d, "lineitem", ["l_orderkey", "l_suppkey", "l_quantity"]).filter("l_quantity >= 49")


@reg.add("io_roundtrip", "select fmt, (select count(*) from supplier) as n, (select sum(s_suppkey)::bigint from supplier) as keys, (select count(distinct s_name) from supplier) as names from (values ('csv'), ('json'), ('orc')) f(fmt)")
def io_roundtrip(spark, d):
    src, out = T(spark, d, "supplier"), None
    for fmt in ("csv", "json", "orc"):
        one = S.roundtrip(src, fmt).agg(n(), F.sum("s_suppkey").alias("keys"), F.countDistinct("s_name").alias("names")).select(F.lit(fmt).alias("fmt"), "n", "keys", "names")
        out = one if out is None else out.unionByName(one)
    return out


# --- filters and projection

_O = ["o_orderkey", "o_orderstatus", "o_orderpriority", "o_totalprice"]


@reg.add("filter_eq", "select o_orderkey from orders where o_orderstatus = 'F' and o_orderpriority = '1-URGENT'")
def filter_eq(spark, d):
    return keep(T(spark, d, "orders", _O), Predicate.eq(o_orderstatus="F", o_orderpriority="1-URGENT")).select("o_orderkey")


@reg.add("filter_inlist", "select l_orderkey, l_linenumber from lineitem where l_quantity in (1, 17, 50)")
def filter_inlist(spark, d):
    return keep(T(spark, d, "lineitem", ["l_orderkey", "l_linenumber", "l_quantity"]), Predicate.isin("l_quantity", (1.0, 17.0, 50.0))).select("l_orderkey", "l_linenumber")


@reg.add("filter_range", "select p_partkey from part where p_size between 10 and 20")
def filter_range(spark, d):
    return keep(T(spark, d, "part", ["p_partkey", "p_size"]), Predicate.between("p_size", 10, 20)).select("p_partkey")


@reg.add("filter_or", "select o_orderkey from orders where (o_orderstatus = 'F' and o_orderpriority = '1-URGENT') or o_orderstatus = 'P'")
def filter_or(spark, d):
    return keep(T(spark, d, "orders", _O), Predicate.any_of(Predicate.eq(o_orderstatus="F", o_orderpriority="1-URGENT"), Predicate.eq(o_orderstatus="P"))).select("o_orderkey")


@reg.add("filter_residual", "select o_orderkey from orders where o_orderstatus = 'F' and o_totalprice > 200000 and o_orderpriority <> '5-LOW'")
def filter_residual(spark, d):
    pred = Predicate.eq(o_orderstatus="F").and_residual("o_totalprice > 200000").and_residual("o_orderpriority <> '5-LOW'")
    return keep(T(spark, d, "orders", _O), pred).select("o_orderkey")


@reg.add("filter_like_null", "select p_partkey, p_brand like '%3' as like3, p_type is not distinct from null as no_type, p_name is null as no_name from part where p_brand like 'Brand#1%'")
def filter_like_null(spark, d):
    p = T(spark, d, "part", ["p_partkey", "p_brand", "p_type", "p_name"]).filter(F.col("p_brand").like("Brand#1%"))
    return p.select("p_partkey", F.col("p_brand").like("%3").alias("like3"), F.col("p_type").eqNullSafe(F.lit(None)).alias("no_type"), F.col("p_name").isNull().alias("no_name"))


@reg.add("project_expr", "select l_orderkey, l_linenumber, cast(round(l_extendedprice * 100) as bigint) * (100 - cast(round(l_discount * 100) as bigint)) as net, l_returnflag || '/' || l_linestatus as flags from lineitem")
def project_expr(spark, d):
    li = T(spark, d, "lineitem", ["l_orderkey", "l_linenumber", "l_extendedprice", "l_discount", "l_returnflag", "l_linestatus"])
    return li.select("l_orderkey", "l_linenumber", (F.round(F.col("l_extendedprice") * 100).cast("long") * (100 - F.round(F.col("l_discount") * 100).cast("long"))).alias("net"), F.concat("l_returnflag", F.lit("/"), "l_linestatus").alias("flags"))


# --- joins

_SN = "select s_suppkey, n_name from supplier join nation on s_nationkey = n_nationkey"


def _suppliers(spark, d):
    return T(spark, d, "supplier", ["s_suppkey", "s_nationkey"]), T(spark, d, "nation", ["n_nationkey", "n_name"])


@reg.add("join_broadcast", _SN)
def join_broadcast(spark, d):
    s, na = _suppliers(spark, d)
    return O.join(s, na, s.s_nationkey == na.n_nationkey, strategy="broadcast").select("s_suppkey", "n_name")


_OC = "select o_orderkey, c_mktsegment from orders join customer on o_custkey = c_custkey"


def _orders_customers(spark, d):
    return T(spark, d, "orders", ["o_orderkey", "o_custkey"]), T(spark, d, "customer", ["c_custkey", "c_mktsegment"])


for _name, _strategy in (("join_shuffle_hash", "shuffle_hash"), ("join_sort_merge", "merge")):

    @reg.add(_name, _OC)
    def _joined(spark, d, strategy=_strategy):
        o, c = _orders_customers(spark, d)
        return O.join(o, c, o.o_custkey == c.c_custkey, strategy=strategy).select("o_orderkey", "c_mktsegment")


_B = "select user_id as k, count(*) as b from events group by all"


@reg.add("join_outer", " union all ".join(f"select '{h}' as how, count(*) as n, count(a) as with_a, count(b) as with_b from (select c_custkey as k, c_nationkey as a from customer) x {h} join ({_B}) y using (k)" for h in ("left", "right", "full")))
def join_outer(spark, d):
    a = T(spark, d, "customer", ["c_custkey", "c_nationkey"]).select(F.col("c_custkey").alias("k"), F.col("c_nationkey").alias("a"))
    b, out = T(spark, d, "events", ["user_id"]).groupBy(F.col("user_id").alias("k")).agg(F.count("*").alias("b")), None
    for how in ("left", "right", "full"):
        one = O.join(a, b, "k", how).agg(n(), F.count("a").alias("with_a"), F.count("b").alias("with_b")).select(F.lit(how).alias("how"), "n", "with_a", "with_b")
        out = one if out is None else out.unionByName(one)
    return out


@reg.add("join_semi", "select c_custkey from customer where c_custkey in (select user_id from events)")
def join_semi(spark, d):
    c, e = T(spark, d, "customer", ["c_custkey"]), T(spark, d, "events", ["user_id"])
    return O.semi(c, e, c.c_custkey == e.user_id)


@reg.add("join_anti", "select o_orderkey from orders where o_orderkey not in (select l_orderkey from lineitem)")
def join_anti(spark, d):
    o, li = T(spark, d, "orders", ["o_orderkey"]), T(spark, d, "lineitem", ["l_orderkey"])
    return O.anti(o, li, o.o_orderkey == li.l_orderkey)


_RANGES = [(0, 50_000), (40_000, 120_000), (120_001, 400_000)]


@reg.add("join_range", "select lo, hi, count(*) as n from orders join (values " + ", ".join(map(str, _RANGES)) + ") r(lo, hi) on cast(o_totalprice as bigint) between lo and hi group by all")
def join_range(spark, d):
    o = T(spark, d, "orders", ["o_totalprice"]).select(F.floor("o_totalprice").alias("x"))
    return O.range_join(o, "x", spark.createDataFrame(_RANGES, "lo long, hi long"), "lo", "hi", 50_000).groupBy("lo", "hi").agg(n())


reg.sql["join_range"] = reg.sql["join_range"].replace("cast(o_totalprice as bigint)", "cast(floor(o_totalprice) as bigint)")


@reg.add("join_cross", "select status, priority, flag from (select distinct o_orderstatus as status from orders), (select distinct o_orderpriority as priority from orders), (select distinct l_returnflag as flag from lineitem)")
def join_cross(spark, d):
    """All combinations of the values of three columns."""
    axis = lambda t, c, name: T(spark, d, t, [c]).withColumnRenamed(c, name).distinct()
    return O.grid(axis("orders", "o_orderstatus", "status"), axis("orders", "o_orderpriority", "priority"), axis("lineitem", "l_returnflag", "flag"))


@reg.add("join_asof", "select e.event_id, (select last(v.value order by v.ts, v.event_id) from events v where v.user_id = e.user_id and v.event_type = 'view' and v.ts <= e.ts) is not null as seen, (select max(v.ts) from events v where v.user_id = e.user_id and v.event_type = 'view' and v.ts <= e.ts) = e.ts as same from events e where e.event_type = 'purchase'")
def join_asof(spark, d):
    """Purchases with the time of the user's last view up to then."""
    e = T(spark, d, "events", ["event_id", "ts", "user_id", "event_type"])
    views = e.filter("event_type = 'view'").select("user_id", "ts", F.col("ts").alias("viewed"))
    out = O.asof(e.filter("event_type = 'purchase'").select("event_id", "user_id", "ts"), views, "user_id", "ts", "viewed")
    return out.select("event_id", F.col("viewed").isNotNull().alias("seen"), (F.col("viewed") == F.col("ts")).alias("same"))


@reg.add("join_interval", "select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and epoch(b.ts) - epoch(a.ts) between 0 and 86400")
def join_interval(spark, d):
    e = T(spark, d, "events", ["event_id", "ts", "user_id", "event_type"])
    a = e.filter("event_type = 'click'").select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"))
    b = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"))
    return O.interval_join(a, b, "user_id", "ta", "tb", 1).select("a", "b")


# --- aggregates


@reg.add("agg_basic", "select l_returnflag, l_linestatus, count(*) as n, sum(cast(l_quantity as bigint))::bigint as qty, max(l_suppkey) as top from lineitem group by all")
def agg_basic(spark, d):
    return T(spark, d, "lineitem", ["l_returnflag", "l_linestatus", "l_quantity", "l_suppkey"]).groupBy("l_returnflag", "l_linestatus").agg(n(), F.sum(F.col("l_quantity").cast("long")).alias("qty"), F.max("l_suppkey").alias("top"))


@reg.add("agg_sorted", "select s_nationkey, array_to_string(list(s_suppkey order by s_suppkey), ',') as keys from supplier group by all")
def agg_sorted(spark, d):
    return T(spark, d, "supplier", ["s_nationkey", "s_suppkey"]).groupBy("s_nationkey").agg(F.concat_ws(",", F.transform(F.sort_array(F.collect_list("s_suppkey")), lambda x: x.cast("string"))).alias("keys"))


@reg.add("agg_distinct", "select l_returnflag, count(distinct l_suppkey) as supps, count(distinct l_partkey) as parts from lineitem group by all")
def agg_distinct(spark, d):
    return T(spark, d, "lineitem", ["l_returnflag", "l_suppkey", "l_partkey"]).groupBy("l_returnflag").agg(F.countDistinct("l_suppkey").alias("supps"), F.countDistinct("l_partkey").alias("parts"))


@reg.add("agg_approx_distinct")
def agg_approx_distinct(spark, d):
    li = T(spark, d, "lineitem", ["l_orderkey"])
    return li.agg(F.approx_count_distinct("l_orderkey", 0.02).alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("l_orderkey")).alias("hll"), F.countDistinct("l_orderkey").alias("exact"))


@reg.add("agg_bits", "select l_orderkey, bit_or(1::bigint << l_linenumber::int) as any_, bit_and(l_suppkey) as all_ from lineitem group by all")
def agg_bits(spark, d):
    li = T(spark, d, "lineitem", ["l_orderkey", "l_linenumber", "l_suppkey"])
    return li.groupBy("l_orderkey").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("l_linenumber").cast("int"))).alias("any_"), F.bit_and("l_suppkey").alias("all_"))


for _name, _sql, _how in (("agg_cube", "cube (o_orderstatus, o_orderpriority)", "cube"), ("agg_rollup", "rollup (o_orderstatus, o_orderpriority)", "rollup")):

    @reg.add(_name, f"select o_orderstatus, o_orderpriority, count(*) as n from orders group by {_sql}")
    def _super(spark, d, how=_how):
        return getattr(T(spark, d, "orders", _O), how)("o_orderstatus", "o_orderpriority").agg(n())


@reg.add("agg_grouping_sets", "select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")
def agg_grouping_sets(spark, d):
    return T(spark, d, "orders", _O).groupingSets([["o_orderstatus"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority").agg(n())


@reg.add("agg_pivot", "select o_orderpriority, count(*) filter (o_orderstatus = 'F') as F, count(*) filter (o_orderstatus = 'O') as O, count(*) filter (o_orderstatus = 'P') as P from orders group by all")
def agg_pivot(spark, d):
    return T(spark, d, "orders", _O).groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0)


@reg.add("agg_quantile", "select l_returnflag, quantile_cont(l_quantity, 0.5) as med, arg_max(l_orderkey, l_orderkey) as last from lineitem group by all")
def agg_quantile(spark, d):
    return T(spark, d, "lineitem", ["l_returnflag", "l_quantity", "l_orderkey"]).groupBy("l_returnflag").agg(F.percentile("l_quantity", 0.5).alias("med"), F.max_by("l_orderkey", "l_orderkey").alias("last"))


# --- windows, sorts, sets


@reg.add("win_row_number_cap", "select l_orderkey, l_partkey from (select distinct l_orderkey, l_partkey from lineitem) qualify row_number() over (partition by l_orderkey order by l_partkey) <= 3")
def win_row_number_cap(spark, d):
    return O.top_per_group(T(spark, d, "lineitem", ["l_orderkey", "l_partkey"]).distinct(), ["l_orderkey"], [F.col("l_partkey")], 3)


def _types():
    return Window.partitionBy("p_type").orderBy("p_size")


@reg.add("win_rank", "select p_partkey, rank() over w as r, dense_rank() over w as dr from part window w as (partition by p_type order by p_size)")
def win_rank(spark, d):
    return T(spark, d, "part", ["p_partkey", "p_type", "p_size"]).select("p_partkey", F.rank().over(_types()).alias("r"), F.dense_rank().over(_types()).alias("dr"))


@reg.add("win_ntile", "select s_suppkey, ntile(4) over (partition by s_nationkey order by s_suppkey) as q from supplier")
def win_ntile(spark, d):
    return T(spark, d, "supplier", ["s_suppkey", "s_nationkey"]).select("s_suppkey", F.ntile(4).over(Window.partitionBy("s_nationkey").orderBy("s_suppkey")).alias("q"))


_EW = "partition by user_id order by ts, event_id"


def _users():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


@reg.add("win_lag_lead", f"select event_id, lag(event_id) over w as prev, lead(event_id) over w as next, first_value(event_id) over w as first from events window w as ({_EW})")
def win_lag_lead(spark, d):
    return T(spark, d, "events", ["event_id", "user_id", "ts"]).select("event_id", F.lag("event_id").over(_users()).alias("prev"), F.lead("event_id").over(_users()).alias("next"), F.first("event_id").over(_users()).alias("first"))


@reg.add("win_rows_frame", f"select event_id, count(*) over (w rows between 2 preceding and current row) as n3, min(event_id) over (w rows between 2 preceding and current row) as low from events window w as ({_EW})")
def win_rows_frame(spark, d):
    f = _users().rowsBetween(-2, 0)
    return T(spark, d, "events", ["event_id", "user_id", "ts"]).select("event_id", F.count("*").over(f).alias("n3"), F.min("event_id").over(f).alias("low"))


@reg.add("win_range_frame", "select event_id, count(*) over (partition by user_id order by cast(floor(epoch(ts)) as bigint) range between 86400 preceding and current row) as day_n from events")
def win_range_frame(spark, d):
    f = Window.partitionBy("user_id").orderBy(F.unix_timestamp("ts")).rangeBetween(-86400, 0)
    return T(spark, d, "events", ["event_id", "user_id", "ts"]).select("event_id", F.count("*").over(f).alias("day_n"))


@reg.add("topk_basic", "select o_orderkey from orders order by o_totalprice desc, o_orderkey limit 20")
def topk_basic(spark, d):
    return T(spark, d, "orders", _O).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey")


@reg.add("bottomk_keys", f"select o_orderkey from orders order by {Q.h('o_orderkey', 'sample')}, o_orderkey limit 100")
def bottomk_keys(spark, d):
    return T(spark, d, "orders", ["o_orderkey"]).orderBy(h60("o_orderkey", "sample", 0, "portable"), "o_orderkey").limit(100)


@reg.add("topk_per_group", "select l_suppkey, l_partkey, n from (select l_suppkey, l_partkey, count(*) as n from lineitem group by all) qualify row_number() over (partition by l_suppkey order by n desc, l_partkey) <= 2")
def topk_per_group(spark, d):
    c = T(spark, d, "lineitem", ["l_suppkey", "l_partkey"]).groupBy("l_suppkey", "l_partkey").agg(n())
    return O.top_per_group(c, ["l_suppkey"], [F.desc("n"), F.col("l_partkey")], 2)


@reg.add("set_intersect", "select l_orderkey from lineitem where l_quantity = 17 intersect select l_orderkey from lineitem where l_linestatus = 'O'")
def set_intersect(spark, d):
    li = T(spark, d, "lineitem", ["l_orderkey", "l_quantity", "l_linestatus"])
    return li.filter("l_quantity = 17").select("l_orderkey").intersect(li.filter("l_linestatus = 'O'").select("l_orderkey"))


@reg.add("set_except", "select o_custkey from orders where o_orderstatus = 'F' except select o_custkey from orders where o_orderstatus = 'P'")
def set_except(spark, d):
    o = T(spark, d, "orders", ["o_custkey", "o_orderstatus"])
    return o.filter("o_orderstatus = 'F'").select("o_custkey").subtract(o.filter("o_orderstatus = 'P'").select("o_custkey"))


@reg.add("set_except_all", "select o_custkey from orders where o_orderstatus = 'F' except all select o_custkey from orders where o_orderstatus = 'O'")
def set_except_all(spark, d):
    o = T(spark, d, "orders", ["o_custkey", "o_orderstatus"])
    return o.filter("o_orderstatus = 'F'").select("o_custkey").exceptAll(o.filter("o_orderstatus = 'O'").select("o_custkey"))


# --- functions


@reg.add("fn_bits", "select o_orderkey, xor(o_orderkey, o_custkey) as x, o_orderkey << 3 as left3, o_orderkey >> 2 as right2, bit_count(o_orderkey)::int as ones, lower(to_hex(o_orderkey)) as hex from orders")
def fn_bits(spark, d):
    o = T(spark, d, "orders", ["o_orderkey", "o_custkey"])
    return o.select("o_orderkey", F.col("o_orderkey").bitwiseXOR(F.col("o_custkey")).alias("x"), F.shiftleft("o_orderkey", 3).alias("left3"), F.shiftright("o_orderkey", 2).alias("right2"), F.bit_count("o_orderkey").alias("ones"), F.lower(F.hex("o_orderkey")).alias("hex"))


@reg.add("fn_string", "select c_custkey, lower(c_name) as low, substr(c_name, 1, 8) as head, regexp_extract(c_name, '([0-9]+)', 1) as digits, md5(c_name) as digest, length(c_name)::int as len, concat_ws('-', c_mktsegment, c_name) as both from customer")
def fn_string(spark, d):
    return T(spark, d, "customer", ["c_custkey", "c_name", "c_mktsegment"]).select(
        "c_custkey", F.lower("c_name").alias("low"), F.substring("c_name", 1, 8).alias("head"), F.regexp_extract("c_name", "([0-9]+)", 1).alias("digits"), F.md5("c_name").alias("digest"), F.length("c_name").alias("len"), F.concat_ws("-", "c_mktsegment", "c_name").alias("both")
    )


@reg.add("fn_date", "select o_orderkey, year(o_orderdate)::int as y, month(o_orderdate)::int as m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as first, date_diff('day', date '1995-01-01', o_orderdate::date)::int as days from orders")
def fn_date(spark, d):
    o = T(spark, d, "orders", ["o_orderkey", "o_orderdate"])
    return o.select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("first"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).alias("days"))


@reg.add("fn_math", "select p_partkey, round(log2(p_size), 9) as lg, round(exp(-p_size / 10.0), 9) as e, round(pow(2, -p_size), 12) as p, ceil(p_retailprice / 100)::bigint as up from part")
def fn_math(spark, d):
    return T(spark, d, "part", ["p_partkey", "p_size", "p_retailprice"]).select("p_partkey", F.round(F.log2("p_size"), 9).alias("lg"), F.round(F.exp(-F.col("p_size") / 10.0), 9).alias("e"), F.round(F.pow(F.lit(2.0), -F.col("p_size")), 12).alias("p"), F.ceil(F.col("p_retailprice") / 100).alias("up"))


@reg.add("fn_array", "select s_suppkey, list_sum(generate_series(1, s_suppkey % 5 + 1))::bigint as total, list_contains([1, 2, 3], s_suppkey % 5) as has, len(list_filter(generate_series(1, 10), lambda x: x % (s_suppkey % 3 + 1) = 0))::int as picked from supplier")
def fn_array(spark, d):
    k = F.col("s_suppkey")
    return T(spark, d, "supplier", ["s_suppkey"]).select(
        "s_suppkey", F.aggregate(F.sequence(F.lit(1).cast("long"), k % 5 + 1), F.lit(0).cast("long"), lambda a, x: a + x).alias("total"),
        F.exists(F.array(*(F.lit(i) for i in (1, 2, 3))), lambda x: x == k % 5).alias("has"), F.size(F.filter(F.sequence(F.lit(1), F.lit(10)), lambda x: x % (k % 3 + 1) == 0)).alias("picked"),
    )


@reg.add("fn_map", "select n_nationkey, n_regionkey as region, case when n_nationkey > 10 then 2 else 1 end::int as kept from nation")
def fn_map(spark, d):
    m = F.map_from_arrays(F.array(F.lit("region"), F.lit("nation")), F.array("n_regionkey", "n_nationkey"))
    kept = F.map_filter(m, lambda k, v: (k == "region") | (v > 10))
    return T(spark, d, "nation", ["n_nationkey", "n_regionkey"]).select("n_nationkey", m["region"].alias("region"), F.size(F.map_keys(kept)).alias("kept"))


@reg.add("fn_json", "select event_id, cast(json_extract(props, '$.k') as bigint) as k from events")
def fn_json(spark, d):
    e = T(spark, d, "events", ["event_id", "props"])
    return e.select("event_id", F.coalesce(F.from_json("props", "k long")["k"], F.get_json_object("props", "$.k").try_cast("long")).alias("k"))


@reg.add("fn_conditional", "select o_orderkey, case when o_totalprice > 300000 then 'high' when o_totalprice > 100000 then 'mid' else 'low' end as band, coalesce(nullif(o_orderstatus, 'P'), 'open') as st from orders")
def fn_conditional(spark, d):
    p = F.col("o_totalprice")
    return T(spark, d, "orders", _O).select("o_orderkey", F.when(p > 300000, "high").when(p > 100000, "mid").otherwise("low").alias("band"), F.coalesce(F.nullif("o_orderstatus", F.lit("P")), F.lit("open")).alias("st"))
