"""Queries on join processing: reduced scans, baselines, reduction factors and false positive rates."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import functions as F

from ..config import LARGE, SMALL, Predicate
from ..operators import baselines as B
from ..operators import pairs as P
from ..operators import probe as R
from ..plans import bounds, measures, star
from ..sources import tables as S
from ..workloads import star70, star70_arrays
from ..workloads.fixtures import FIXTURES, relation, relation_sql, spec_for
from . import sql as Q
from .registry import Registry

reg = Registry()
BIG = LARGE.with_(hash_family="portable", m=8192, l_max=4)
LITTLE = SMALL.with_(hash_family="portable", m=8192, l_max=4)

# --- the seventy queries


@reg.add("star70_instances", star70.instances_sql())
def star70_instances(spark, d):
    return star70.instances(spark, d)


@reg.add("star70_large", star70.instances_sql(BIG))
def star70_large(spark, d):
    return _instances(spark, d, BIG)


@reg.add("star70_small", star70.instances_sql(LITTLE))
def star70_small(spark, d):
    return _instances(spark, d, LITTLE)


@reg.add("star70_binned", f"select q, rel, m_exact, m_binned, round(m_binned / m_pred, 6) as rf_binned from ({star70.instances_sql()})")
def star70_binned(spark, d):
    return star70.instances(spark, d).select("q", "rel", "m_exact", "m_binned", measures.reduction_factor(F.col("m_binned"), F.col("m_pred")).alias("rf_binned"))


_made: dict = {}


def _instances(spark, d, base, fitted=False):
    """The instances of a base, written once for a session and read by all summaries of them."""
    key = (spark.sparkContext.applicationId, d, base, fitted)
    if key not in _made:
        _make(spark, d, [base], fitted)
    path, number = _made[key]
    rows = spark.read.parquet(path)
    return rows if number is None else rows.filter(F.col("base") == number).drop("base")


def _make(spark, d, bases, fitted=False):
    """Writes the instances of those bases that have none yet: together by print where arrays can be, else one by one."""
    session = (spark.sparkContext.applicationId, d)
    bases = [b for b in dict.fromkeys(bases) if (*session, b, fitted) not in _made]
    if not bases:
        return
    if star70_arrays.whole(spark, d) and star70_arrays.suits([star70.specs(b) for b in bases]):
        path = f"{S.shared_dir(spark)}/instances"
        rows = star70_arrays.by_prints(spark, d, min(b.key_bits for b in bases), bases[0].salt)
        if fitted:  # read for duplicates, and again for the sketches
            rows = star70_arrays.packed(rows).persist(StorageLevel.DISK_ONLY)
        chosen = [star70.sized(spark, d, b, rows) if fitted else star70.specs(b) for b in bases]
        star70_arrays.instances(spark, d, rows, chosen).write.parquet(path)
        if fitted:
            rows.unpersist()
        _made.update({(*session, b, fitted): (path, i) for i, b in enumerate(bases)})
        return
    if (*session, "own") not in _made:
        path = f"{S.shared_dir(spark)}/own"
        star70.coded_rows(spark, d).write.parquet(f"{path}/rows")
        star70.keyed(spark, d, spark.read.parquet(f"{path}/rows")).write.parquet(f"{path}/keys")
        _made[(*session, "own")] = path
    own = tuple(spark.read.parquet(f"{_made[(*session, 'own')]}/{part}") for part in ("rows", "keys"))
    for base in bases:
        path = f"{S.shared_dir(spark)}/instances"
        star70.instances(spark, d, star70.sized(spark, d, base) if fitted else base, own).write.parquet(path)
        _made[(*session, base, fitted)] = (path, None)


#: (variant, preset) -> base; every relation's sketch has the shape that its predicted entries need
FITTED = {(v, n): base.with_(variant=v) for v in ("chained", "hybrid", "bloomattr", "plain") for n, base in (("large", BIG), ("small", LITTLE))}

for (_v, _n), _base in FITTED.items():

    @reg.add(f"star70_{_v}_{_n}", star70.instances_sql(_base, fitted=True))
    def _of_variant(spark, d, base=_base):
        return _instances(spark, d, base, fitted=True)


def _shape_sql(v: str, n: str) -> str:
    base = FITTED[v, n]
    return " union all ".join(f"(select '{v}' as variant, '{n}' as preset, '{r}' as rel, m, b, entries, round(entries / (m * b), 6) as load, m * b * {bounds.entry_bits(s)} as bits from ({star70.shape_sql(r, s)}))" for r, s in star70.specs(base).items())


@reg.add("star70_shapes", " union all ".join(_shape_sql(*k) for k in FITTED))
def star70_shapes(spark, d):
    """Buckets, slots, predicted load and size of every relation's sketch, by variant and preset, from each relation's numbers of duplicates."""
    from ..plans import sizing

    out = []
    for r in star70.ROLES:
        counts = star70.duplicates(spark, d, r)
        for (v, n), base in FITTED.items():
            s = sizing.shape_of(counts, star70.specs(base)[r], shard=None)
            entries = sizing.predicted(counts, s)
            out.append((v, n, r, s.m, s.b, entries, round(entries / (s.m * s.b), 6), bounds.size_bits(s)))
    return spark.createDataFrame(out, "variant string, preset string, rel string, m long, b long, entries long, load double, bits long")


def _by_size_sql(v: str, n: str) -> str:
    t = f"select sum(m_pred) as p, sum(m_exact) as e, sum(m_binned) as bi, sum(m_keyonly) as ko, sum(m_sketch) as sk from ({star70.instances_sql(FITTED[v, n], fitted=True)})"
    return f"(select '{v}' as variant, '{n}' as preset, (select sum(bits) from ({_shape_sql(v, n)}))::bigint as bits, round(sk / p, 6) as rf_sketch, round(e / p, 6) as rf_exact, round(bi / p, 6) as rf_binned, round(ko / p, 6) as rf_keyonly, round((sk - e) / (p - e), 6) as fpr_exact, round((sk - bi) / (p - bi), 6) as fpr_binned from ({t}))"


@reg.add("rf_by_variant_and_size", " union all ".join(_by_size_sql(*k) for k in FITTED))
def rf_by_variant_and_size(spark, d):
    """Pooled reduction factor and false positive rate of the seventy queries, by variant and total size of the sketches."""
    _make(spark, d, FITTED.values(), fitted=True)
    out = None
    for (v, n), base in FITTED.items():
        t = _instances(spark, d, base, fitted=True).agg(*(F.sum(c).alias(c) for c in ("m_pred", *METHODS)))
        rf = [F.round(F.col(m) / F.col("m_pred"), 6).alias(m.replace("m_", "rf_")) for m in ("m_sketch", "m_exact", "m_binned", "m_keyonly")]
        fpr = [F.round((F.col("m_sketch") - F.col(e)) / (F.col("m_pred") - F.col(e)), 6).alias(e.replace("m_", "fpr_")) for e in ("m_exact", "m_binned")]
        one = t.select(F.lit(v).alias("variant"), F.lit(n).alias("preset"), *rf, *fpr)
        out = one if out is None else out.unionByName(one)
    return out.join(star70_shapes(spark, d).groupBy("variant", "preset").agg(F.sum("bits").alias("bits")), ["variant", "preset"])


METHODS = ["m_exact", "m_binned", "m_keyonly", "m_sketch"]


def _rf(c: str) -> str:
    return f"round({c} / m_pred, 6) as {c.replace('m_', 'rf_')}"


@reg.add("rf_per_instance", f"select q, rel, {', '.join(map(_rf, METHODS))} from ({star70.instances_sql(BIG)})")
def rf_per_instance(spark, d):
    rows = _instances(spark, d, BIG)
    return rows.select("q", "rel", *(measures.reduction_factor(F.col(c), F.col("m_pred")).alias(c.replace("m_", "rf_")) for c in METHODS))


def _pooled(c: str) -> str:
    return f"round(sum({c}) / sum(m_pred), 6) as {c.replace('m_', 'rf_')}, round(avg({c} / m_pred), 6) as {c.replace('m_', 'mean_')}"


for _name, _base in (("rf_overall", BIG), ("rf_overall_small", LITTLE)):

    @reg.add(_name, f"select count(*) as instances, {', '.join(map(_pooled, METHODS))} from ({star70.instances_sql(_base)})")
    def _overall(spark, d, base=_base):
        return measures.overall(_instances(spark, d, base), METHODS)


@reg.add("rf_by_join_count", f"select n_rel, count(*) as instances, {', '.join(f'round(sum({c}) / sum(m_pred), 6) as ' + c.replace('m_', 'rf_') for c in METHODS)} from ({star70.instances_sql(BIG)}) group by n_rel")
def rf_by_join_count(spark, d):
    return measures.by_joins(_instances(spark, d, BIG), METHODS)


_FPR = "select round((sum({s}) - sum({e})) / (sum(m_pred) - sum({e})), 6)"


@reg.add(
    "fpr_workload",
    f"select round((sum(m_sketch) - sum(m_exact)) / (sum(m_pred) - sum(m_exact)), 6) as fpr_exact, round((sum(m_sketch) - sum(m_binned)) / (sum(m_pred) - sum(m_binned)), 6) as fpr_binned, "
    f"round((sum(m_keyonly) - sum(m_exact)) / (sum(m_pred) - sum(m_exact)), 6) as fpr_keyonly from ({star70.instances_sql(BIG)})",
)
def fpr_workload(spark, d):
    t = _instances(spark, d, BIG).agg(*(F.sum(c).alias(c) for c in ("m_pred", *METHODS)))
    f = lambda s, e: measures.workload_fpr(F.col(s), F.col(e), F.col("m_pred"))
    return t.select(f("m_sketch", "m_exact").alias("fpr_exact"), f("m_sketch", "m_binned").alias("fpr_binned"), f("m_keyonly", "m_exact").alias("fpr_keyonly"))


@reg.add(
    "expected_output",
    f"select q, rel, round(m_exact + fpr * (m_pred - m_exact), 3) as expected from ({star70.instances_sql(BIG)}), (select (sum(m_sketch) - sum(m_exact)) / (sum(m_pred) - sum(m_exact)) as fpr from ({star70.instances_sql(BIG)}))",
)
def expected_output(spark, d):
    rows = _instances(spark, d, BIG)
    fpr = rows.agg(((F.sum("m_sketch") - F.sum("m_exact")) / (F.sum("m_pred") - F.sum("m_exact"))).alias("fpr"))
    return rows.crossJoin(fpr).select("q", "rel", F.round(bounds.expected_output(F.col("m_exact"), F.col("m_pred"), F.col("fpr")), 3).alias("expected"))


# --- single stars: own predicates as SQL, what sketches know of them

#: star -> relation -> (own predicate, allowed values)
STARS = {
    "example3": {"hdr": ("status = 'F'", {"status": ("F",)}), "disc": ("disc = 4", {"disc": (4,)}), "supp": ("lstatus = 'O'", {"lstatus": ("O",)})},
    "customer": {"cust": ("segment = 'BUILDING'", {"segment": ("BUILDING",)}), "co": ("status = 'F' and priority = '1-URGENT'", {"status": ("F",), "priority": ("1-URGENT",)}), "ev": ("kind = 'click' and day = 5", {"kind": ("click",), "day": (5,)})},
    "part": {"prt": ("size between 10 and 20", {"size": tuple(range(10, 21))}), "ps": ("supp = 7", {"supp": (7,)})},
    "supplier": {"sup": ("nation = 3", {"nation": (3,)}), "sp": ("part = 1500", {"part": (1500,)})},
    "documents": {"doc": ("lang = 'en'", {"lang": ("en",)}), "lab": ("quality = 1 and toxic = 0", {"quality": (1,), "toxic": (0,)})},
}
VARIANT = {"ev": "hybrid", "sp": "hybrid", "ps": "bloomattr", "co": "bloomattr"}


def _spec(name):
    return spec_for(name, BIG, small_values=True, variant=VARIANT.get(name, "chained"))


def _query(spark, d, which):
    parts = STARS[which]
    return star.StarQuery([star.Relation(n, relation(spark, d, n), own, Predicate(allowed)) for n, (own, allowed) in parts.items()])


def _catalog(spark, d, which):
    catalog = star.SketchCatalog()
    for n in STARS[which]:
        catalog.put(n, P.build(relation(spark, d, n), "k", _spec(n)))
    return catalog


def live_sql(name: str, allowed: dict, spec=None) -> str:
    s = spec or _spec(name)
    source = relation_sql(name)
    if s.variant == "chained":
        return f"(with {Q.chained(source, s)}, {Q.closed(s)}, {Q.live_chained(allowed, s)} select pair_id, kappa from live)"
    if s.variant == "bloomattr":
        return f"(with {Q.bloom(source, s)} select pair_id, kappa from entries where {Q.want_mask(allowed, s)})"
    bits, hashes = P.hybrid_bits(s), P.hybrid_hashes(s)
    return f"(with {Q.hybrid(source, s, bits, hashes)}, {Q.live_hybrid(allowed, s, bits, hashes)} select pair_id, kappa from live)"


def _star_sql(which: str) -> str:
    parts, out = STARS[which], []
    lives = ", ".join(f"live_{n} as {live_sql(n, allowed)}" for n, (_, allowed) in parts.items())
    for n, (own, _) in parts.items():
        rows = f"select * from ({relation_sql(n)}) where {own}"
        semi = " ".join(f"semi join live_{o} on live_{o}.pair_id = p.pair_id and live_{o}.kappa = p.kappa" for o in parts if o != n)
        exact = " and ".join(f"k in (select k from ({relation_sql(o)}) where {w})" for o, (w, _) in parts.items() if o != n)
        out.append(f"select '{n}' as rel, (select count(*) from ({rows})) as m_pred, (select count(*) from ({rows}) where {exact}) as m_exact, (select count(*) from ({Q.located(rows, BIG)}) p {semi}) as m_sketch")
    return f"with {lives} " + " union all ".join(out)


def _star(spark, d, which):
    query = _query(spark, d, which)
    pred = star.counts({r.name: r.scan() for r in query.relations}, "m_pred")
    exact = star.counts(star.exact_semijoin(query), "m_exact")
    return pred.join(exact, "rel").join(star.counts(star.reduce(query, _catalog(spark, d, which)), "m_sketch"), "rel")


for _which in STARS:

    @reg.add(f"star_{_which}", _star_sql(_which))
    def _one(spark, d, which=_which):
        return _star(spark, d, which)


def _join_sql(which: str) -> str:
    parts = STARS[which]
    first = next(iter(parts))
    cols = ", ".join(f"{n}.{a} as {n}_{a}" for n in parts for a in FIXTURES[n][2])
    tables = " join ".join(f"(select * from ({relation_sql(n)}) where {own}) {n}" + ("" if n == first else f" on {n}.k = {first}.k") for n, (own, _) in parts.items())
    return f"select {first}.k, {cols} from {tables}"


@reg.add("star_join_result", _join_sql("example3"))
def star_join_result(spark, d):
    """The join over reduced scans: the rows of the plain join."""
    return star.plan_join(_query(spark, d, "example3"), _catalog(spark, d, "example3"))


@reg.add("star_join_stored", _join_sql("example3"))
def star_join_stored(spark, d):
    """The same over sketches that were built before and stored with their closures."""
    return star.plan_join(_query(spark, d, "example3"), _catalog(spark, d, "example3").stored())


@reg.add("base_engine_bloom", _join_sql("example3"))
def base_engine_bloom(spark, d):
    """The plain join in which the engine injects its own Bloom filter of the smaller side at run time: one filter for each join, without predicates of other relations."""
    return B.engine_bloom(_query(spark, d, "example3"))


@reg.add("star_join_customer", _join_sql("customer"))
def star_join_customer(spark, d):
    return star.plan_join(_query(spark, d, "customer"), _catalog(spark, d, "customer"))


EQUALITIES = [("l_orderkey", "o_orderkey"), ("o_custkey", "c_custkey"), ("user_id", "c_custkey"), ("l_suppkey", "s_suppkey")]
COLUMNS = {"l_orderkey": "lineitem", "o_orderkey": "orders", "o_custkey": "orders", "c_custkey": "customer", "user_id": "events", "l_suppkey": "lineitem", "s_suppkey": "supplier"}
#: Smallest name of each class, and its members.
CLASSES = {"l_orderkey": ["l_orderkey", "o_orderkey"], "c_custkey": ["o_custkey", "c_custkey", "user_id"], "l_suppkey": ["l_suppkey", "s_suppkey"]}


def _reached_sql(col: str, name: str) -> str:
    held = " and ".join(f"{col} in (select {o} from {COLUMNS[o]} where {o} is not null)" for o in CLASSES[name] if o != col)
    return f"select '{col}' as col, '{name}' as class, count(distinct {col}) as n_keys, count(distinct {col}) filter ({held}) as reached from {COLUMNS[col]}"


@reg.add("star_transitive", " union all ".join(_reached_sql(c, name) for name, members in CLASSES.items() for c in members))
def star_transitive(spark, d):
    """Columns that filters reach through equalities: keys of each, and those that all columns of its class hold."""
    classes, out = star.equality_closure(EQUALITIES), None
    keys = {c: S.table(spark, d, t, [c]).select(F.col(c).alias("k")).filter("k is not null").distinct() for c, t in COLUMNS.items()}
    for name in sorted(set(classes.values())):
        own = sorted(c for c, n in classes.items() if n == name)
        met = None
        for c in own:
            one = keys[c].select("k", F.lit(1 << own.index(c)).alias("by"))
            met = one if met is None else met.unionByName(one)
        met = met.groupBy("k").agg(F.bit_or("by").alias("by"))
        for i, c in enumerate(own):
            has = F.col("by").bitwiseAND(1 << i) != 0
            one = met.agg(F.count_if(has).alias("n_keys"), F.count_if(F.col("by") == (1 << len(own)) - 1).alias("reached"))
            one = one.select(F.lit(c).alias("col"), F.lit(name).alias("class"), "n_keys", "reached")
            out = one if out is None else out.unionByName(one)
    return out


JOINT = spec_for("supp", BIG, small_values=True)
ONE_SUPP, ONE_STATUS = (spec_for("supp", BIG, small_values=True, only=(a,)) for a in ("supp", "lstatus"))
SUPP7 = {"supp": (7,), "lstatus": ("O",)}
ORDERS = "select o_orderkey as k from orders"


def _single_live(spec, allowed) -> str:
    source = f"select k, {', '.join(a.name for a in spec.attrs)} from ({relation_sql('supp')})"
    return f"(with {Q.chained(source, spec)}, {Q.closed(spec)}, {Q.live_chained(allowed, spec)} select pair_id, kappa from live)"


@reg.add(
    "star_joint_vs_single",
    f"with jo as {_single_live(JOINT, SUPP7)}, sa as {_single_live(ONE_SUPP, {'supp': (7,)})}, sb as {_single_live(ONE_STATUS, {'lstatus': ('O',)})}, p as ({Q.located(ORDERS, BIG)}) "
    "select (select count(*) from p semi join jo on jo.pair_id = p.pair_id and jo.kappa = p.kappa) as joint, "
    "(select count(*) from p semi join sa on sa.pair_id = p.pair_id and sa.kappa = p.kappa semi join sb on sb.pair_id = p.pair_id and sb.kappa = p.kappa) as single, "
    f"(select count(distinct k) from ({relation_sql('supp')}) where supp = 7 and lstatus = 'O') as exact",
)
def star_joint_vs_single(spark, d):
    """Orders that a joint sketch of two attributes leaves, and two single ones together."""
    rows = relation(spark, d, "supp")
    keys = S.table(spark, d, "orders", ["o_orderkey"]).withColumnRenamed("o_orderkey", "k")
    joint = R.contains(keys, "k", Predicate(SUPP7), P.build_chained(rows, "k", JOINT)).agg(F.count("*").alias("joint"))
    one = R.contains(keys, "k", Predicate({"supp": (7,)}), P.build_chained(rows, "k", ONE_SUPP))
    both = R.contains(one, "k", Predicate({"lstatus": ("O",)}), P.build_chained(rows, "k", ONE_STATUS)).agg(F.count("*").alias("single"))
    return joint.crossJoin(both).crossJoin(rows.filter("supp = 7 and lstatus = 'O'").select("k").distinct().agg(F.count("*").alias("exact")))


# --- baselines


@reg.add("base_predicate_rows", " union all ".join(f"select '{n}' as rel, count(*) as m_pred from ({relation_sql(n)}) where {own}" for n, (own, _) in STARS["example3"].items()))
def base_predicate_rows(spark, d):
    return B.predicate_rows(_query(spark, d, "example3"))


def _exact_sql(which: str) -> str:
    parts = STARS[which]
    return " union all ".join(
        f"select '{n}' as rel, count(*) as m_exact from ({relation_sql(n)}) where {own} and " + " and ".join(f"k in (select k from ({relation_sql(o)}) where {w})" for o, (w, _) in parts.items() if o != n) for n, (own, _) in parts.items()
    )


@reg.add("base_exact_semijoin", _exact_sql("example3"))
def base_exact_semijoin(spark, d):
    return B.exact_semijoin(_query(spark, d, "example3"))


@reg.add("base_exact_binned", f"select 'qty' as rel, count(*) as m_binned from ({relation_sql('qty')}) where qty = 17 and k in (select k from ({relation_sql('hdr')}) where bin between 6 and 9)")
def base_exact_binned(spark, d):
    """Lines of quantity 17 whose order's month lies in 33..47, seen by bins of five months."""
    hdr = relation(spark, d, "hdr").filter("bin between 6 and 9")
    return B.exact_binned("qty", relation(spark, d, "qty").filter("qty = 17"), hdr)


def _others_sql(which: str, name: str) -> str:
    parts, out = STARS[which], []
    lives = ", ".join(f"live_{n} as (select distinct pair_id, kappa from ({Q.located(relation_sql(n), BIG)}))" for n in parts)
    for n, (own, _) in parts.items():
        semi = " ".join(f"semi join live_{o} on live_{o}.pair_id = p.pair_id and live_{o}.kappa = p.kappa" for o in parts if o != n)
        rows = f"select * from ({relation_sql(n)}) where {own}"
        out.append(f"select '{n}' as rel, (select count(*) from ({Q.located(rows, BIG)}) p {semi}) as {name}")
    return f"with {lives} " + " union all ".join(out)


@reg.add("base_keyonly", _others_sql("customer", "m_keyonly"))
def base_keyonly(spark, d):
    return B.keyonly(_query(spark, d, "customer"), BIG)


@reg.add("base_paf_nopred", _others_sql("customer", "m_nopred"))
def base_paf_nopred(spark, d):
    """The predicate-aware sketches asked for keys alone: the same as key-only filters."""
    return B.without_predicates(_query(spark, d, "customer"), _catalog(spark, d, "customer"))


FB, FH = 1 << 17, 6


def _places(e: str) -> str:
    return "[" + ", ".join(f"({Q.h(e, f'filter{j}')} % {FB})" for j in range(FH)) + "]"


@reg.add("base_bloom", f"with bits as (select distinct unnest({_places('k')}) as b from (select distinct user_id as k from events)), c as (select c_custkey as k, unnest({_places('c_custkey')}) as b from customer) select k from c group by k having bool_and(b in (select b from bits))")
def base_bloom(spark, d):
    """Customers that a classical prebuilt filter of event users lets through."""
    words = B.bloom_build(S.table(spark, d, "events", ["user_id"]).select(F.col("user_id").alias("k")), "k", FB, FH, "portable")
    return B.bloom_probe(S.table(spark, d, "customer", ["c_custkey"]).select(F.col("c_custkey").alias("k")), "k", words, FB, FH, "portable")


@reg.add("base_per_value_filters", f"select disc, count(distinct k) as n_keys from ({relation_sql('disc')}) group by disc")
def base_per_value_filters(spark, d):
    """One filter for each value: keys that each of them has to hold."""
    return B.per_value(relation(spark, d, "disc"), "k", ["disc"])


@reg.add("base_per_value_probe", f"with f as (select disc, pair_id, kappa from ({Q.located(relation_sql('disc'), BIG)}) group by all) select disc, count(*) as passed from (select distinct k, pair_id, kappa from ({Q.located(ORDERS, BIG)})) p join f on f.pair_id = p.pair_id and f.kappa = p.kappa group by disc")
def base_per_value_probe(spark, d):
    """Orders that each value's own key filter lets through."""
    from ..functions.hashing import locate

    f = locate(relation(spark, d, "disc"), "k", BIG).select("disc", "pair_id", "kappa").distinct()
    p = locate(S.table(spark, d, "orders", ["o_orderkey"]).withColumnRenamed("o_orderkey", "k"), "k", BIG).select("k", "pair_id", "kappa")
    return p.join(f, ["pair_id", "kappa"]).groupBy("disc").agg(F.count("*").alias("passed"))


# --- false positive rates

ABSENT = "select range as k from range(1000000, 1020000)"
EV = spec_for("ev", BIG, variant="keyonly", m=2048, key_bits=8)


def _absent(spark):
    return spark.range(1_000_000, 1_020_000).withColumnRenamed("id", "k")


SMALLKEYS = BIG.with_(variant="keyonly", m=4096, key_bits=7)


@reg.add("fpr_key_measured", f"with live as (select distinct pair_id, kappa from ({Q.located(ORDERS, SMALLKEYS)})) select 20000::bigint as asked, (select count(*) from ({Q.probe(ABSENT, SMALLKEYS)})) as passed")
def fpr_key_measured(spark, d):
    keys = S.table(spark, d, "orders", ["o_orderkey"]).withColumnRenamed("o_orderkey", "k")
    hit = R.contains_key(_absent(spark), "k", P.build_keyonly(keys, "k", SMALLKEYS)).agg(F.count("*").alias("passed"))
    return _absent(spark).agg(F.count("*").alias("asked")).crossJoin(hit)


@reg.add(
    "fpr_key_bound",
    f"with g as (select pair_id, kappa from ({Q.located(ORDERS, SMALLKEYS)}) group by all), n as (select pair_id, count(*) as filled from g group by all), p as (select count(*) as asked, sum(coalesce(filled, 0)) as filled from ({Q.located(ABSENT, SMALLKEYS)}) a left join n on n.pair_id = a.pair_id) select round(filled / asked / {1 << SMALLKEYS.key_bits}, 9) as bound from p",
)
def fpr_key_bound(spark, d):
    """The expected filled entries of the pairs that absent keys look at, by 2^-bits."""
    from ..functions.hashing import locate

    keys = S.table(spark, d, "orders", ["o_orderkey"]).withColumnRenamed("o_orderkey", "k")
    filled = P.build_keyonly(keys, "k", SMALLKEYS).entries.groupBy("pair_id").agg(F.count("*").alias("filled"))
    asked = locate(_absent(spark), "k", SMALLKEYS).join(filled, "pair_id", "left")
    return asked.agg(F.round(F.sum(F.coalesce("filled", F.lit(0))) / F.count("*") / (1 << SMALLKEYS.key_bits), 9).alias("bound"))


QTYB = spec_for("qty", BIG, variant="bloomattr")
QTYC = spec_for("qty", BIG, variant="chained", attr_bits=4)
_WITHOUT = f"select k from ({relation_sql('qty')}) group by k having not bool_or(qty = 17)"


@reg.add(
    "fpr_pred_measured",
    f"with asked_ as (select count(*) as asked from ({_WITHOUT})), b as (with live as {live_sql('qty', {'qty': (17,)}, QTYB)} select count(*) as bloomattr from ({Q.probe(_WITHOUT, QTYB)})), c as (with live as {live_sql('qty', {'qty': (17,)}, QTYC)} select count(*) as chained from ({Q.probe(_WITHOUT, QTYC)})) select asked, bloomattr, chained from asked_, b, c",
)
def fpr_pred_measured(spark, d):
    """Keys with lines but none of quantity 17, and how many of them two sketches let through."""
    rows = relation(spark, d, "qty")
    without = rows.groupBy("k").agg(F.max((F.col("qty") == 17).cast("int")).alias("has")).filter("has = 0").select("k")
    out = without.agg(F.count("*").alias("asked"))
    for spec in (QTYB, QTYC):
        out = out.crossJoin(R.contains(without, "k", Predicate({"qty": (17,)}), P.build(rows, "k", spec)).agg(F.count("*").alias(spec.variant)))
    return out


@reg.add(
    "fpr_pred_bound",
    f"with v as (select k, count(distinct qty) as n from ({relation_sql('qty')}) group by k having not bool_or(qty = 17)) select round(avg(pow(1 - pow(1 - 1 / {QTYB.bloom_bits}.0, {QTYB.bloom_hashes} * n), {QTYB.bloom_hashes})), 6) as bloomattr, round(avg(n) * pow(2, -{QTYC.attr_bits}), 6) as chained from v",
)
def fpr_pred_bound(spark, d):
    """The bounds for the same keys: masks by their items, vectors by the entries looked at."""
    v = relation(spark, d, "qty").groupBy("k").agg(F.countDistinct("qty").alias("n"), F.max((F.col("qty") == 17).cast("int")).alias("has")).filter("has = 0")
    h, s = QTYB.bloom_hashes, QTYB.bloom_bits
    mask = F.pow(1 - F.pow(F.lit(1 - 1 / s), h * F.col("n")), F.lit(h))
    return v.agg(F.round(F.avg(mask), 6).alias("bloomattr"), F.round(F.avg("n") * 2.0**-QTYC.attr_bits, 6).alias("chained"))


CUST_KEYS = "select c_custkey as k from customer"
EVB = spec_for("ev", BIG, variant="bloomattr", m=2048, key_bits=7, bloom_bits=12, bloom_hashes=2)


@reg.add(
    "fp_blame",
    f"with live as {live_sql('ev', {'kind': ('click',)}, EVB)}, hit as (select p.k from ({Q.located(CUST_KEYS, EVB)}) p semi join live l on l.pair_id = p.pair_id and l.kappa = p.kappa), t as (select distinct k from ({relation_sql('ev')}) where kind = 'click'), any_ as (select distinct k from ({relation_sql('ev')})) "
    "select (select count(*) from hit) as passed, (select count(*) from hit where k not in (select k from t)) as false_positives, (select count(*) from hit where k not in (select k from any_)) as by_key, (select count(*) from hit where k in (select k from any_) and k not in (select k from t)) as by_attribute",
)
def fp_blame(spark, d):
    """False positives among customers by cause: the key print, or the attribute sketch of a present key."""
    rows = relation(spark, d, "ev")
    keys = S.table(spark, d, "customer", ["c_custkey"]).withColumnRenamed("c_custkey", "k")
    hit = R.contains(keys, "k", Predicate({"kind": ("click",)}), P.build_bloomattr(rows, "k", EVB))
    true = rows.filter("kind = 'click'").select("k", F.lit(1).alias("t")).distinct()
    present = rows.select("k", F.lit(1).alias("p")).distinct()
    f = hit.join(true, "k", "left").join(present, "k", "left")
    n = lambda c: F.coalesce(F.sum(c.cast("long")), F.lit(0))
    return f.agg(F.count("*").alias("passed"), n(F.col("t").isNull()).alias("false_positives"), n(F.col("p").isNull()).alias("by_key"), n(F.col("t").isNull() & F.col("p").isNotNull()).alias("by_attribute"))


GRID = [(k, a, v) for k in (7, 12) for a in (4, 8) for v in ("chained", "hybrid")] + [(k, s, "bloomattr") for k in (7, 12) for s in (4, 12, 24)]


def _grid_spec(k, a, v):
    return spec_for("qty", BIG, variant=v, key_bits=k, **({"bloom_bits": a, "bloom_hashes": 2} if v == "bloomattr" else {"attr_bits": a}))


def _grid_row(k, a, v) -> str:
    s = _grid_spec(k, a, v)
    return f"(select '{v}' as variant, {k} as key_bits, {a} as attr_bits, {bounds.entry_bits(s)} as entry_bits, (with live as {live_sql('qty', {'qty': (17,)}, s)} select count(*) from ({Q.probe(ORDERS, s)})) as passed)"


@reg.add("grid_small_large", " union all ".join(_grid_row(*g) for g in GRID))
def grid_small_large(spark, d):
    """Orders that pass for quantity 17, over key, attribute and mask sizes."""
    rows = relation(spark, d, "qty")
    keys = S.table(spark, d, "orders", ["o_orderkey"]).withColumnRenamed("o_orderkey", "k")
    out = None
    for k, a, v in GRID:
        spec = _grid_spec(k, a, v)
        one = R.contains(keys, "k", Predicate({"qty": (17,)}), P.build(rows, "k", spec)).agg(F.count("*").alias("passed"))
        one = one.select(F.lit(v).alias("variant"), F.lit(k).alias("key_bits"), F.lit(a).alias("attr_bits"), F.lit(bounds.entry_bits(spec)).alias("entry_bits"), "passed")
        out = one if out is None else out.unionByName(one)
    return out
