"""Seventy star queries over the order star, by fixed arithmetic from the query number.

All queries run together: each relation is scanned once, and what a value, a key or a group of a sketch means to the
seventy queries is a mask of 70 bits in two numbers, so rows are never multiplied by queries.
"""

from __future__ import annotations

from itertools import combinations

SATELLITES = ("disc", "supp", "qty", "line", "part")


def n_relations(q: int) -> int:
    return 2 if q < 12 else 3 if q < 38 else 4 if q < 63 else 5


def query(q: int, n_supp: int, n_part: int) -> dict:
    """Relations of a query with their literals; month ranges are closed, None is open."""
    n = n_relations(q)
    combos = list(combinations(SATELLITES, n - 1))
    months = None
    if q % 14 < 11:
        months = {0: (20 + q % 40, None), 1: (None, 30 + q % 40), 2: (q % 40, q % 40 + 24)}[q % 3]
    literals = {
        "disc": {"disc": 3 * q % 11},
        "qty": {"qty": 1 + 7 * q % 50},
        "line": {"line": 1 + 5 * q % 7},
        "supp": {"lstatus": "FO"[q // 2 % 2]} | ({"supp": 13 * q % n_supp} if q % 2 else {}),
        "part": {"part": 37 * q % n_part},
    }
    return {"q": q, "n_rel": n, "status": "FOP"[q % 3], "months": months, "satellites": {s: literals[s] for s in combos[7 * q % len(combos)]}}


def queries(n_supp: int = 100, n_part: int = 2000) -> list[dict]:
    return [query(q, n_supp, n_part) for q in range(70)]


# --- all queries at once, as DataFrames

#: Queries in one number of a mask.
HALF = 35
ATTRS = {"disc": ("disc",), "supp": ("supp", "lstatus"), "qty": ("qty",), "line": ("line",), "part": ("part",)}
#: What a row's code holds, eight bits each: the number of its value among the literals, 0 if it is none of them.
FIELDS = {"disc": ("disc",), "qty": ("qty",), "line": ("line",), "part": ("part",), "both": ("supp", "lstatus"), "lstatus": ("lstatus",), "orders": ("status", "mon")}
#: Which fields a relation's rows are matched by.
MATCHED = {"orders": ("orders",), "disc": ("disc",), "supp": ("both", "lstatus"), "qty": ("qty",), "line": ("line",), "part": ("part",)}


def halves(qs) -> tuple[int, int]:
    qs = set(qs)
    return sum(1 << q for q in qs if q < HALF), sum(1 << (q - HALF) for q in qs if q >= HALF)


def _told(spark, d) -> list[dict]:
    from ..sources.tables import table

    return queries(table(spark, d, "supplier").count(), table(spark, d, "part").count())


def _literals(spark, d):
    """(orders literals, satellite literals by role): rows with the query number; None means no condition."""
    told = _told(spark, d)
    orders = [(t["q"], t["n_rel"], t["status"], *(t["months"] or (None, None))) for t in told]
    rows = {s: [(t["q"], t["n_rel"], *(t["satellites"][s].get(a) for a in ATTRS[s])) for t in told if s in t["satellites"]] for s in SATELLITES}
    kinds = {a: "string" if a == "lstatus" else "long" for s in SATELLITES for a in ATTRS[s]}
    return (
        spark.createDataFrame(orders, "q int, n_rel int, status string, lo int, hi int"),
        {s: spark.createDataFrame(rows[s], "q int, n_rel int, " + ", ".join(f"w_{a} {kinds[a]}" for a in ATTRS[s])) for s in SATELLITES},
    )


def _fields(told: list[dict]) -> dict[str, dict[tuple, tuple[int, int]]]:
    """field -> value -> mask of the queries whose literal it is; `near`: months that lie in a bin that the range touches."""
    out: dict[str, dict] = {f: {} for f in (*FIELDS, "near")}
    for t in told:
        for s, values in t["satellites"].items():
            field = s if s != "supp" else "both" if "supp" in values else "lstatus"
            out[field].setdefault(tuple(values[a] for a in FIELDS[field]), []).append(t["q"])
        lo, hi = (x if x is not None else o for x, o in zip(t["months"] or (None, None), (0, 79), strict=True))
        for mon in range(lo // 5 * 5, hi // 5 * 5 + 5):
            out["near"].setdefault((t["status"], mon), []).append(t["q"])
            out["orders"].setdefault((t["status"], mon), []).extend([t["q"]] if lo <= mon <= hi else [])
    return {f: {v: halves(qs) for v, qs in values.items()} for f, values in out.items()}


#: What columns the values of a relation's attributes are in, in rows that keep them.
VALUES = {"orders": ("t", "i0"), "disc": ("i0",), "supp": ("i1", "t"), "qty": ("i2",), "line": ("i3",), "part": ("i4",)}
VALUE_COLUMNS = ("i0", "i1", "i2", "i3", "i4", "t")


def _valued(spark, d) -> dict[str, dict[str, object]]:
    """table -> column of `VALUE_COLUMNS` -> expression of the attribute that is kept there."""
    from pyspark.sql import functions as F

    from .fixtures import FIXTURES

    out: dict[str, dict] = {}
    for r, columns in VALUES.items():
        source, _, attrs, _ = FIXTURES[fixture(r)]
        out.setdefault(source, {}).update(zip(columns, map(F.expr, attrs.values()), strict=True))
    return out


def coded_rows(spark, d, values: bool = False):
    """(k, code): every row of lineitem and of orders, with the numbers of its values among the literals; bit 56 marks orders.

    `values`: also what the relations' attributes hold, as `VALUES` says.
    """
    from pyspark.sql import functions as F

    from ..sources.tables import table
    from .fixtures import FIXTURES, MONTH

    fields = _fields(_told(spark, d))
    lines = {a: F.expr(e) for s in SATELLITES for a, e in FIXTURES[s][2].items()}
    sides = {
        "lineitem": ("l_orderkey", lines, [f for f in FIELDS if f != "orders"], 0),
        "orders": ("o_orderkey", {"status": F.col("o_orderstatus"), "mon": F.expr(MONTH)}, ["orders"], 1 << 56),
    }
    out = None
    for name, (key, columns, own, mark) in sides.items():
        kept = {c: e.cast("string" if c == "t" else "bigint").alias(c) for c, e in _valued(spark, d)[name].items()} if values else {}
        none = [F.lit(None).cast("string" if c == "t" else "bigint").alias(c) for c in VALUE_COLUMNS if values and c not in kept]
        rows = table(spark, d, name).select(F.col(key).alias("k"), *kept.values(), *none, *(c.alias(a) for a, c in columns.items())).withColumn("code", F.lit(mark).cast("bigint"))
        for f in own:
            kinds = ["string" if a in ("status", "lstatus") else "long" for a in FIELDS[f]]
            names = [(*v, i << 8 * list(FIELDS).index(f)) for i, v in enumerate(fields[f], 1)]
            told = spark.createDataFrame(names, ", ".join(f"w_{a} {k}" for a, k in zip(FIELDS[f], kinds, strict=True)) + ", own long")
            on = [F.col(a) == F.col(f"w_{a}") for a in FIELDS[f]]
            rows = rows.join(F.broadcast(told), on, "left").withColumn("code", F.col("code").bitwiseOR(F.coalesce("own", F.lit(0)))).drop("own", *(f"w_{a}" for a in FIELDS[f]))
        one = rows.select("k", "code", *(VALUE_COLUMNS if values else ()))
        out = one if out is None else out.unionByName(one)
    return out


def _mask_of(code, field: str, values: dict, half: int):
    """The mask of a row's value in a field, from its code."""
    from pyspark.sql import functions as F

    place = list(FIELDS).index("orders" if field == "near" else field)
    masks = [0, *(m[half] for m in values.values())]
    return F.get(F.array(*(F.lit(m).cast("bigint") for m in masks)), F.shiftright(code, 8 * place).bitwiseAND(F.lit(255)).cast("int"))


def keyed(spark, d, rows):
    """(k, ex0, ex1, wi0, wi1, in_l, in_o): the queries all of whose relations hold a key, exactly and with orders seen by bins."""
    from pyspark.sql import functions as F

    told = _told(spark, d)
    fields = _fields(told)
    code = F.col("code")
    is_order = F.shiftright(code, 56) == 1
    sums = [F.max(is_order).alias("in_o"), F.max(~is_order).alias("in_l")]
    for h in (0, 1):
        for r, own in (MATCHED | {"near": ("near",)}).items():
            mask = F.lit(0).cast("bigint")
            for f in own:
                mask = mask.bitwiseOR(_mask_of(code, f, fields[f], h))
            sums.append(F.bit_or(mask).alias(f"{r}{h}"))
    keys = rows.filter("k is not null").groupBy("k").agg(*sums)
    every = halves(range(len(told)))
    out = []
    for h in (0, 1):
        for name, first in (("ex", "orders"), ("wi", "near")):
            held = F.col(f"{first}{h}")
            for s in SATELLITES:
                others = halves(t["q"] for t in told if s not in t["satellites"])
                held = held.bitwiseAND(F.col(f"{s}{h}").bitwiseOR(F.lit(others[h]).cast("bigint")))
            out.append(held.bitwiseAND(F.lit(every[h]).cast("bigint")).alias(f"{name}{h}"))
    return keys.select("k", *out, "in_l", "in_o")


ROLES = ("orders", *SATELLITES)


def fixture(role: str) -> str:
    return "hdr" if role == "orders" else role


def specs(base) -> dict:
    """The spec of every relation's sketch in a base's variant and widths."""
    from .fixtures import spec_for

    return {r: spec_for(fixture(r), base, small_values=True) for r in ROLES}


def sized(spark, d, base, rows=None) -> dict:
    """The same with the least shape for the entries that each relation's duplicates predict: one sketch of each, whatever its size."""
    from ..plans import sizing

    return {role: sizing.shape_of(duplicates(spark, d, role, rows), spec, shard=None) for role, spec in specs(base).items()}


_counted: dict = {}


def duplicates(spark, d, role: str, rows=None) -> dict[int, int]:
    """How many keys of a relation have so many vectors; counted once for a session, for sketches of all variants.

    `rows` is what `by_prints` or `packed` gives, where it is at hand; all relations are counted together where arrays can be.
    """
    from ..plans import sizing
    from . import star70_arrays as together
    from .fixtures import FIXTURES, relation

    name = (spark.sparkContext.applicationId, d, role)
    if name not in _counted and together.whole(spark, d):
        counts = together.duplicates(together.by_prints(spark, d) if rows is None else rows)
        _counted.update({(*name[:2], r): counts.get(r, {}) for r in ROLES})
    elif name not in _counted:
        _counted[name] = sizing.histogram(sizing.per_key(relation(spark, d, fixture(role)), "k", list(FIXTURES[fixture(role)][2])))
    return _counted[name]


def _wanted(spark, d, role, spec):
    """Parts of (q, codes c_i, mask w) of a relation's literals, each with the places that have a code."""
    from pyspark.sql import functions as F

    from ..functions.attrs import attr_print, item_mask
    from ..operators.pairs import hybrid_bits, hybrid_hashes

    lit, lits = _literals(spark, d)
    if role == "orders":
        bins = F.explode(F.sequence(F.floor(F.coalesce("lo", F.lit(0)) / 5), F.floor(F.coalesce("hi", F.lit(79)) / 5)))
        values = lit.select("q", F.col("status").alias("v0"), bins.alias("v1")).withColumn("v1", F.col("v1").cast("bigint"))
        parts = [(values, (0, 1))]
    elif role == "supp":
        values = lits[role].select("q", F.col("w_supp").alias("v0"), F.col("w_lstatus").alias("v1"))
        parts = [(values.filter("v0 is null"), (1,)), (values.filter("v0 is not null"), (0, 1))]
    else:
        parts = [(lits[role].select("q", F.col(f"w_{ATTRS[role][0]}").alias("v0")), (0,))]
    out = []
    for values, places in parts:
        code = {i: attr_print(F.col(f"v{i}"), i, spec, spec.attrs[i]) for i in places}
        mask = F.lit(0).cast("bigint")
        for i in places:
            mask = mask.bitwiseOR(item_mask(code[i], i, spec, hybrid_bits(spec), hybrid_hashes(spec)) if spec.variant == "hybrid" else item_mask(F.col(f"v{i}"), i, spec))
        out.append((values.select("q", *(c.alias(f"c{i}") for i, c in code.items()), mask.alias("w")), places))
    return out


def _by_print(wanted) -> list[tuple[dict, tuple]]:
    """(codes -> mask, places) of each part of the literals."""
    out = []
    for want, places in wanted:
        found: dict[tuple, list] = {}
        for r in want.collect():
            found.setdefault(tuple(r[f"c{i}"] for i in places), []).append(r["q"])
        out.append(({c: halves(qs) for c, qs in found.items()}, places))
    return out


def _met_by_masks(groups, found: dict[int, tuple[int, int]], most: int):
    """(GROUP, l0, l1): groups of more than `most` vectors by their Bloom masks, one mask of literals at a time; others keep l0 and l1."""
    import numpy as np
    import pyarrow as pa

    from ..operators.pairs import GROUP

    def run(batches):
        for batch in batches:
            mask, n, *own = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("mask", "n", "l0", "l1"))
            met = [np.zeros(len(mask), np.int64) for _ in own]
            for w, queries in found.items():
                hit = -((mask & w) == w).astype(np.int64)  # all bits or none
                for m, q in zip(met, queries, strict=True):
                    if q:
                        m |= hit & q
            out = [np.where(n > most, m, o) for m, o in zip(met, own, strict=True)]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in GROUP), *map(pa.array, out)], [*GROUP, "l0", "l1"])

    return groups.select(*GROUP, "mask", "n", "l0", "l1").mapInArrow(run, "shard int, pair_id bigint, kappa int, l0 bigint, l1 bigint")


def live_masks(spark, d, role: str, spec):
    """(shard, pair_id, kappa, l0, l1): the queries under whose literals a group of a relation's sketch is left.

    Vectors meet the literals by their codes, masks one by one. Each group is one row, however many queries leave it.
    """
    from pyspark.sql import functions as F

    from ..operators import chains
    from ..operators import pairs as P
    from ..operators.probe import close
    from .fixtures import relation

    wanted = _wanted(spark, d, role, spec)
    group, zero = P.GROUP, F.lit(0).cast("bigint")

    def of_vectors(entries, *more):
        for n, (found, places) in enumerate(_by_print(wanted)):
            told = spark.createDataFrame([(*c, *m) for c, m in found.items()], ", ".join([*(f"c{i} int" for i in places), f"x{n}0 long", f"x{n}1 long"]))
            entries = entries.join(F.broadcast(told), [F.col(f"a_{i}") == F.col(f"c{i}") for i in places], "left").drop(*(f"c{i}" for i in places))
        parts = []
        for h in (0, 1):
            m = zero
            for n in range(len(wanted)):
                m = m.bitwiseOR(F.coalesce(f"x{n}{h}", zero))
            parts.append(F.bit_or(m).alias(f"l{h}"))
        return entries.groupBy(*group).agg(*parts, *more)

    def of_masks(entries):
        found: dict[int, list] = {}
        for want, _ in wanted:
            for r in want.select("q", "w").collect():
                found.setdefault(r["w"], []).append(r["q"])
        return _met_by_masks(entries, {w: halves(qs) for w, qs in found.items()}, spec.d)

    rows = relation(spark, d, fixture(role))
    if spec.variant == "hybrid":  # what the sketch would hold of a group and what the literals meet there, in one aggregate
        out = of_masks(of_vectors(P.vectors(rows, "k", spec), F.count("*").alias("n"), F.bit_or(P.print_mask(spec)).alias("mask")))
        return out.filter("l0 <> 0 or l1 <> 0")
    if spec.variant == "chained" and P.by_arrays(rows, spec):
        always = halves(r["q"] for want, _ in wanted for r in want.select("q").distinct().collect())
        return P.chained_masks(rows, "k", spec, _by_print(wanted), always)
    sketch = P.build(rows, "k", spec)
    if spec.variant == "plain":
        out = of_vectors(sketch.entries)
    elif spec.variant == "chained":
        always = halves(r["q"] for want, _ in wanted for r in want.select("q").distinct().collect())
        if chains.suits(spec):
            out = P.walked(of_vectors(sketch.entries, F.count("*").alias("n")).select(*group, "l0", "l1", (F.col("n") >= spec.d).alias("full")), spec, ["l0", "l1"])
        else:
            closed = close(sketch)
            own = of_vectors(closed.select(*group, F.explode("payloads").alias("p")).select(*group, "p.*"))
            out = own.join(closed.select(*group, "saturated"), group)
        out = out.select(*group, *(F.when(F.col("saturated"), F.lit(always[h]).cast("bigint")).otherwise(F.col(f"l{h}")).alias(f"l{h}") for h in (0, 1)))
    else:
        out = of_masks(sketch.entries.select(*group, "mask", zero.alias("l0"), zero.alias("l1"), F.lit(spec.d + 1).cast("bigint").alias("n")))
    return out.filter("l0 <> 0 or l1 <> 0")


def own_rows(spark, d):
    """(rows by code, what the relations hold of each key)."""
    rows = coded_rows(spark, d)
    return rows, keyed(spark, d, rows)


def _passed(spark, d, keys, chosen: dict, told: list[dict]):
    """keys with p_<relation>0 and 1, the queries whose other relations' sketches let a key through, and key-only answers."""
    from pyspark.sql import functions as F

    from ..functions.hashing import locate
    from ..operators import places
    from ..operators.pairs import GROUP

    zero = F.lit(0).cast("bigint")
    shapes: dict = {}  # relations of one shape share their keys' places
    for role, spec in chosen.items():
        shapes.setdefault((spec.m, spec.shards, spec.key_bits, spec.salt, spec.hash_family), []).append(role)
    for roles in shapes.values():
        first = chosen[roles[0]]
        spot = places.placed(keys, "k", first) if first.hash_family == "portable" else locate(keys, "k", first)
        names, live = [f"{r}{h}" for r in roles for h in (0, 1)], None
        asked = [(c, of) for c, of, r in (("by_lines", "in_l", "disc"), ("by_orders", "in_o", "orders")) if r in roles]
        for r in roles:
            one = live_masks(spark, d, r, chosen[r])
            one = one.select(*GROUP, *((F.col(f"l{n[-1]}") if n[:-1] == r else zero).alias(n) for n in names), *(F.lit(False).alias(c) for c, _ in asked))
            live = one if live is None else live.unionByName(one)
        if asked:
            live = live.unionByName(spot.select(*GROUP, *(zero.alias(n) for n in names), *(F.col(of).alias(c) for c, of in asked)))
        live = live.groupBy(*GROUP).agg(*(F.bit_or(n).alias(n) for n in names), *(F.max(c).alias(c) for c, _ in asked))
        keys = spot.join(live, GROUP, "left").drop(*GROUP)
    out = []
    for r in chosen:
        for h in (0, 1):
            held = F.lit(halves(range(len(told)))[h]).cast("bigint")
            for by in chosen:
                if by != r:
                    others = () if by == "orders" else (t["q"] for t in told if by not in t["satellites"])
                    held = held.bitwiseAND(F.coalesce(f"{by}{h}", zero).bitwiseOR(F.lit(halves(others)[h]).cast("bigint")))
            out.append(held.alias(f"p_{r}{h}"))
    return keys.select("k", "ex0", "ex1", "wi0", "wi1", "by_lines", "by_orders", *out)


def _counter(fields: dict, with_sketch: bool):
    """A function over Arrow batches of rows with their keys' masks: partial counts of every (query, relation)."""
    import numpy as np
    import pyarrow as pa

    places = {f: 8 * i for i, f in enumerate(FIELDS)}
    masks = {f: [[0, *(m[h] for m in fields[f].values())] for h in (0, 1)] for f in FIELDS}
    most = 1 << 18

    def chunks(batches):
        held, n = [], 0
        for b in batches:
            held.append(b)
            n += b.num_rows
            if n >= most:
                yield pa.Table.from_batches(held).combine_chunks()
                held, n = [], 0
        if held:
            yield pa.Table.from_batches(held).combine_chunks()

    def run(batches):
        total = np.zeros((2 * HALF, len(ROLES), 5), np.int64)
        for t in chunks(batches):
            column = {c: t[c].to_numpy() for c in t.column_names}
            code = column["code"]
            of_orders = (code >> 56) == 1
            for i, role in enumerate(ROLES):
                one, *more = ((code >> places[f]) & 255 for f in MATCHED[role])
                kind = (one | more[0] << 8 if more else one).astype(np.uint16)
                if role != "orders":
                    kind[of_orders] = 0
                order = np.argsort(kind, kind="stable")
                values, starts = np.unique(kind[order], return_index=True)
                for v, lo, hi in zip(values.tolist(), starts.tolist(), [*starts[1:].tolist(), len(kind)], strict=True):
                    for h in (0, 1):
                        mask = masks[MATCHED[role][0]][h][v & 255] | (masks[MATCHED[role][1]][h][v >> 8] if more else 0)
                        if not mask:
                            continue
                        at = order[lo:hi]
                        seen = [column[f"ex{h}"][at], column[f"{'ex' if role == 'orders' else 'wi'}{h}"][at]]
                        if with_sketch:
                            seen.append(column[f"p_{role}{h}"][at])
                            by_key = int(column["by_lines" if role == "orders" else "by_orders"][at].sum())
                        for bit in range(HALF):
                            if mask >> bit & 1:
                                counts = [len(at), *(int(((x >> bit) & 1).sum()) for x in seen)]
                                if with_sketch:
                                    counts.insert(3, by_key)
                                total[h * HALF + bit, i, : len(counts)] += counts
        q, r = np.nonzero(total[:, :, 0])
        sums = [pa.array(total[q, r, j]) for j in range(5)]
        yield pa.RecordBatch.from_arrays([pa.array(q.astype(np.int32)), pa.array([ROLES[i] for i in r], pa.string()), *sums], names=["q", "rel", *MEASURED])

    return run


MEASURED = ("m_pred", "m_exact", "m_binned", "m_keyonly", "m_sketch")


def instances(spark, d, base=None, own=None):
    """One row for each (query, relation): own rows, and what exact, binned, key-only and sketch semi joins leave of them.

    `base` is a spec, or the specs of all relations; `own` is what `own_rows` gives, where it is at hand.
    """
    from pyspark.sql import functions as F

    told = _told(spark, d)
    rows, keys = own_rows(spark, d) if own is None else own
    if base is not None:
        keys = _passed(spark, d, keys, base if isinstance(base, dict) else specs(base), told)
    else:
        keys = keys.drop("in_l", "in_o")
    none = {c: (F.lit(False) if t == "boolean" else F.lit(0).cast("bigint")) for c, t in keys.dtypes if c != "k"}
    met = rows.join(keys, "k", "left").select("code", *(F.coalesce(F.col(c), v).alias(c) for c, v in none.items()))
    counts = met.mapInArrow(_counter(_fields(told), base is not None), "q int, rel string, " + ", ".join(f"{m} long" for m in MEASURED))
    n_rel = F.get(F.array(*(F.lit(t["n_rel"]) for t in told)), F.col("q"))
    return counts.withColumn("n_rel", n_rel).groupBy("q", "rel", "n_rel").agg(*(F.sum(m).alias(m) for m in (MEASURED if base is not None else MEASURED[:3])))


# --- the same in SQL


def _literal_sql() -> tuple[str, dict[str, str]]:
    def lit(v):
        return "null" if v is None else f"'{v}'" if isinstance(v, str) else str(v)

    orders, sats = [], {s: [] for s in SATELLITES}
    for q in range(70):
        t = query(q, 10**9, 10**9)  # without wrapping; the tables' sizes are taken in SQL
        lo, hi = t["months"] or (None, None)
        orders.append(f"({q}, {t['n_rel']}, {lit(t['status'])}, {lit(lo)}::int, {lit(hi)}::int)")
        for s, values in t["satellites"].items():
            own = []
            for a in ATTRS[s]:
                v = values.get(a)
                if a == "supp":
                    own.append("null::bigint" if v is None else f"({v} % (select count(*) from supplier))")
                elif a == "part":
                    own.append(f"({v} % (select count(*) from part))")
                else:
                    own.append(lit(v))
            sats[s].append(f"({q}, {t['n_rel']}, {', '.join(own)})")
    first = f"lit_orders(q, n_rel, status, lo, hi) as (values {', '.join(orders)})"
    return first, {s: f"lit_{s}(q, n_rel, {', '.join('w_' + a for a in ATTRS[s])}) as (values {', '.join(v)})" for s, v in sats.items()}


def shape_sql(role: str, spec, extra: str = "") -> str:
    """(m, b, entries) of the least shape for a relation's predicted entries, as `sizing.shape` chooses it."""
    import math

    from ..plans import sizing
    from .fixtures import FIXTURES, relation_sql

    name, most = fixture(role), sizing.cap(spec)
    per = f"select k, count(*) as n from (select distinct k, {', '.join(FIXTURES[name][2])} from ({relation_sql(name)})) where k is not null group by k"
    told = f"select sum({'n' if math.isinf(most) else f'least(n, {int(most)})'})::bigint as entries, max(n) as largest from ({per})"
    if spec.variant == "plain":
        sizes = f"select greatest({min(sizing.LOADS)}, ceil(largest / 2)::bigint) as b, {max(sizing.LOADS.values())} as top, entries from ({told})"
    else:
        sizes = f"select b, top, entries from ({told}), (values {', '.join(f'({b}, {t})' for b, t in sizing.LOADS.items())}) t(b, top)"
    fits = f"select (1::bigint << j::int) as m, b::bigint as b, entries from ({sizes}), generate_series(1, 30) g(j) where entries / ((1::bigint << j::int) * b) <= top"
    return f"select m, b, entries{extra} from ({fits}) order by m * b, b limit 1"


def instances_sql(base=None, fitted: bool = False) -> str:
    """`fitted`: every relation's number of buckets is the one that its predicted entries need."""
    from ..operators.pairs import hybrid_bits, hybrid_hashes
    from ..queries import sql as Q
    from .fixtures import MONTH, relation_sql

    first, rest = _literal_sql()
    ctes = [first, *rest.values()]
    ctes.append(f"hdr_ as (select o_orderkey as k, o_orderstatus as status, {MONTH} as mon from orders)")
    parts = [
        "select l.q, 'orders' as rel, l.n_rel, o.k, count(*) filter (o.mon between coalesce(l.lo, 0) and coalesce(l.hi, 79)) as n from hdr_ o join lit_orders l on o.status = l.status "
        "where floor(o.mon / 5) between floor(coalesce(l.lo, 0) / 5) and floor(coalesce(l.hi, 79) / 5) group by all"
    ]
    for s in SATELLITES:
        on = " and ".join(f"(l.w_{a} is null or l.w_{a} = r.{a})" for a in ATTRS[s])
        parts.append(f"select l.q, '{s}' as rel, l.n_rel, r.k, count(*) as n from ({relation_sql(s)}) r join lit_{s} l on {on} group by all")
    ctes.append("found as (" + " union all ".join(parts) + ")")
    ctes.append("exact_ as (select q, k from found where n > 0 group by q, n_rel, k having count(*) = n_rel)")
    ctes.append("wide_ as (select q, k from found group by q, n_rel, k having count(*) = n_rel)")
    ctes.append("own as (select f.*, (e.k is not null)::int as ex, (w.k is not null)::int as wi from found f left join exact_ e on e.q = f.q and e.k = f.k left join wide_ w on w.q = f.q and w.k = f.k where f.n > 0)")
    sums = "sum(n)::bigint as m_pred, sum(ex * n)::bigint as m_exact, sum(case when rel = 'orders' then ex else wi end * n)::bigint as m_binned"
    if base is None:
        return f"with {', '.join(ctes)} select q, rel, n_rel, {sums} from own group by all"
    chosen = specs(base)
    if fitted:
        for i, (role, s) in enumerate(chosen.items()):
            ctes.append(f"shape_{role} as materialized ({shape_sql(role, s)})")
            chosen[role] = s.with_(m=1 << (40 + i))  # stands for the number that the shape has
    for role, s in chosen.items():
        p = lambda e, i, s=s: Q.a_print(e, i, s, s.attrs[i].exact_ints)
        if role == "orders":
            values = "select q, status as v0, unnest(generate_series(floor(coalesce(lo, 0) / 5)::bigint, floor(coalesce(hi, 79) / 5)::bigint)) as v1 from lit_orders"
            on = "e.a_0 = w.c0 and e.a_1 = w.c1"
        elif role == "supp":
            values = "select q, w_supp as v0, w_lstatus as v1 from lit_supp"
            on = "(w.any0 or e.a_0 = w.c0) and e.a_1 = w.c1"
        else:
            values = f"select q, w_{ATTRS[role][0]} as v0 from lit_{role}"
            on = "e.a_0 = w.c0"
        n = len(s.attrs)
        codes = ", ".join(f"{p(f'v{i}', i)} as c{i}" for i in range(n))
        if s.variant == "hybrid":
            w = " | ".join(f"case when v{i} is null then 0 else {Q.mask([(i, p(f'v{i}', i))], s, hybrid_bits(s), hybrid_hashes(s))} end" for i in range(n))
        else:
            w = Q.mask([(i, f"v{i}") for i in range(n)], s)
        want = f"want as (select q, v0 is null as any0, {codes}, ({w}) as w from ({values}))"
        rel, hit = relation_sql(fixture(role)), "(e.mask & w.w) = w.w"
        row = f"select '{role}' as rel, w.q, e.pair_id, e.kappa"
        if s.variant == "chained":
            one = f"{Q.chained(rel, s)}, {Q.closed(s)}, {want} select '{role}' as rel, w.q, r.root as pair_id, r.kappa from reach r join entries e on e.pair_id = r.pair_id and e.kappa = r.kappa join want w on {on} union select '{role}', w.q, root, kappa from saturated, (select distinct q from want) w"
        elif s.variant == "hybrid":
            few = f"(select v.* from vecs v join entries x on x.pair_id = v.pair_id and x.kappa = v.kappa where x.n <= {s.d})"
            one = f"{Q.hybrid(rel, s, hybrid_bits(s), hybrid_hashes(s))}, {want} {row} from {few} e join want w on {on} union {row} from entries e join want w on {hit} where e.n > {s.d}"
        elif s.variant == "plain":
            one = f"entries as ({Q.vectors(rel, s)}), {want} {row} from entries e join want w on {on}"
        else:
            one = f"{Q.bloom(rel, s)}, {want} {row} from entries e join want w on {hit}"
        ctes.append(f"live_{role} as (with {one})")
        ctes.append(f"spot_{role} as ({Q.located('select distinct k from own', s)})")
    holds = " union ".join(f"select '{r}' as by_, l.q, s.k from live_{r} l join spot_{r} s on s.pair_id = l.pair_id and s.kappa = l.kappa" for r in ROLES)
    ctes.append(f"holds as ({holds})")
    ctes.append("passed as (select o.q, o.rel, o.k from own o join holds h on h.q = o.q and h.k = o.k and h.by_ <> o.rel group by o.q, o.rel, o.k, o.n_rel having count(*) = o.n_rel - 1)")
    ctes.append(f"kl as (select distinct pair_id, kappa from ({Q.located(relation_sql('disc'), chosen['disc'])}))")
    ctes.append(f"ko as (select distinct pair_id, kappa from ({Q.located(relation_sql('hdr'), chosen['orders'])}))")
    ctes.append("il as (select k from spot_disc s semi join kl on kl.pair_id = s.pair_id and kl.kappa = s.kappa)")
    ctes.append("io as (select k from spot_orders s semi join ko on ko.pair_id = s.pair_id and ko.kappa = s.kappa)")
    ctes.append("all_ as (select o.*, (p.k is not null)::int as sk, case when o.rel = 'orders' then (il.k is not null)::int else (io.k is not null)::int end as kk from own o left join passed p on p.q = o.q and p.rel = o.rel and p.k = o.k left join il on il.k = o.k left join io on io.k = o.k)")
    out = f"with {', '.join(ctes)} select q, rel, n_rel, {sums}, sum(kk * n)::bigint as m_keyonly, sum(sk * n)::bigint as m_sketch from all_ group by all"
    if fitted:
        for role, s in chosen.items():
            out = out.replace(str(s.m - 1), f"(select m - 1 from shape_{role})").replace(str(s.m), f"(select m from shape_{role})")
    return out
