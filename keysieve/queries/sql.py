"""SQL for DuckDB that computes sketches anew from the definitions, without the Spark code."""

from __future__ import annotations

from ..config import SketchSpec


def h(expr: str, role: str, salt: int = 0) -> str:
    return f"('0x' || substr(md5('{role}:{salt}:' || cast({expr} as varchar)), 1, 15))::bigint"


def kappa(key: str, s: SketchSpec) -> str:
    return f"({h(key, 'key', s.salt)} & {(1 << s.key_bits) - 1})"


def pair(bucket: str, k: str, s: SketchSpec) -> str:
    return f"least({bucket}, xor({bucket}, 1 + {h(k, 'pair', s.salt)} % {s.m - 1}))"


def located(source: str, s: SketchSpec, extra: str = "*") -> str:
    """k's place for each row of a subquery with column k."""
    inner = f"select {extra}, {kappa('k', s)} as kappa, {h('k', 'bucket', s.salt)} % {s.m} as bucket_ from ({source}) where k is not null"
    return f"select * exclude (bucket_), {pair('bucket_', 'kappa', s)} as pair_id from ({inner})"


def a_print(expr: str, i: int, s: SketchSpec, exact: bool) -> str:
    hashed = f"({h(expr, f'attr{i}', s.salt)} & {(1 << s.attr_bits) - 1})"
    if exact:
        hashed = f"case when {expr} between 0 and {(1 << s.attr_bits) - 1} then {expr} else {hashed} end"
    return f"coalesce({hashed}, -1)"


def literal(v) -> str:
    return f"'{v}'" if isinstance(v, str) else str(v)


def vectors(source: str, s: SketchSpec) -> str:
    prints = ", ".join(f"{a_print(a.name, i, s, a.exact_ints)} as a_{i}" for i, a in enumerate(s.attrs))
    return f"select distinct pair_id, kappa, {prints} from ({located(source, s)})"


def cols(s: SketchSpec) -> str:
    return ", ".join(f"a_{i}" for i in range(len(s.attrs)))


def mask(items: list[tuple[int, str]], s: SketchSpec, bits: int | None = None, hashes: int | None = None) -> str:
    parts = []
    for i, e in items:
        text = f"'{i}=' || cast({e} as varchar)"
        one = " | ".join(f"(1::bigint << ({h(f'({text})', f'bloom{j}', s.salt)} % {bits or s.bloom_bits})::int)" for j in range(hashes or s.bloom_hashes))
        parts.append(f"coalesce({one}, 0)")
    return "(" + " | ".join(parts) + ")"


def next_pair(p: str, k: str, s: SketchSpec, attempt: int = 0) -> str:
    more = f" || ':{attempt}'" if attempt else ""
    joined = f"(cast({p} as varchar) || ':' || cast({k} as varchar){more})"
    return pair(f"({h(joined, 'chain', s.salt)} % {s.m})", k, s)


def onward(seen: str, k: str, s: SketchSpec, attempts: int = 4) -> str:
    """The first attempt's pair that a list of pairs does not hold, or null."""
    found = ", ".join(next_pair(f"{seen}[-1]", k, s, t) for t in range(attempts))
    return f"list_filter([{found}], lambda p: not list_contains({seen}, p))[1]"


def uncapped(source: str, s: SketchSpec, rounds: int) -> str:
    """CTE list that ends in `entries` and `over_` after that many rounds of chains without cap; `late_` is what still moves."""
    c, out = cols(s), [f"r0 as (select *, 1 as late, [pair_id] as seen from ({vectors(source, s)}))"]
    for t in range(rounds):
        out.append(f"g{t} as (select pair_id, kappa, {c}, seen, min(late) over (partition by pair_id, kappa, {c}) as late from r{t})")
        out.append(f"k{t} as (select *, dense_rank() over (partition by pair_id, kappa order by late, {c}) as rk from g{t})")
        out.append(f"n{t} as materialized (select *, case when rk > {s.d} then {onward('seen', 'kappa', s)} end as go from k{t})")
        out.append(f"r{t + 1} as (select distinct coalesce(go, pair_id) as pair_id, kappa, {c}, case when go is null then seen else list_append(seen, go) end as seen, case when rk <= {s.d} then 0 else 1 end as late from n{t} where rk <= {s.d} or go is not null)")
    out.append(f"entries as (select distinct pair_id, kappa, {c} from r{rounds})")
    out.append("over_ as (" + " union ".join(f"select pair_id, kappa, {c} from n{t} where rk > {s.d} and go is null" for t in range(rounds)) + ")")
    out.append(f"late_ as (select * from r{rounds} where late = 1)")
    return ", ".join(out)


def chained(source: str, s: SketchSpec) -> str:
    """CTE list that ends in `entries` (pair_id, kappa, prints) and `over` (what found no place)."""
    return rounds(vectors(source, s), s)


def rounds(start: str, s: SketchSpec) -> str:
    """The same from any (pair_id, kappa, prints)."""
    c, out = cols(s), [f"r0 as (select *, 1 as late from ({start}))"]
    for t in range(s.l_max):
        out.append(f"g{t} as (select pair_id, kappa, {c}, min(late) as late from r{t} group by all)")
        out.append(f"k{t} as (select *, dense_rank() over (partition by pair_id, kappa order by late, {c}) as rk from g{t})")
        go = next_pair("pair_id", "kappa", s) if t + 1 < s.l_max else "pair_id"
        out.append(f"r{t + 1} as (select case when rk <= {s.d} then pair_id else {go} end as pair_id, kappa, {c}, case when rk <= {s.d} then 0 else 1 end as late from k{t})")
    out.append(f"entries as (select distinct pair_id, kappa, {c} from r{s.l_max} where late = 0)")
    out.append(f"over_ as (select distinct pair_id, kappa, {c} from r{s.l_max} where late = 1)")
    return ", ".join(out)


def closed(s: SketchSpec) -> str:
    """CTE list after `entries`: `reach` (root, kappa, pair_id) of chains and `saturated` (root, kappa)."""
    out = [
        f"grp as (select pair_id, kappa, count(*) >= {s.d} as is_full from entries group by all)",
        "c0 as (select pair_id as root, kappa, pair_id, is_full from grp)",
    ]
    for t in range(1, s.l_max):
        out.append(f"n{t} as (select root, kappa, {next_pair('pair_id', 'kappa', s)} as pair_id from c{t - 1} where is_full)")
        out.append(f"c{t} as (select n.root, n.kappa, n.pair_id, g.is_full from n{t} n join grp g on g.pair_id = n.pair_id and g.kappa = n.kappa)")
    out.append("reach as (" + " union ".join(f"select root, kappa, pair_id from c{t}" for t in range(s.l_max)) + ")")
    out.append(f"saturated as (select distinct root, kappa from c{s.l_max - 1} where is_full)")
    return ", ".join(out)


def match(pred: dict, s: SketchSpec, prefix: str = "") -> str:
    names = [a.name for a in s.attrs]
    parts = []
    for n, values in pred.items():
        i = names.index(n)
        one = " or ".join(f"{prefix}a_{i} = {a_print(literal(v), i, s, s.attrs[i].exact_ints and not isinstance(v, str))}" for v in values)
        parts.append(f"({one})")
    return " and ".join(parts) or "true"


def live_chained(pred: dict, s: SketchSpec) -> str:
    """CTE `live` after `entries` and `closed`."""
    hit = f"select r.root as pair_id, r.kappa from reach r join entries e on e.pair_id = r.pair_id and e.kappa = r.kappa where {match(pred, s, 'e.')}"
    return f"live as ({hit} union select root, kappa from saturated)"


def want_mask(pred: dict, s: SketchSpec, column: str = "mask", bits: int | None = None, hashes: int | None = None, of_prints: bool = False) -> str:
    names, parts = [a.name for a in s.attrs], []
    for n, values in pred.items():
        i, ones = names.index(n), []
        for v in values:
            e = a_print(literal(v), i, s, s.attrs[i].exact_ints and not isinstance(v, str)) if of_prints else literal(v)
            want = mask([(i, e)], s, bits, hashes)
            ones.append(f"(({column} & {want}) = {want})")
        parts.append("(" + " or ".join(ones) + ")")
    return " and ".join(parts) or "true"


def bloom(source: str, s: SketchSpec) -> str:
    """CTE `entries` (pair_id, kappa, mask)."""
    items = [(i, a.name) for i, a in enumerate(s.attrs)]
    return f"entries as (select pair_id, kappa, bit_or({mask(items, s)}) as mask from ({located(source, s)}) group by all)"


def hybrid(source: str, s: SketchSpec, bits: int, hashes: int) -> str:
    """CTEs `vecs`, and `entries` (pair_id, kappa, n, mask)."""
    items = " | ".join(f"case when a_{i} = -1 then 0 else {mask([(i, f'a_{i}')], s, bits, hashes)} end" for i in range(len(s.attrs)))
    return f"vecs as ({vectors(source, s)}), entries as (select pair_id, kappa, count(*) as n, case when count(*) > {s.d} then bit_or({items}) else 0 end as mask from vecs group by pair_id, kappa)"


def live_hybrid(pred: dict, s: SketchSpec, bits: int, hashes: int) -> str:
    return (
        f"live as (select distinct v.pair_id, v.kappa from vecs v join entries e on e.pair_id = v.pair_id and e.kappa = v.kappa where e.n <= {s.d} and {match(pred, s, 'v.')} "
        f"union select pair_id, kappa from entries where n > {s.d} and {want_mask(pred, s, 'mask', bits, hashes, of_prints=True)})"
    )


def probe(keys: str, s: SketchSpec, select: str = "k") -> str:
    """Rows of a subquery with k whose group is in `live`."""
    return f"select {select} from ({located(keys, s)}) p semi join live l on l.pair_id = p.pair_id and l.kappa = p.kappa"
