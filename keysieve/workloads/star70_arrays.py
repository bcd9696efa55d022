"""The seventy queries on all sketches at once, by print.

A key's print tells its task: what relations hold of the key, every sketch's groups that it may lie in, and all chains
from there. So rows are dealt once by the shortest print, and each task builds the sketches of its prints in arrays,
of all bases, probes them with its keys and counts its rows. Nothing else is exchanged but counts.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from ..functions import md5
from ..operators import arrays, chains, places
from ..operators.pairs import hybrid_bits, hybrid_hashes
from . import star70 as W

#: Marks of a code: a row of orders, a null key.
_ORDER, _NULL = 56, 57
_LEAST_BITS = 7
#: Rows of a slice of packed rows.
_SLICE = 1 << 15


def whole(spark, d) -> bool:
    """Whether the tables' keys and numbers are integers, as arrays need them."""
    from ..sources.tables import table
    from .fixtures import FIXTURES, relation

    for r in W.ROLES:
        source, key, _, _ = FIXTURES[W.fixture(r)]
        kinds = relation(spark, d, W.fixture(r)).schema
        if not isinstance(table(spark, d, source).schema[key].dataType, places._INTS):
            return False
        for column, f in zip(W.VALUES[r], kinds.fields[1:], strict=True):
            if f.dataType.simpleString() != "string" if column == "t" else not isinstance(f.dataType, places._INTS):
                return False
    return True


def suits(chosen: list[dict]) -> bool:
    """Whether specs by relation can be built by print: prints of one family and salt, which are cut to their widths, without shards."""
    every = [s for specs in chosen for s in specs.values()]
    return all(chains.suits(s) and s.shards == 1 and s.variant != "keyonly" and s.salt == every[0].salt for s in every)


def by_prints(spark, d, bits: int = _LEAST_BITS, salt: int = 0):
    """(kappa, k, code, values): all rows by the first bits of their keys' prints; null keys join nothing and may be anywhere."""
    from ..functions.hashing import h60, low

    rows = W.coded_rows(spark, d, values=True)
    own = F.coalesce(low(h60("k", "key", salt, "portable"), bits), F.pmod(F.monotonically_increasing_id(), F.lit(1 << bits))).cast("int")
    code = F.when(F.col("k").isNull(), F.col("code").bitwiseOR(F.lit(1 << _NULL))).otherwise(F.col("code"))
    rows = rows.select(own.alias("kappa"), F.coalesce(F.col("k").cast("bigint"), F.lit(0).cast("bigint")).alias("k"), code.alias("code"), *W.VALUE_COLUMNS)
    return rows.repartition("kappa").sortWithinPartitions("kappa")


def _tables(batches):
    return chains.by_prints(batches, ("kappa",))


def packed(rows, most: int | None = _SLICE):
    """(blob, ends, rel, dupes, n) of `by_prints`: whole prints as Arrow streams, each slice a row, and rows with how many keys of a relation have so many vectors.

    What is read again is read in this form, which takes no turn from row to row; slices of at most so many rows bound what a row holds, and None leaves them out.
    """

    def run(batches):
        schema = pa.schema([("blob", pa.binary()), ("ends", pa.bool_()), ("rel", pa.string()), ("dupes", pa.int64()), ("n", pa.int64())])
        found: dict[tuple, int] = {}
        for table in _tables(batches):
            _count_duplicates(found, Part(table))
            table = table.drop_columns(["kappa"])
            for at in range(0, len(table), most) if most else ():
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, table.schema, options=pa.ipc.IpcWriteOptions(compression="lz4")) as stream:
                    stream.write_table(table.slice(at, most).combine_chunks())
                yield pa.RecordBatch.from_pylist([{"blob": sink.getvalue().to_pybytes(), "ends": at + most >= len(table)}], schema)
        yield pa.RecordBatch.from_pylist([{"rel": r, "dupes": x, "n": n} for (r, x), n in found.items()], schema)

    return rows.mapInArrow(run, "blob binary, ends boolean, rel string, dupes long, n long")


def _unpacked(batches):
    """The tables that `packed` made of whole prints."""
    held = []
    for batch in batches:
        for blob, ends in zip(batch.column("blob"), batch.column("ends").to_pylist(), strict=True):
            held.append(pa.ipc.open_stream(blob.as_buffer()).read_all())
            if ends:
                yield pa.concat_tables(held)
                held = []


class Part:
    """All rows of some prints, in order of their keys, lines first; row numbers of keys, the last one for null keys."""

    def __init__(self, table: pa.Table):
        k, code = table["k"].to_numpy(), table["code"].to_numpy()
        there = code >> _NULL == 0
        self.keys, back = np.unique(k[there], return_inverse=True)
        of = np.full(len(k), len(self.keys), np.int64)
        of[there] = back.reshape(-1)
        is_order = code >> _ORDER & 1
        order = np.argsort(is_order * (len(self.keys) + 1) + of, kind="stable")
        n = len(order) - int(is_order.sum())
        self.table, self.rows = table, {"orders": order[n:]} | dict.fromkeys(W.SATELLITES, order[:n])
        self.code = {r: code[order[n:] if r == "orders" else order[:n]] for r in ("orders", "disc")}
        self.of = {r: of[order[n:] if r == "orders" else order[:n]] for r in ("orders", "disc")}
        self.code |= dict.fromkeys(W.SATELLITES, self.code["disc"])
        self.of |= dict.fromkeys(W.SATELLITES, self.of["disc"])
        self._kept: dict = {}

    def _once(self, name, make):
        if name not in self._kept:
            self._kept[name] = make()
        return self._kept[name]

    def _column(self, role: str, column: str):
        """(different values, each row's number among them, -1 for null) of rows with a key."""

        def make():
            held = self.rows[role][: np.searchsorted(self.of[role], len(self.keys))]
            coded = self.table[column].combine_chunks().take(pa.array(held)).dictionary_encode()
            coded = coded.combine_chunks() if isinstance(coded, pa.ChunkedArray) else coded
            return coded.dictionary, coded.indices.fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64)

        return self._once((role == "orders", column), make)

    def distinct(self, role: str) -> tuple[np.ndarray, list[np.ndarray]]:
        """Different (key, values) of a relation, by key: numbers of keys, and of values."""

        def make():
            columns = [self._column(role, c) for c in W.VALUES[role]]
            sizes, number = [len(v) + 1 for v, _ in columns], self.of[role][: len(columns[0][1])]
            for size, (_, at) in zip(sizes, columns, strict=True):
                number = number * size + at + 1
            number, out = chains.different(number), []
            for size in reversed(sizes):
                out.insert(0, number % size - 1)
                number = number // size
            return number, out

        return self._once(("distinct", role), make)

    def _h60(self, role: str, column: str):
        """Hashes of a column's different values, each role's taken once for prints and masks of all widths."""
        return lambda before, values: self._once(("h60", role == "orders", column, before), lambda: md5.column(before, values))

    def prints(self, role: str, spec) -> list[np.ndarray]:
        """The prints of `distinct`."""
        out = []
        for i, (column, at) in enumerate(zip(W.VALUES[role], self.distinct(role)[1], strict=True)):
            values = self._column(role, column)[0]
            make = lambda i=i, values=values, at=at, h60=self._h60(role, column): np.r_[places.prints(values, i, spec, h60), places.A.NULL_PRINT][at].astype(np.int64)
            out.append(self._once(("print", role, i, spec.attrs[i].exact_ints, spec.attr_bits, spec.salt), make))
        return out

    def masks(self, role: str, spec) -> np.ndarray:
        """The Bloom bits of `distinct`."""
        out = np.zeros(len(self.distinct(role)[0]), np.int64)
        for i, (column, at) in enumerate(zip(W.VALUES[role], self.distinct(role)[1], strict=True)):
            out |= np.r_[places.mask(self._column(role, column)[0], i, spec, spec.bloom_bits, spec.bloom_hashes, self._h60(role, column)), 0][at]
        return out

    def slots(self, spec) -> tuple[np.ndarray, np.ndarray]:
        """(slot of each key, the prints of the slots)."""

        def make():
            own, bucket = self._once(("hash", spec.salt), lambda: places.hashed(pa.array(self.keys), spec))
            pair, kappa = places.pairs_of(own, bucket, spec, places.offset_table(spec))
            kappas, home = np.unique(kappa, return_inverse=True)
            return home.reshape(-1) * spec.m + pair, kappas

        return self._once(("slots", spec.m, spec.key_bits, spec.salt), make)

    def _met(self, spec) -> tuple[np.ndarray, np.ndarray]:
        """Different slots of the keys in order, and the place of each key's."""
        return self._once(("met", spec.m, spec.key_bits, spec.salt), lambda: np.unique(self.slots(spec)[0], return_inverse=True))

    def held(self, role: str, spec, asked) -> list[np.ndarray]:
        """For each key, the queries under whose literals its group of the relation's sketch is left."""
        slot, kappas = self.slots(spec)
        of = self.distinct(role)[0]
        by_bits = spec.variant == "bloomattr"
        onward = self._once(("onward", spec.m, spec.key_bits, spec.salt), lambda: chains.Onward(kappas, spec))
        at, met = arrays.live(slot[of], [] if by_bits else self.prints(role, spec), self.masks(role, spec) if by_bits else None, asked, kappas, spec, onward)
        if not len(at):
            return [np.zeros(len(self.keys), np.int64) for _ in (0, 1)]
        some, back = self._met(spec)
        there = np.minimum(np.searchsorted(at, some), len(at) - 1)
        return [np.where(at[there] == some, m[there], 0)[back] for m in met]

    def by_key(self, spec, role: str) -> np.ndarray:
        """Keys whose group in a sketch holds any key of a relation."""

        def make():
            (some, back), mine = self._met(spec), self.of[role]
            there = np.zeros(len(some), bool)
            there[back[mine[mine < len(self.keys)]]] = True
            return there[back]

        return self._once(("by", role, spec.m, spec.key_bits, spec.salt), make)

    def joined(self, role: str, masks: np.ndarray) -> np.ndarray:
        """For each key, what the masks of a relation's rows hold together."""
        out = np.zeros(len(self.keys) + 1, np.int64)
        starts = arrays._groups(self.of[role])
        if len(starts):
            out[self.of[role][starts]] = np.bitwise_or.reduceat(masks, starts)
        return out[:-1]


def _all(masks: dict, told: list[dict], h: int, n: int, without: str | None = None) -> np.ndarray:
    """For each of n keys, the queries all of whose relations, but for one, have it in their masks."""
    out = np.full(n, W.halves(range(len(told)))[h], np.int64)
    for r, m in masks.items():
        if r != without:
            others = () if r == "orders" else (t["q"] for t in told if r not in t["satellites"])
            out &= m[h] | W.halves(others)[h]
    return out


def asked(told: list[dict], role: str, spec) -> arrays.Asked:
    """The literals of a relation in its sketch's prints and Bloom bits."""
    parts: dict[tuple, list] = {}
    for t in told:
        if role == "orders":
            lo, hi = (x if x is not None else o for x, o in zip(t["months"] or (None, None), (0, 79), strict=True))
            parts.setdefault((0, 1), []).extend((t["q"], (t["status"], b)) for b in range(lo // 5, hi // 5 + 1))
        elif role in t["satellites"]:
            values = t["satellites"][role]
            at = tuple(i for i, a in enumerate(W.ATTRS[role]) if a in values)
            parts.setdefault(at, []).append((t["q"], tuple(values[W.ATTRS[role][i]] for i in at)))
    found, bits = [], {}
    for at, rows in parts.items():
        columns = [pa.array([v[j] for _, v in rows]) for j in range(len(at))]
        prints = [places.prints(c, i, spec) for c, i in zip(columns, at, strict=True)]
        w = np.zeros(len(rows), np.int64)
        for c, p, i in zip(columns, prints, at, strict=True):
            w |= places.mask(pa.array(p), i, spec, hybrid_bits(spec), hybrid_hashes(spec)) if spec.variant == "hybrid" else places.mask(c, i, spec, spec.bloom_bits, spec.bloom_hashes)
        by: dict[tuple, list] = {}
        for (q, _), *code in zip(rows, *(p.tolist() for p in prints), strict=True):
            by.setdefault(tuple(code), []).append(q)
        found.append(({c: W.halves(qs) for c, qs in by.items()}, at))
        for (q, _), x in zip(rows, w.tolist(), strict=True):
            bits.setdefault(x, []).append(q)
    every = W.halves(q for rows in parts.values() for q, _ in rows)
    return arrays.Asked(chains.coded(found), [(w, W.halves(qs)) for w, qs in bits.items()], every)


def _count(total: np.ndarray, part: Part, fields: dict, seen: list, sketched: list) -> None:
    """Adds a part's rows to (base, query, relation, measure). `seen`: exact and binned masks of keys; `sketched`: of each base, by relation, what passes and keys known by print alone."""
    place = {f: 8 * i for i, f in enumerate(W.FIELDS)}
    any_of = {r: [np.bitwise_or.reduce([*(s[h] for s in seen), *(passed[r][h] for passed, _ in sketched)]) for h in (0, 1)] for r in W.ROLES}
    for i, role in enumerate(W.ROLES):
        if not len(part.code[role]):
            continue
        one, *more = (part.code[role] >> place[f] & 255 for f in W.MATCHED[role])
        kind = (one | more[0] << 8 if more else one).astype(np.uint16)
        order = np.argsort(kind, kind="stable")
        values, starts = np.unique(kind[order], return_index=True)
        tables = [[[0, *(m[h] for m in fields[f].values())] for h in (0, 1)] for f in W.MATCHED[role]]
        for v, lo, hi in zip(values.tolist(), starts.tolist(), [*starts[1:].tolist(), len(kind)], strict=True):
            masks = [tables[0][h][v & 255] | (tables[1][h][v >> 8] if more else 0) for h in (0, 1)]
            if not any(masks):
                continue
            at = part.of[role][order[lo:hi]]
            found = {h: at[any_of[role][h][at] & masks[h] != 0] for h in (0, 1) if masks[h]}
            by_key = [int(np.count_nonzero(known[role == "orders"][at])) for _, known in sketched]
            for h, at in found.items():
                bits = [b for b in range(W.HALF) if masks[h] >> b & 1]
                row = [h * W.HALF + b for b in bits]
                total[:, row, i, 0] += hi - lo
                total[:, row, i, 1] += _bits(seen[0][h][at], bits)
                total[:, row, i, 2] += _bits(seen[0 if role == "orders" else 1][h][at], bits)
                for n, (passed, _) in enumerate(sketched):
                    total[n, row, i, 3] += by_key[n]
                    total[n, row, i, 4] += _bits(passed[role][h][at], bits)


def _bits(masks: np.ndarray, bits: list[int]) -> np.ndarray:
    """How many masks have each bit."""
    return np.array([np.count_nonzero(masks & (1 << b)) for b in bits], np.int64)


def counter(told: list[dict], fields: dict, bases: list[dict], tables=_tables):
    """A function over Arrow batches of `by_prints`, or of what `tables` reads: counts of every (base, query, relation); no bases give the exact ones alone."""
    literals = [{r: asked(told, r, s) for r, s in chosen.items()} for chosen in bases]

    def masks_of(part, role, field, h):
        own = [0, *(m[h] for m in fields[field].values())]
        place = 8 * list(W.FIELDS).index("orders" if field == "near" else field)
        return np.array(own, np.int64)[part.code[role] >> place & 255]

    def run(batches):
        total = np.zeros((max(1, len(bases)), 2 * W.HALF, len(W.ROLES), len(W.MEASURED)), np.int64)
        for table in tables(batches):
            part = Part(table)
            n = len(part.keys)
            own = {r: [part.joined(r, np.bitwise_or.reduce([masks_of(part, r, f, h) for f in W.MATCHED[r]])) for h in (0, 1)] for r in W.ROLES}
            near = {"orders": [part.joined("orders", masks_of(part, "orders", "near", h)) for h in (0, 1)]}
            seen = [[np.r_[_all(m, told, h, n), 0] for h in (0, 1)] for m in (own, own | near)]
            sketched = []
            for chosen, literal in zip(bases, literals, strict=True):
                held = {r: part.held(r, s, literal[r]) for r, s in chosen.items()}
                passed = {r: [np.r_[_all(held, told, h, n, without=r), 0] for h in (0, 1)] for r in chosen}
                known = [np.r_[part.by_key(chosen[r], r), False] for r in ("orders", "disc")]  # for lines, and for orders
                sketched.append((passed, known))
            _count(total, part, fields, seen, sketched)
        base, q, r = np.nonzero(total[..., 0])
        sums = [pa.array(total[base, q, r, j]) for j in range(len(W.MEASURED))]
        yield pa.RecordBatch.from_arrays([pa.array(base.astype(np.int32)), pa.array(q.astype(np.int32)), pa.array([W.ROLES[i] for i in r], pa.string()), *sums], names=["base", "q", "rel", *W.MEASURED])

    return run


def instances(spark, d, rows, bases: list[dict]):
    """(base, q, rel, n_rel, measures) of the bases' specs by relation, numbered from 0; rows are those of `by_prints`, or packed."""
    told, tables = W._told(spark, d), _tables
    if "blob" in rows.columns:
        rows, tables = rows.filter("blob is not null").select("blob", "ends"), _unpacked
    counts = rows.mapInArrow(counter(told, W._fields(told), bases, tables), "base int, q int, rel string, " + ", ".join(f"{m} long" for m in W.MEASURED))
    n_rel = F.get(F.array(*(F.lit(t["n_rel"]) for t in told)), F.col("q"))
    return counts.withColumn("n_rel", n_rel).groupBy("base", "q", "rel", "n_rel").agg(*(F.sum(m).alias(m) for m in W.MEASURED))


def _count_duplicates(found: dict[tuple, int], part: Part) -> None:
    for r in W.ROLES:
        many = np.bincount(part.distinct(r)[0])
        for dupes, n in zip(*(x.tolist() for x in np.unique(many[many > 0], return_counts=True)), strict=True):
            found[r, dupes] = found.get((r, dupes), 0) + n


def duplicates(rows) -> dict[str, dict[int, int]]:
    """relation -> how many keys have so many vectors; rows are those of `by_prints`, or packed."""
    held = rows if "blob" in rows.columns else packed(rows, None)
    out: dict[str, dict[int, int]] = {}
    for r in held.filter("rel is not null").groupBy("rel", "dupes").agg(F.sum("n").alias("n")).collect():
        out.setdefault(r["rel"], {})[r["dupes"]] = r["n"]
    return out
