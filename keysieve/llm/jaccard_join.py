"""Similarity self-join on word n-grams by a grouped prefix join.

A document's set is its distinct hashes of k successive lower-cased words (fewer words: the whole sequence).
Two documents link when 100 * intersection >= percent * union. Sets are ordered by one order over the corpus,
rare n-grams first; two sets can only link if they share an n-gram among the first few of each, their prefixes.

1. All n-grams of all documents are counted by ranges of their hash. Each range gives a filter of its n-grams that
   two tasks or documents had, and those counted often; both are of bounded size and are broadcast.
2. Documents are read once more. Each gives its size, its set's name and its group: documents of one prefix and
   one size. The first of a group that a task meets posts the prefix's repeated n-grams with their places.
3. Groups that share a posted n-gram are candidates if size and place leave room: where the first n-gram that two
   sets share lies, at least the needed intersection must still follow in both. A group stands for its members
   by its leader. Lists have a few hubs; in each of the first rounds a group is tried with one hub of its lists in
   another class, the one that parities of their n-grams call nearest. Then all group pairs that still hold two
   classes are expanded to members, but for pairs that parities prove to differ too much: first the nearest few
   of two classes, then, of classes that these do not unite, all.
4. Pairs are verified on whole sets: the texts of partners pass by one held set, and partners of one set are dealt
   into as many seats as they need.

Classes need no list of all pairs: links inside a class that is already known are not enumerated, so a group of
many near copies costs a few checks per member, and no link between classes is lost.

Sets and groups go by 64-bit names and sets of one name count as equal: two of N different sets share a name with
a chance of N^2 / 2^65.

Defined results: null and empty texts and those without words have an empty set and link with nothing. Documents
with equal sets link. Rows of equal doc_id are one document of the result's classes but keep a row each; a null
doc_id gets no class. Columns other than doc_id and text are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import U64, bucket_bits, by_bucket, common, components, forget, gathered, having, mix, shingles, text_buffer, written

#: Frequent n-grams that are broadcast, least count of one, and bits of the filter of repeated ones.
HEAVY, LEAST_HEAVY, FILTER_LOG2 = 1 << 20, 9, 27
#: Hubs of a list, about, in the rounds in which a group is tried with one of them, the first with its lists' least;
#: then pairs of two classes that are tried in a round, before all pairs.
HUBS, NEAREST = (1, 4, 8, 16), (1, 4)
#: N-grams that a task holds before it sends them on, and partners of one seat.
FLUSH, PARTNERS = 1 << 21, 256
#: Parities in 512 cells, 64 to a number.
PARITY = tuple(f"p{i}" for i in range(8))


def _needed(n: np.ndarray, m: np.ndarray, percent: int) -> np.ndarray:
    """Least intersection of sets of sizes n and m that link."""
    return -((-percent * (n + m)) // (100 + percent))


def _rows(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))


def _sign(s: np.ndarray) -> int:
    """A 64-bit name of a set, 0 of the empty one."""
    return int(mix(mix(s).sum(keepdims=True, dtype=np.uint64) + U64(len(s))).view(np.int64)[0]) if len(s) else 0


def _parity(s: np.ndarray) -> np.ndarray:
    """Parities of a set's n-grams in cells: an n-gram that only one of two sets has flips one."""
    cells = 64 * len(PARITY)
    odd = np.bincount((mix(s) & U64(cells - 1)).astype(np.int64), minlength=cells).astype(np.uint8) & 1
    return np.packbits(odd, bitorder="little").view(np.int64)


# --- the order


def _name(s: np.ndarray, bits: int) -> np.ndarray:
    """What counting keeps of a hash: the bucket's bits and 32 more."""
    return s >> U64(32 - bits)


def _places(names: np.ndarray, size: np.ndarray, turn: int) -> np.ndarray:
    """The place of each name in a filter of `size` bits."""
    return (((mix(names + U64((turn * 2 + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1))) >> U64(32)) * size.astype(np.uint64) >> U64(32)).astype(np.int64)


class Order:
    """Filters of repeated n-grams, one for each bucket, and the levels of frequent ones."""

    TURNS = 3

    def __init__(self, bits: int, filters: dict[int, bytes], heavy: np.ndarray, level: np.ndarray):
        self.bits, self.heavy, self.level = bits, heavy, level.astype(np.int64)
        self.size = np.zeros(1 << bits, np.int64)
        for b, f in filters.items():
            self.size[b] = len(f) * 8
        self.base = self.size.cumsum() - self.size
        self.data = np.frombuffer(b"".join(filters[b] for b in sorted(filters)), np.uint8)

    @staticmethod
    def filter(names: np.ndarray, most: int) -> bytes:
        size = min(max(8, most // 8 * 8), -(-12 * len(names) // 8) * 8)
        data = np.zeros(size, bool)
        for t in range(Order.TURNS):
            data[_places(names, np.full(len(names), size), t)] = True
        return np.packbits(data, bitorder="little").tobytes()

    def rank(self, s: np.ndarray) -> np.ndarray:
        """0 for an n-gram that nothing else has, 1 for a repeated one, more for a frequent one."""
        out, names = np.zeros(len(s), np.int64), _name(s, self.bits)
        bucket = (names >> U64(32)).astype(np.int64)
        some = np.flatnonzero(self.size[bucket] > 0)
        for t in range(self.TURNS):
            p = _places(names[some], self.size[bucket[some]], t) + self.base[bucket[some]]
            some = some[(self.data[p >> 3] >> (p & 7).astype(np.uint8)) & 1 == 1]
        out[some] = 1
        if len(self.heavy):
            at = np.searchsorted(self.heavy, names[some])
            at[at == len(self.heavy)] = 0
            hit = self.heavy[at] == names[some]
            out[some[hit]] = 2 + self.level[at[hit]]
        return out


def order(docs: DataFrame, k: int, bits: int) -> Order:
    """The corpus order, from counts of all n-grams of all documents."""

    def send(batches):
        def flush(parts):
            names, n = np.unique(np.concatenate(parts), return_counts=True)
            bucket = (names >> U64(32)).astype(np.int64)
            ends = [*(np.flatnonzero(np.diff(bucket)) + 1).tolist(), len(names)]
            low, one, n = names.astype("<u4"), n == 1, n.astype("<u4")
            rows = [(int(bucket[a]), low[a:b][one[a:b]].tobytes(), low[a:b][~one[a:b]].tobytes(), n[a:b][~one[a:b]].tobytes()) for a, b in zip([0, *ends[:-1]], ends, strict=True)]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.binary(), pa.binary(), pa.binary()), strict=True)], ["bucket", "c0", "c1", "c2"])

        parts, size = [], 0
        for batch in batches:
            for s in shingles(*text_buffer(batch.column(1)), k):
                if len(s):
                    parts.append(_name(s, bits))
                    size += len(s)
                if size > FLUSH:
                    yield flush(parts)
                    parts, size = [], 0
        if parts:
            yield flush(parts)

    def total(batches):
        for bucket, (one, more, n) in by_bucket(batches, ["<u4", "<u4", "<u4"]):
            low, at = np.unique(np.concatenate([one, more]), return_inverse=True)
            sums = np.bincount(at, np.concatenate([np.ones(len(one)), n])).astype(np.int64)
            names = (U64(bucket) << U64(32)) | low[sums > 1].astype(np.uint64)
            sums = sums[sums > 1]
            often = sums >= LEAST_HEAVY
            if len(names):
                level = np.floor(4 * np.log2(sums[often])).astype(np.uint8)
                cells = [Order.filter(names, (1 << FILTER_LOG2) >> bits), names[often].tobytes(), level.tobytes()]
                yield pa.RecordBatch.from_arrays([pa.array([bucket], pa.int32()), *(pa.array([c], pa.binary()) for c in cells)], ["bucket", "filter", "names", "levels"])

    def levels(batches):
        seen = np.zeros(256, np.int64)
        for batch in batches:
            for x in batch.column(0).to_pylist():
                seen += np.bincount(np.frombuffer(x, np.uint8), minlength=256)
        yield pa.RecordBatch.from_arrays([pa.array(range(256), pa.int32()), pa.array(seen)], ["level", "n"])

    sent = _rows(docs).mapInArrow(send, "bucket int, c0 binary, c1 binary, c2 binary")
    counted = written(gathered(sent).mapInArrow(total, "bucket int, filter binary, names binary, levels binary"), "counts")
    # at most 256 levels; the least whose n-grams and those above it stay within the bound
    seen = {r["level"]: r["n"] for r in counted.select("levels").mapInArrow(levels, "level int, n long").groupBy("level").agg(F.sum("n").alias("n")).collect()}
    least, held = 256, 0
    while least and held + seen.get(least - 1, 0) <= HEAVY:
        least -= 1
        held += seen.get(least, 0)

    def often(batches):
        for batch in batches:
            rows = [(np.frombuffer(n, "<u8"), np.frombuffer(v, np.uint8)) for n, v in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)]
            cells = [[n[v >= least].tobytes() for n, v in rows], [v[v >= least].tobytes() for n, v in rows]]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(c, pa.binary()) for c in cells)], ["bucket", "filter", "names", "levels"])

    # filters of 2^FILTER_LOG2 bits in all, and at most HEAVY names
    got = counted.mapInArrow(often, counted.schema).toArrow().to_pydict()
    names, level = np.frombuffer(b"".join(got["names"]), "<u8"), np.frombuffer(b"".join(got["levels"]), np.uint8)
    sort = names.argsort()
    forget(counted)
    return Order(bits, dict(zip(got["bucket"], got["filter"], strict=True)), names[sort], level[sort])


# --- sets, groups and postings


def _told(sets: list[np.ndarray], known: set, order: Order, percent: int):
    """For each set: size, name, group, whether its prefix has a repeated n-gram, parities, and its posted n-grams with their places."""
    sizes = np.array([len(s) for s in sets], np.int64)
    out = []
    ranks = order.rank(np.concatenate(sets)) if sizes.sum() else np.zeros(0, np.int64)
    ends = sizes.cumsum()
    for s, end in zip(sets, ends.tolist(), strict=True):
        n = len(s)
        rank = ranks[end - n : end]
        length = n + (-percent * n) // 100 + 1 if n else 0
        if n - np.count_nonzero(rank) >= length:  # a prefix of n-grams that nothing else has, or an empty set
            out.append((n, _sign(s), 0, False, *[None] * len(PARITY), [], []))
            continue
        sort = rank.argsort(kind="stable")[:length]
        own, posted = s[sort], np.flatnonzero(rank[sort] > 0)
        group = int(mix(mix(own).sum(keepdims=True, dtype=np.uint64) ^ U64(n)).view(np.int64)[0])
        if group in known:
            posted = posted[:0]
        known.add(group)
        out.append((n, _sign(s), group, True, *_parity(s).tolist(), own[posted].view(np.int64), posted.astype(np.int32)))
    return out


SETS = f"doc_id long, n int, sign long, grp long, shared boolean, {', '.join(f'{p} long' for p in PARITY)}, grams array<long>, places array<int>"


def read_sets(docs: DataFrame, k: int, percent: int, order: Order) -> DataFrame:
    """What every row's set is, and the postings of its group where a task met it first."""
    shared = docs.sparkSession.sparkContext.broadcast(order)
    kinds = [pa.int32(), pa.int64(), pa.int64(), pa.bool_(), *[pa.int64()] * len(PARITY), pa.list_(pa.int64()), pa.list_(pa.int32())]

    def run(batches):
        known: set[int] = set()
        for batch in batches:
            sets, rows, held, size = shingles(*text_buffer(batch.column(1)), k), [], [], 0
            for s in sets:
                held.append(s)
                size += len(s)
                if size > 1 << 20:
                    rows.extend(_told(held, known, shared.value, percent))
                    held, size = [], 0
            rows.extend(_told(held, known, shared.value, percent))
            columns = zip(*rows, strict=True) if rows else [[]] * len(kinds)
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(list(c), t) for c, t in zip(columns, kinds, strict=True))], [x.split()[0] for x in SETS.split(", ")])

    return written(_rows(docs).mapInArrow(run, SETS), "sets")


def _sql_needed(a: str, b: str, percent: int) -> str:
    return f"({percent} * ({a}.n + {b}.n) + {99 + percent}) div {100 + percent}"


def _may(a: str, b: str, percent: int):
    """Whether sizes and the places of a shared n-gram leave room for a link if it is the first that both have."""
    needed = _sql_needed(a, b, percent)
    return F.expr(f"100 * least({a}.n, {b}.n) >= {percent} * greatest({a}.n, {b}.n) and {a}.n - {a}.place >= {needed} and {b}.n - {b}.place >= {needed}")


def _differ(a: str, b: str) -> str:
    """The parities in which two sets differ: at most the n-grams that only one of them has."""
    return "(" + " + ".join(f"bit_count({a}.{p} ^ {b}.{p})" for p in PARITY) + ")"


def _near(a: str, b: str, percent: int):
    """Whether parities leave room for a link: sets that link differ in at most n + m - 2 * needed n-grams."""
    return F.expr(f"{_differ(a, b)} <= {a}.n + {b}.n - 2 * ({_sql_needed(a, b, percent)})")


def _pairs(df: DataFrame, a: str, b: str) -> DataFrame:
    return df.select(F.least(a, b).alias("a"), F.greatest(a, b).alias("b")).filter("a < b").distinct()


# --- verification


def verify(texts: DataFrame, pairs: DataFrame, k: int, percent: int) -> DataFrame:
    """The pairs (a, b) of doc_ids whose sets link, by their whole texts (doc_id, text).

    Of a pair, the one with more partners is held and the texts of its partners pass by; beyond `PARTNERS` of
    them it is held in several seats. So a task holds one set at a time, and no seat has more than its share.
    """
    spark = texts.sparkSession
    ends = pairs.select(F.explode(F.array("a", "b")).alias("x")).groupBy("x").agg(F.count("*").alias("c"))
    both = pairs.join(ends.select(F.col("x").alias("a"), F.col("c").alias("ca")), "a").join(ends.select(F.col("x").alias("b"), F.col("c").alias("cb")), "b")
    first = F.col("ca") >= F.col("cb")
    dealt = both.select(F.when(first, F.col("a")).otherwise(F.col("b")).alias("held"), F.when(first, F.col("b")).otherwise(F.col("a")).alias("doc_id"), F.greatest("ca", "cb").alias("c"))
    seat = F.pmod(F.xxhash64("doc_id"), F.ceil(F.col("c") / PARTNERS)).cast("int").alias("seat")
    dealt = written(dealt.select("held", seat, F.lit(1).alias("role"), "doc_id"), "seats")
    need = dealt.select("held", "seat", F.lit(0).alias("role"), F.col("held").alias("doc_id")).distinct().unionByName(dealt)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = need.join(texts, "doc_id").repartition(parts, "held", "seat").sortWithinPartitions("held", "seat", "role").select("held", "role", "doc_id", "text")

    def run(batches):
        one = None
        for batch in batches:
            sets = shingles(*text_buffer(batch.column(3)), k)
            found = []
            for held, role, doc, x in zip(*(batch.column(i).to_pylist() for i in range(3)), sets, strict=True):
                if role == 0:
                    one = x
                    continue
                n = common(one, x)
                if n and 100 * n >= percent * (len(one) + len(x) - n):
                    found.append((held, doc))
            yield pa.RecordBatch.from_arrays([pa.array([f[i] for f in found], pa.int64()) for i in (0, 1)], ["a", "b"])

    links = written(rows.mapInArrow(run, "a long, b long"), "links")
    forget(dealt)
    return links


# --- classes


def _united(labels: DataFrame, links: DataFrame) -> DataFrame:
    """Labels after links: the smallest label that the classes at both ends reach."""
    spark = labels.sparkSession
    of = labels.select("unit", "label")
    ends = links.join(of.select(F.col("unit").alias("a"), F.col("label").alias("x")), "a").join(of.select(F.col("unit").alias("b"), F.col("label").alias("y")), "b")
    edges = written(ends.select(F.col("x").alias("a"), F.col("y").alias("b")).filter("a <> b").distinct(), "joined")
    parts = components(spark, edges)
    new = written(labels.join(parts, labels.label == parts.node, "left").select("unit", F.coalesce("component", "label").alias("label")), "classes")
    forget(edges, parts, labels)
    return new


def classes(docs: DataFrame, k: int = 4, percent: int = 85) -> DataFrame:
    """(doc_id, n_shingles, component_id) of every row; component_id is the smallest doc_id that links reach."""
    bits = bucket_bits(docs.count(), each=1000)
    sets = read_sets(docs, k, percent, order(docs, k, bits))
    named = sets.filter("n > 0 and doc_id is not null")
    units = named.groupBy("sign").agg(F.min("doc_id").alias("unit"))
    members = named.filter("shared").groupBy("sign").agg(F.min("doc_id").alias("unit"), F.min("grp").alias("grp"), F.min("n").alias("n"), *(F.min(p).alias(p) for p in PARITY))
    members = written(members, "members")
    groups = written(members.groupBy("grp").agg(F.min("n").alias("n"), F.min(F.struct("unit", *PARITY)).alias("lead"), F.count("*").alias("held")).select("grp", "n", "lead.*", "held"), "groups")
    each = sets.filter("size(grams) > 0").select("grp", "n", F.explode(F.arrays_zip("grams", "places")).alias("g"))
    posted = each.select(F.col("g.grams").alias("gram"), "grp", "n", F.col("g.places").alias("place")).distinct().join(groups.select("grp", F.col("unit").alias("lead")), "grp")
    lists = posted.groupBy("gram").agg(F.count("*").alias("c"), F.min(F.struct(F.xxhash64("grp"), "grp", "n", "place", "lead")).alias("hub")).filter("c > 1")
    posted = written(posted.join(lists, "gram"), "postings")
    crowds = groups.filter("held > 1").select("grp")
    wanted = members.join(posted.select("grp").unionByName(crowds).distinct(), "grp", "left_semi").select(F.col("unit").alias("doc_id"))
    texts = written(having(_rows(docs), written(wanted, "wanted")), "texts")
    labels = written(members.select("unit", F.col("unit").alias("label")), "classes")

    # every group with a hub of its lists, every member with its group's leader
    star = posted.select(F.struct("n", "place").alias("x"), F.col("hub").alias("y"), "lead").filter(_may("x", "y", percent) & F.expr("lead <> y.lead"))
    star = star.groupBy(F.col("lead").alias("a")).agg(F.min("y").alias("y")).select("a", F.col("y.lead").alias("b"))
    within = members.join(groups.filter("held > 1").select("grp", F.col("unit").alias("lead")), "grp").select(F.col("unit").alias("a"), F.col("lead").alias("b"))
    tested = None
    for turn in range(len(HUBS) + len(NEAREST) + 1):
        if turn == 0:
            found = _pairs(star.unionByName(within), "a", "b").alias("p")
            found = found.join(members.alias("x"), F.expr("x.unit = p.a")).join(members.alias("y"), F.expr("y.unit = p.b")).filter(_near("x", "y", percent)).select("p.a", "p.b")
            tested = written(found.filter("false"), "pairs")
        else:
            own = written(members.join(labels, "unit"), "own")
            spread = own.groupBy("grp").agg(F.min("label").alias("low"), F.max("label").alias("high"))
            rows = written(_open(groups, posted, spread), "open")
            apart = spread.filter("low <> high")
            if not rows.limit(1).count() and not apart.limit(1).count():
                forget(own, rows)
                break  # no list and no group has two classes
            if turn < len(HUBS):
                found = _one_hub(rows, tested, percent, turn)
            else:
                found = _members(rows, own, apart, tested, percent, dict(enumerate(NEAREST, len(HUBS))).get(turn))
        pairs = written(found, "pairs")
        if turn:
            forget(own, rows)
        if not pairs.limit(1).count():
            forget(pairs)
            continue
        links = verify(texts, pairs, k, percent)
        both = written(tested.unionByName(pairs), "tested")
        forget(tested, pairs)
        tested = both
        labels = _united(labels, links)
        forget(links)
    forget(tested)
    out = units.join(labels, "unit", "left").select("sign", F.coalesce("label", "unit").alias("label"))
    out = written(out, "labelled")
    forget(members, groups, posted, texts, labels)
    told = sets.select("doc_id", "n", "sign").join(out, "sign", "left")
    return told.select("doc_id", F.col("n").cast("long").alias("n_shingles"), F.when(F.expr("n > 0 and doc_id is not null"), F.col("label")).otherwise(F.col("doc_id")).alias("component_id"))


def _open(groups: DataFrame, posted: DataFrame, spread: DataFrame) -> DataFrame:
    """Postings of lists that still hold two classes, with their groups."""
    rows = posted.select("gram", "grp", "place", "c").join(groups.join(spread, "grp").withColumnRenamed("unit", "lead"), "grp")
    still = rows.groupBy("gram").agg(F.min("low").alias("l"), F.max("high").alias("h")).filter("l <> h").select("gram")
    return rows.join(still, "gram", "left_semi")


def _apart(percent: int):
    """Two groups of a list that hold different classes and leave room for a link."""
    return F.expr("x.gram = y.gram and x.grp <> y.grp and not (x.low = y.low and x.low = x.high and y.low = y.high)") & _may("x", "y", percent)


def _one_hub(rows: DataFrame, tested: DataFrame, percent: int, turn: int) -> DataFrame:
    """Each group's leader with one hub: of those of its lists in other classes that were not tried, the nearest by parities."""
    share = F.pmod(F.xxhash64("grp", F.lit(turn)), F.lit(1 << 20)) * F.col("c")
    hubs = rows.filter(share < F.lit(HUBS[turn] << 20)).alias("y")
    met = rows.alias("x").join(hubs, _apart(percent) & _near("x", "y", percent) & F.expr("x.low <> y.low"))
    met = met.select(F.least("x.lead", "y.lead").alias("a"), F.greatest("x.lead", "y.lead").alias("b"), F.col("x.lead").alias("of"), F.expr(f"{_differ('x', 'y')} / (x.n + y.n)").alias("far"))
    met = met.distinct().join(tested, ["a", "b"], "left_anti")
    return met.groupBy("of").agg(F.min(F.struct("far", "a", "b")).alias("p")).select("p.a", "p.b").distinct()


def _members(rows: DataFrame, own: DataFrame, apart: DataFrame, tested: DataFrame, percent: int, most: int | None) -> DataFrame:
    """Pairs of members of different classes that group pairs of a list, and groups of two classes, leave room for.

    The nearest `most` of each pair of classes, or all.
    """
    # a group of one member is bounded by its parities here, others member by member
    met = rows.alias("x").join(rows.alias("y"), _apart(percent) & F.expr("x.grp < y.grp") & (F.expr("x.held > 1 or y.held > 1") | _near("x", "y", percent)))
    met = met.select(F.col("x.grp").alias("g"), F.col("y.grp").alias("h")).unionByName(apart.select(F.col("grp").alias("g"), F.col("grp").alias("h"))).distinct().alias("m")
    both = met.join(own.alias("x"), F.expr("m.g = x.grp")).join(own.alias("y"), F.expr("m.h = y.grp and x.label <> y.label") & _near("x", "y", percent))
    named = [F.least("x.unit", "y.unit").alias("a"), F.greatest("x.unit", "y.unit").alias("b"), F.least("x.label", "y.label").alias("low"), F.greatest("x.label", "y.label").alias("high")]
    both = both.select(*named, F.expr(f"{_differ('x', 'y')} / (x.n + y.n)").alias("far")).distinct().join(tested, ["a", "b"], "left_anti")
    if most is not None:
        both = both.withColumn("nth", F.row_number().over(Window.partitionBy("low", "high").orderBy("far", "a", "b"))).filter(F.col("nth") <= most)
    return both.select("a", "b")
