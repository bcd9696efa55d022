"""Near-duplicate vectors by an inverted multi-index.

Unit vectors are cut into halves, each half has a codebook of its own, and the pairs of codes form the cells.
A vector visits cells in ascending order of its summed half distances (multi-sequence order) and every vector
in a visited cell is verified by its cosine in double precision. The number of visits is the smallest that
finds the wanted share of partners at exactly the threshold, tried on a bounded sample with partners in
random directions, so real partners, which are mostly nearer, are found more often.

Cells of one code of the first half are worked on together, in blocks of bounded size, so a crowded code is
split and a vector travels once for each block it visits. Identical vectors are one vector with a weight.
Links are counted and united inside each block; pairs are never listed.

Defined results: null and zero vectors, vectors with null or non-finite components, and vectors of another
length than most have no links and are their own component. Rows of equal vec_id count as vectors of their own.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, written

#: Vectors that codebooks are fitted on, index rows of a block, and the share of partners at the threshold to find.
SAMPLE, BLOCK, RECALL = 8192, 8192, 0.97


def unit(rows: np.ndarray) -> np.ndarray:
    return rows / np.linalg.norm(rows, axis=1, keepdims=True)


def _codebook(x: np.ndarray, k: int, rng: np.random.Generator, rounds: int = 12) -> np.ndarray:
    centres = x[rng.choice(len(x), k, replace=False)].copy()
    for _ in range(rounds):
        near = distances(x, centres).argmin(1)
        sums, n = np.zeros_like(centres), np.bincount(near, minlength=k)
        np.add.at(sums, near, x)
        full = n > 0
        centres[full] = sums[full] / n[full, None]
    return centres


def distances(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return (x**2).sum(1)[:, None] - 2 * x @ centres.T + (centres**2).sum(1)[None, :]


class MultiIndex:
    def __init__(self, first: np.ndarray, second: np.ndarray, visits: int):
        self.books, self.k, self.visits = (first, second), len(first), visits

    def home(self, x: np.ndarray) -> np.ndarray:
        h = self.books[0].shape[1]
        return distances(x[:, :h], self.books[0]).argmin(1) * self.k + distances(x[:, h:], self.books[1]).argmin(1)

    def visited(self, x: np.ndarray, visits: int | None = None) -> np.ndarray:
        """The nearest cells of each vector in multi-sequence order.

        A cell whose codes are the i-th and j-th nearest comes after all i*j cells of nearer codes, so among
        the first n cells only pairs with i*j <= n have to be looked at.
        """
        n = min(visits or self.visits, self.k**2)
        i, j = np.meshgrid(np.arange(self.k), np.arange(self.k), indexing="ij")
        fit = (i + 1) * (j + 1) <= n
        i, j, h, out = i[fit], j[fit], self.books[0].shape[1], []
        for a in range(0, len(x), 512):
            d1, d2 = distances(x[a : a + 512, :h], self.books[0]), distances(x[a : a + 512, h:], self.books[1])
            o1, o2 = d1.argsort(1), d2.argsort(1)
            total = np.take_along_axis(d1, o1, 1)[:, i] + np.take_along_axis(d2, o2, 1)[:, j]
            take = np.argpartition(total, n - 1, axis=1)[:, :n] if n < total.shape[1] else np.argsort(total, axis=1)
            take = np.take_along_axis(take, np.take_along_axis(total, take, 1).argsort(1), 1)
            out.append(np.take_along_axis(o1, i[take], 1) * self.k + np.take_along_axis(o2, j[take], 1))
        return np.concatenate(out).astype(np.int32) if out else np.zeros((0, n), np.int32)


def fit(sample: np.ndarray, n: int, threshold: float, recall: float = RECALL, seed: int = 3) -> MultiIndex:
    """Codebooks for n vectors from a sample of unit vectors, and the number of visits that finds `recall` of partners at the threshold."""
    rng = np.random.default_rng(seed)
    k = int(min(1024, max(1, np.sqrt(n / 64)), len(sample)))
    h = max(1, sample.shape[1] // 2)
    index = MultiIndex(_codebook(sample[:, :h], k, rng), _codebook(sample[:, h:], k, rng), 1)
    some = sample[rng.choice(len(sample), min(1024, len(sample)), replace=False)]
    side = rng.normal(size=some.shape)
    side -= (side * some).sum(1, keepdims=True) * some
    partner = threshold * some + np.sqrt(1 - threshold**2) * side / np.maximum(np.linalg.norm(side, axis=1, keepdims=True), 1e-300)
    goal, visits = index.home(partner), 1
    while visits < k * k:
        if (index.visited(some, visits) == goal[:, None]).any(1).mean() >= recall:
            break
        visits = min(k * k, visits + max(1, visits // 4))
    index.visits = visits
    return index


def _forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, smallest node of its component) for the nodes of some links, but for the smallest ones themselves."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = label.copy()
        np.minimum.at(low, x, label[y])
        np.minimum.at(low, y, label[x])
        np.minimum.at(low, label, low)
        low = low[low]
        if (low == label).all():
            break
        label = low
    moved = label != np.arange(len(nodes))
    return nodes[moved], nodes[label[moved]]


def link(vectors: DataFrame, threshold: float = 0.95, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every row."""
    spark = vectors.sparkSession
    rows = vectors.select(F.col(key).cast("long").alias("vec_id"), F.col(vector).cast("array<double>").alias("v"))
    sound = F.col("v").isNotNull() & (F.size("v") > 0) & F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0)
    good = rows.filter(sound).filter("vec_id is not null")
    common = good.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").limit(1).collect()
    dim = common[0]["n"] if common else 0
    good = good.filter(F.size("v") == dim)
    one = written(good.groupBy("v").agg(F.min("vec_id").alias("rep"), F.count("*").alias("weight")), "vectors")
    n = one.count()
    if not n:
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    sample = np.array([r[0] for r in one.orderBy(F.xxhash64("rep"), "rep").limit(SAMPLE).select("v").collect()])
    index = fit(unit(sample), n, threshold)
    k = index.k
    shared = spark.sparkContext.broadcast(index)

    def arrays(batch):
        flat = batch.column(0).flatten().to_numpy(zero_copy_only=False)
        return unit(flat.reshape(len(batch), dim)), batch.column(1).to_numpy(zero_copy_only=False), batch.column(2).to_numpy(zero_copy_only=False)

    def homes(batches):
        for batch in batches:
            code, count = np.unique(shared.value.home(arrays(batch)[0]) // k, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(code.astype(np.int32)), pa.array(count.astype(np.int64))], ["code", "n"])

    sizes = {r["code"]: r["n"] for r in one.mapInArrow(homes, "code int, n long").groupBy("code").agg(F.sum("n").alias("n")).collect()}  # a row for each code
    blocks = np.array([-(-sizes.get(c, 0) // BLOCK) for c in range(k)], np.int64)
    begin = np.concatenate([[0], blocks.cumsum()])

    def deal(batches):
        index = shared.value
        for batch in batches:
            for a in range(0, len(batch), 1024):
                x, ids, weight = arrays(batch.slice(a, 1024))
                home, seen = index.home(x).astype(np.int32), index.visited(x)
                code = home // k
                own = begin[code] + (ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)).astype(np.int64) % blocks[code]
                out = []
                for block in np.unique(own):
                    out.append((int(block), 0, own == block))
                seats = [np.unique(r // k) for r in seen]
                row, to = np.repeat(np.arange(len(x)), [len(s) for s in seats]), np.concatenate(seats)
                for c in np.unique(to):
                    pick = np.zeros(len(x), bool)
                    pick[row[to == c]] = True
                    out.extend((int(b), 1, pick) for b in range(begin[c], begin[c + 1]))
                names = ["block", "kind", "ids", "weight", "home", "seen", "x"]
                columns = [[o[0] for o in out], [o[1] for o in out], *([arr[o[2]].tobytes() for o in out] for arr in (ids, weight, home, seen, x))]
                kinds = [pa.int32(), pa.int32(), *[pa.binary()] * 5]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names)

    def match(batches):
        block, held, base = None, [], None

        def emit(ids, other, kind):
            return pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), kind, np.int32)), pa.array(ids), pa.array(other)], ["kind", "a", "b"])

        for batch in batches:
            for r in range(len(batch)):
                b, kind, *blobs = (batch.column(c)[r].as_py() for c in range(7))
                ids, weight, home = np.frombuffer(blobs[0], np.int64), np.frombuffer(blobs[1], np.int64), np.frombuffer(blobs[2], np.int32)
                seen, x = np.frombuffer(blobs[3], np.int32).reshape(len(ids), -1), np.frombuffer(blobs[4]).reshape(len(ids), -1)
                if b != block:
                    block, held, base = b, [], None
                if kind == 0:
                    held.append((ids, weight, home, seen, x))
                    continue
                if base is None:
                    if not held:
                        continue
                    base = [np.concatenate(p) for p in zip(*held, strict=True)]
                    order = base[2].argsort(kind="stable")
                    base = [p[order] for p in base]
                    cells, starts = np.unique(base[2], return_index=True)
                    ends = np.append(starts[1:], len(order))
                q, cell = np.nonzero(np.isin(seen, cells))
                cell = seen[q, cell]
                order = cell.argsort(kind="stable")
                q, cell = q[order], cell[order]
                wanted, first = np.unique(cell, return_index=True)
                at = np.searchsorted(cells, wanted)
                for c, lo, hi in zip(at, first, [*first[1:], len(q)], strict=True):
                    asks, own = q[lo:hi], slice(starts[c], ends[c])
                    i, j = np.nonzero(x[asks] @ base[4][own].T >= threshold)
                    i, j = asks[i], j + starts[c]
                    other = ids[i] != base[0][j]
                    i, j = i[other], j[other]
                    if not len(i):
                        continue
                    alone = ~(base[3][j] == home[i][:, None]).any(1)  # the partner does not come by itself
                    who, slot = np.unique(np.concatenate([ids[i], base[0][j[alone]]]), return_inverse=True)
                    yield emit(who, np.bincount(slot, np.concatenate([base[1][j], weight[i[alone]]])).astype(np.int64), 0)
                    yield emit(*_forest(ids[i], base[0][j]), 1)

    dealt = one.mapInArrow(deal, "block int, kind int, ids binary, weight binary, home binary, seen binary, x binary")
    found = written(dealt.repartitionById(max(1, int(begin[-1])), F.col("block")).sortWithinPartitions("block", "kind").mapInArrow(match, "kind int, a long, b long"), "links")
    links = found.filter("kind = 0").groupBy(F.col("a").alias("rep")).agg(F.sum("b").alias("n"))
    parts = components(spark, found.filter("kind = 1").select("a", "b")).withColumnRenamed("node", "rep")
    told = one.join(links, "rep", "left").join(parts, "rep", "left")
    told = told.select("v", (F.coalesce("n", F.lit(0)) + F.col("weight") - 1).cast("long").alias("n"), F.coalesce("component", "rep").alias("component"))
    out = rows.join(told, "v", "left")
    own = F.coalesce("component", "vec_id")
    return out.select("vec_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), own.alias("component_id"), (F.col("vec_id") == own).alias("kept"))
