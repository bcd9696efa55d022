"""Pieces that several text operators share: text buffers, hashing, written tables, pair checks, components.

Words are maximal runs of bytes other than 0x20 and 0x09-0x0D, and only A-Z are lower-cased, so all
word work is done on UTF-8 bytes with NumPy. Null texts count as empty texts everywhere.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.folders import shared_root as shared_dir

U64 = np.uint64
SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: Bytes of text that are turned into 64-bit arrays at once; a longer document is a slice of its own.
SLICE_BYTES = 1 << 20

_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_BYTE = np.random.default_rng(20240607).integers(1, 2**63, 256, dtype=np.uint64)
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


@contextmanager
def released(spark: SparkSession) -> Iterator[None]:
    """What is planned and run inside leaves no shuffle files: Spark removes them at the end of each execution."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    was = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.unset(name) if was is None else spark.conf.set(name, was)


def written(df: DataFrame, name: str) -> DataFrame:
    """The rows of df from a table in the shared folder: lineage ends there, and lost executors cost nothing."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/keysieve/{name}-{uuid.uuid4().hex}"
    with released(spark):
        df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._written = path
    return out


def sweep(spark: SparkSession) -> None:
    """Lets Spark drop the shuffle files of plans that are gone: its cleaner waits for the driver's garbage collector."""
    spark.sparkContext._jvm.System.gc()


def forget(*tables: DataFrame) -> None:
    """Deletes written tables that nothing reads any more, and the shuffle files behind them."""
    for t in tables:
        jvm, conf = t.sparkSession.sparkContext._jvm, t.sparkSession.sparkContext._jsc.hadoopConfiguration()
        path = jvm.org.apache.hadoop.fs.Path(t._written)
        path.getFileSystem(conf).delete(path, True)
    sweep(tables[0].sparkSession)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit mixer."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U64(27))
    x = x * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def text_buffer(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and offsets of a string array; nulls are empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if texts.null_count:
        texts = texts.fill_null("")
    wide = pa.types.is_large_string(texts.type) or pa.types.is_large_binary(texts.type)
    n, kind = len(texts), np.int64 if wide else np.int32
    _, ends, data = texts.buffers()
    if n == 0 or data is None:
        return np.zeros(0, np.uint8), np.zeros(n + 1, np.int64)
    offsets = np.frombuffer(ends, kind, n + 1 + texts.offset)[texts.offset :].astype(np.int64)
    return np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(offsets: np.ndarray, most: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of documents with at most that many bytes, or one document."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + most, "right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = 1 << max(SLICE_BYTES.bit_length(), (n + 1).bit_length())
    if size not in _powers:
        out = []
        for base in (_BASE, _INVERSE):
            p = np.ones(size, np.uint64)
            have = 1
            while have < size:
                step = U64(pow(base, have, 1 << 64))
                p[have : 2 * have] = p[:have] * step
                have *= 2
            out.append(p)
        _powers.clear()
        _powers[size] = (out[0], out[1])
    return _powers[size]


def words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of all words, and the number of words before each document (one entry more than documents)."""
    n = len(data)
    if n == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    solid = ~SPACE[data]
    first = np.zeros(n + 1, bool)
    first[offsets] = True
    before = np.empty(n, bool)
    before[0] = False
    before[1:] = solid[:-1]
    starts = np.flatnonzero(solid & (~before | first[:n]))
    after = np.empty(n, bool)
    after[-1] = False
    after[:-1] = solid[1:]
    ends = np.flatnonzero(solid & (~after | first[1:])) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, offsets: np.ndarray, fold: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """A 64-bit hash of each (lower-cased) word, and the number of words before each document."""
    starts, ends, counts = words(data, offsets)
    if not len(starts):
        return np.zeros(0, np.uint64), counts
    up, down = _power(len(data))
    sums = np.empty(len(data) + 1, np.uint64)
    sums[0] = 0
    np.cumsum(_BYTE[LOWER[data] if fold else data] * up[: len(data)], out=sums[1:])
    return mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64)), counts


def shingles(data: np.ndarray, offsets: np.ndarray, k: int) -> list[np.ndarray]:
    """For each document its sorted distinct hashes of k successive words; fewer words count as one shingle."""
    out: list[np.ndarray] = []
    for i, j in slices(offsets):
        part = offsets[i : j + 1] - offsets[i]
        hashes, counts = word_hashes(data[offsets[i] : offsets[j]], part)
        if len(hashes) >= k:
            joined = hashes[: len(hashes) - k + 1].copy()
            for t in range(1, k):
                joined = mix(joined * U64(0x9E3779B97F4A7C15) + hashes[t : len(hashes) - k + 1 + t])
        else:
            joined = hashes[:0]
        for d in range(j - i):
            a, b = int(counts[d]), int(counts[d + 1])
            if b - a >= k:
                out.append(np.unique(joined[a : b - k + 1]))
            elif b > a:
                h = hashes[a : a + 1]
                for t in range(a + 1, b):
                    h = mix(h * U64(0x9E3779B97F4A7C15) + hashes[t : t + 1])
                out.append(mix(h ^ U64(b - a)))
            else:
                out.append(hashes[:0])
    return out


def common(a: np.ndarray, b: np.ndarray) -> int:
    """Size of the intersection of two sorted arrays of distinct values."""
    if len(a) > len(b):
        a, b = b, a
    if not len(a):
        return 0
    at = np.searchsorted(b, a)
    at[at == len(b)] = 0
    return int((b[at] == a).sum())


def bucket_of(keys: np.ndarray, bits: int) -> np.ndarray:
    return (keys >> U64(64 - bits)).astype(np.int32) if bits else np.zeros(len(keys), np.int32)


def bucket_bits(rows: int, each: int = 2000, least: int = 5, most: int = 20) -> int:
    """Bits of a hash that name a bucket, so that a bucket holds what about that many documents give."""
    return min(most, max(least, int(np.ceil(np.log2(max(1, rows) / each + 1)))))


def blobs(keys: np.ndarray, bits: int, *columns: np.ndarray) -> pa.RecordBatch:
    """One row for each bucket with the columns as packed bytes, sorted by key."""
    order = np.argsort(keys, kind="stable")
    buckets = bucket_of(keys[order], bits)
    cut = np.flatnonzero(np.diff(buckets)) + 1
    begins, ends = np.concatenate([[0], cut]), np.concatenate([cut, [len(keys)]])
    if not len(keys):
        begins = ends = begins[:0]
    packed = [c[order] for c in (keys, *columns)]
    rows = [pa.array(buckets[begins.astype(np.int64)], pa.int32())]
    for c in packed:
        rows.append(pa.array([c[i:j].tobytes() for i, j in zip(begins, ends, strict=True)], pa.binary()))
    return pa.RecordBatch.from_arrays(rows, ["bucket", *(f"c{i}" for i in range(len(packed)))])


def by_bucket(batches: Iterator[pa.RecordBatch], kinds: list[type]) -> Iterator[tuple[int, list[np.ndarray]]]:
    """Whole buckets from rows that come sorted by bucket."""
    bucket, parts = None, [[] for _ in kinds]
    for batch in batches:
        ids = batch.column(0).to_pylist()
        columns = [batch.column(1 + i).to_pylist() for i in range(len(kinds))]
        for r, b in enumerate(ids):
            if b != bucket and bucket is not None:
                yield bucket, [np.frombuffer(b"".join(p), k) for p, k in zip(parts, kinds, strict=True)]
                parts = [[] for _ in kinds]
            bucket = b
            for p, c in zip(parts, columns, strict=True):
                p.append(c[r])
    if bucket is not None:
        yield bucket, [np.frombuffer(b"".join(p), k) for p, k in zip(parts, kinds, strict=True)]


def gathered(df: DataFrame) -> DataFrame:
    """Rows of one bucket together and in turn."""
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return df.repartition(n, "bucket").sortWithinPartitions("bucket")


class Bits:
    """A Bloom filter of a fixed number of bits in 64 segments; a full one passes everything, which costs time but loses nothing."""

    SEGMENTS = 64

    def __init__(self, log2: int, data: np.ndarray | None = None):
        self.log2, self.data = log2, np.zeros(1 << (log2 - 3), np.uint8) if data is None else data

    @staticmethod
    def size_for(n: int, most_log2: int) -> int:
        return min(most_log2, max(13, int(np.ceil(np.log2(12 * n + 1)))))

    @staticmethod
    def segment(keys: np.ndarray) -> np.ndarray:
        return (mix(keys ^ U64(0x5851F42D4C957F2D)) >> U64(58)).astype(np.int32)

    def _places(self, keys: np.ndarray) -> Iterator[np.ndarray]:
        first = self.segment(keys).astype(np.uint64) << U64(self.log2 - 6)
        a = mix(keys + U64(0x2545F4914F6CDD1D))
        for _ in range(3):
            yield first | (a >> U64(70 - self.log2))
            a = mix(a + U64(0x9E3779B97F4A7C15))

    def add(self, keys: np.ndarray) -> None:
        for p in self._places(keys):
            np.bitwise_or.at(self.data, (p >> U64(3)).astype(np.int64), np.left_shift(1, (p & U64(7)).astype(np.uint8)).astype(np.uint8))

    def has(self, keys: np.ndarray) -> np.ndarray:
        out = np.ones(len(keys), bool)
        for p in self._places(keys):
            out &= (self.data[(p >> U64(3)).astype(np.int64)] >> (p & U64(7)).astype(np.uint8)) & 1 == 1
        return out


def as_keys(column: pa.Array) -> np.ndarray:
    """A long column as unsigned keys; nulls are 0."""
    return column.fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)


def bits_of(df: DataFrame, column: str, log2: int) -> Bits:
    """A filter of a long column; each segment is filled by one task, so the driver gets its fixed size once."""

    def place(batches):
        for b in batches:
            keys = as_keys(b.column(0).drop_null())
            yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(Bits.segment(keys))], ["key", "segment"])

    def fill(batches):
        filters: dict[int, Bits] = {}
        for b in batches:
            keys, own = as_keys(b.column(0)), b.column(1).to_numpy(zero_copy_only=False)
            for s in np.unique(own).tolist():
                filters.setdefault(s, Bits(log2)).add(keys[own == s])
        size = (1 << (log2 - 3)) // Bits.SEGMENTS
        for s, f in filters.items():
            yield pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), pa.array([f.data[s * size : (s + 1) * size].tobytes()], pa.binary())], ["segment", "b"])

    placed = df.select(F.col(column).cast("long").alias("key")).mapInArrow(place, "key long, segment int")
    out, size = Bits(log2), (1 << (log2 - 3)) // Bits.SEGMENTS
    for s, x in placed.repartitionById(Bits.SEGMENTS, F.col("segment")).mapInArrow(fill, "segment int, b binary").collect():
        out.data[s * size : (s + 1) * size] |= np.frombuffer(x, np.uint8)
    return out


def having(docs: DataFrame, ids: DataFrame, most_log2: int = 25) -> DataFrame:
    """Rows of docs whose doc_id is among the distinct ids: a superset by a filter of bounded size, then an exact join."""
    log2 = Bits.size_for(ids.count(), most_log2)
    field = docs.sparkSession.sparkContext.broadcast(bits_of(ids, "doc_id", log2).data)

    def keep(batches):
        f = Bits(log2, field.value)
        for b in batches:
            column = b.column(b.schema.get_field_index("doc_id"))
            yield b.filter(pa.array(f.has(as_keys(column)) & column.is_valid().to_numpy(zero_copy_only=False)))

    return docs.mapInArrow(keep, docs.schema).join(ids, "doc_id")


def components(spark: SparkSession, edges: DataFrame) -> DataFrame:
    """(node, component) for every node of the edges (a, b); component is the smallest node that can be reached.

    Each round moves labels across edges and then follows labels of labels, so the number of rounds
    follows the logarithm of a component's diameter. Sums are combined before each exchange.
    """
    e = edges.filter("a <> b").select(F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b")))).alias("x")).select("x.*").distinct()
    e = written(e, "edges")
    labels = written(e.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("label")), "labels")
    while True:
        near = e.join(labels, e.b == labels.node).groupBy("a").agg(F.min("label").alias("near"))
        step = labels.join(near, labels.node == near.a).select("node", "label", F.least("label", "near").alias("low"))
        # the old label's own node hears of the lower label too, so that whole trees hook at once
        hook = step.groupBy(F.col("label").alias("node")).agg(F.min("low").alias("hook"))
        step = step.join(hook, "node", "left").select("node", "label", F.least("low", F.coalesce("hook", "low")).alias("low"))
        up = step.select(F.col("node").alias("low"), F.col("low").alias("top"))
        new = written(step.join(up, "low", "left").select("node", F.coalesce("top", "low").alias("label"), (F.col("label") != F.coalesce("top", "low")).alias("moved")), "labels")
        forget(labels)
        if not new.filter("moved").limit(1).count():
            forget(e)
            out = new.select("node", F.col("label").alias("component"))
            out._written = new._written
            return out
        labels = new
