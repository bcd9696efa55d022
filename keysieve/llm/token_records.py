"""Token ids as length-delimited binary records with an offset index.

A record is: payload length (8 bytes), its masked checksum (4), the payload, the payload's masked checksum (4),
and one end byte 0x0A. A payload is the doc_id (8 bytes, signed), the bytes per id (1: 2 or 4) and the ids; all
numbers are little-endian. Checksums are CRC-32 rotated right by 15 bits plus a fixed number, so that a checksum
of data that holds checksums stays useful. Files are in ascending doc_id order by the numbers of part and file in
their names; the index table has file, offset, length, doc_id, n_tokens, start (ids of all documents before it)
and ids_crc32 of each record, so that a shuffled reader can seek to any record and read it alone.

Records reach storage through Spark's own writer, so any file system of the cluster serves and a lost executor's
attempt leaves nothing behind.

Defined results: null texts are empty (their record holds only the end id). Rows of equal doc_id stand in the
order of their texts. Rows without doc_id come last, by text; in a record the largest number stands for none.
"""

from __future__ import annotations

import os
import re
import struct
import unicodedata
import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import shared_dir

#: Fixed value: what is added to a rotated checksum.
MASK = 0xA282EAD8
#: Pieces whose ids a worker remembers, and most documents in a file.
MEMO, PER_FILE = 1_300_000, 4000
#: Stands for a null doc_id.
LAST = 2**63 - 1
_NARROW = 0x250


def masked(data: bytes) -> int:
    crc = zlib.crc32(data)
    return (((crc >> 15) | (crc << 17)) + MASK) & 0xFFFFFFFF


def frame(payload: bytes) -> bytes:
    head = struct.pack("<Q", len(payload))
    return b"".join((head, struct.pack("<I", masked(head)), payload, struct.pack("<I", masked(payload)), b"\n"))


def unframe(data: bytes, at: int) -> tuple[bytes, int]:
    """The payload of the record at an offset, and the offset after it; damage is an error."""
    head = data[at : at + 8]
    (n,), (crc,) = struct.unpack("<Q", head), struct.unpack_from("<I", data, at + 8)
    if crc != masked(head):
        raise ValueError(f"damaged record length at {at}")
    payload = bytes(data[at + 12 : at + 12 + n])
    (crc,) = struct.unpack_from("<I", data, at + 12 + n)
    if crc != masked(payload) or data[at + 16 + n : at + 17 + n] != b"\n":
        raise ValueError(f"damaged record at {at}")
    return payload, at + 17 + n


def pack(doc_id: int, ids: bytes, width: int) -> bytes:
    return struct.pack("<qB", doc_id, width) + ids


def unpack(payload: bytes) -> tuple[int, np.ndarray]:
    doc_id, width = struct.unpack_from("<qB", payload)
    return doc_id, np.frombuffer(payload, f"<u{width}", offset=9)


def _class(which) -> str:
    return "".join(f"\\x{c:02x}" if c < 256 else f"\\u{c:04x}" for c in range(_NARROW) if which(unicodedata.category(chr(c))[0], c))


_LETTERS, _NUMBERS = _class(lambda k, c: k == "L"), _class(lambda k, c: k == "N")
_BLANKS = _class(lambda k, c: 9 <= c <= 13 or c in (0x20, 0x85, 0xA0))
#: The vocabulary's pieces; letters are tried first, as no other alternative begins with one.
_PIECES = re.compile(rf"[{_LETTERS}]+|'s|'t|'re|'ve|'m|'ll|'d|[{_NUMBERS}]|[^{_BLANKS}{_LETTERS}{_NUMBERS}]+")


def narrow(text: str) -> bool:
    """Whether all characters lie below U+0250."""
    if text.isascii():
        return True
    try:
        text.encode("latin-1")
        return True
    except UnicodeEncodeError:
        return max(text) < chr(_NARROW)


class Encoder:
    """Ids of whole texts as the tokenizers library gives them.

    The word vocabulary treats each piece of a text alone, so the library encodes every distinct piece once and
    pieces are looked up. Texts with characters from U+0250 on, or with what may be a special string, go to the
    library whole.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        self.library, self.bare = Tokenizer.from_file(path), Tokenizer.from_file(path)
        # for pieces, which are normal and apart already
        self.bare.normalizer = normalizers.Sequence([])
        self.bare.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        self.width = 2 if self.library.get_vocab_size(with_added_tokens=True) <= 1 << 16 else 4
        self.memo: dict[str, bytes] = {}
        vocab = self.library.get_vocab(with_added_tokens=False)
        self.last = np.zeros(max(vocab.values()) + 1, bool)
        self.last[[i for t, i in vocab.items() if t.endswith("</w>")]] = True

    def raw(self, ids: list[int]) -> bytes:
        return np.array(ids, f"<u{self.width}").tobytes()

    def encode(self, texts: list[str]) -> list[bytes]:
        memo, out, near = self.memo, [b""] * len(texts), []
        for i, t in enumerate(texts):
            if "<|" not in t and narrow(t):
                near.append((i, _PIECES.findall(t.lower())))
            else:
                out[i] = self.raw(self.library.encode(t, add_special_tokens=False).ids)
        if len(memo) > MEMO:
            memo.clear()
        # asked piece by piece: a difference of sets would walk through the whole memo
        new = [p for p in set().union(*(p for _, p in near)) if p not in memo]
        for i in range(0, len(new), 2000):
            self._learn(new[i : i + 2000])
        get = memo.__getitem__
        for i, pieces in near:
            out[i] = b"".join(map(get, pieces))
        return out

    def _learn(self, pieces: list[str]) -> None:
        """Encodes pieces in one text; the last token of each piece carries the mark of a word's end."""
        ids = np.array(self.bare.encode_batch_fast([" ".join(pieces)], add_special_tokens=False)[0].ids, f"<u{self.width}")
        ends = np.flatnonzero(self.last[ids]) + 1
        if len(ends) != len(pieces):
            raise ValueError("the vocabulary does not mark the ends of words")
        raw, a = ids.tobytes(), 0
        for piece, b in zip(pieces, (ends * self.width).tolist(), strict=True):
            self.memo[piece] = raw[a:b]
            a = b


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def write(docs: DataFrame, path: str, out: str, end_id: int = 2, text: str = "text") -> None:
    """Encodes, frames and writes every row; texts move once, to their place in doc_id order."""
    spark = docs.sparkSession

    def run(batches):
        e = encoder(path)
        end = e.raw([end_id])
        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1)
            for i in range(0, len(ids), 256):
                got = e.encode(texts.slice(i, 256).to_pylist())
                yield pa.RecordBatch.from_arrays([pa.array([frame(pack(d, x + end, e.width))[:-1] for d, x in zip(ids[i : i + 256], got, strict=True)], pa.binary())], ["record"])

    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST)).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    # cuts from the ids alone, so that choosing them reads no text
    cuts = sorted({min(int(c), LAST) for c in rows.filter(F.col("doc_id") < LAST).approxQuantile("doc_id", [i / n for i in range(1, n)], 0.1 / n)}) if n > 1 else []
    seat = F.size(F.filter(F.lit(cuts), lambda c: F.col("doc_id") >= c)) if cuts else F.lit(0)
    ranged = rows.repartitionById(len(cuts) + 1, seat).sortWithinPartitions("doc_id", "text")
    framed = ranged.mapInArrow(run, "record binary").select(F.col("record").cast("string").alias("value"))
    # the writer ends each value with the end byte of its record
    framed.write.option("lineSep", "\n").option("maxRecordsPerFile", PER_FILE).text(out)


def read(spark: SparkSession, path: str) -> DataFrame:
    """(file, offset, length, doc_id, before, n_tokens, ids_crc32) of all records, checked; before: ids in the file before it."""

    def run(batches):
        for batch in batches:
            for name, content in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                data, at, before, rows = memoryview(content.as_buffer()), 0, 0, []
                while at < len(data):
                    payload, after = unframe(data, at)
                    doc_id, ids = unpack(payload)
                    rows.append((at, after - at, None if doc_id == LAST else doc_id, before, len(ids), zlib.crc32(ids.astype("<u4").tobytes())))
                    at, before = after, before + len(ids)
                columns = list(zip(*rows, strict=True)) or [()] * 6
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(rows), pa.string()), *(pa.array(c, pa.int64()) for c in columns)], ["file", "offset", "length", "doc_id", "before", "n_tokens", "ids_crc32"])

    files = spark.read.format("binaryFile").load(path).select(F.element_at(F.split("path", "/"), -1).alias("file"), "content")
    return files.mapInArrow(run, "file string, offset long, length long, doc_id long, before long, n_tokens long, ids_crc32 long")


def in_order(files: DataFrame) -> DataFrame:
    """(file, begin) of (file, ids): ids of all files before, by the numbers of part and file in a name.

    Sums run within each part; only one row for each part is brought into one order.
    """
    number = lambda p: F.regexp_extract("file", p, 1).cast("long")
    named = files.withColumns({"part": number(r"^part-(\d+)"), "nth": F.coalesce(number(r"-c(\d+)[^/]*$"), F.lit(0))})
    before = Window.rowsBetween(Window.unboundedPreceding, -1)
    inside = named.withColumn("inside", F.coalesce(F.sum("ids").over(before.partitionBy("part").orderBy("nth")), F.lit(0)))
    parts = named.groupBy("part").agg(F.sum("ids").alias("all")).withColumn("earlier", F.coalesce(F.sum("all").over(before.orderBy("part")), F.lit(0)))
    return inside.join(parts, "part").select("file", (F.col("inside") + F.col("earlier")).alias("begin"))


def index(spark: SparkSession, path: str, out: str) -> DataFrame:
    """Writes the offset index of the files and returns it."""
    read(spark, path).write.parquet(out)
    found = spark.read.parquet(out)
    begins = in_order(found.groupBy("file").agg(F.sum("n_tokens").alias("ids")))
    return found.join(begins, "file").select("file", "offset", "length", "doc_id", (F.col("begin") + F.col("before")).alias("start"), "n_tokens", "ids_crc32")


def fetch(spark: SparkSession, path: str, rows: list) -> list[np.ndarray]:
    """Ids of some records by index rows (file, offset, length): each record's bytes alone are read."""
    jvm, out = spark.sparkContext._jvm, []
    for r in rows:
        file = jvm.org.apache.hadoop.fs.Path(f"{path}/{r['file']}")
        stream = file.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).open(file)
        try:
            stream.seek(r["offset"])
            content = bytes(jvm.org.apache.commons.io.IOUtils.toByteArray(stream, int(r["length"])))
        finally:
            stream.close()
        out.append(unpack(unframe(content, 0)[0])[1])
    return out


def tokenize_to_files(docs: DataFrame, path: str, end_id: int = 2) -> DataFrame:
    """Writes files and index into the shared folder, and returns (doc_id, start, n_tokens, ids_crc32) as read back from them."""
    spark = docs.sparkSession
    where = f"{shared_dir(spark)}/keysieve/records-{uuid.uuid4().hex}"
    write(docs, path, f"{where}/files", end_id)
    return index(spark, f"{where}/files", f"{where}/index").select("doc_id", "start", "n_tokens", "ids_crc32", "file", "offset", "length")
