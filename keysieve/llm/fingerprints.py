"""Document fingerprints: threshold-scaled sketches of word shingles.

A fingerprint keeps every hash of a document's distinct shingles (five lower-cased words; fewer words are
one shingle) that lies below a fixed fraction of the hash range. So its size follows the document's, the
fingerprint of a union is the union of fingerprints, and both resemblance and containment of very unequal
documents can be estimated from two fingerprints alone. A document with words whose hashes all lie above
the fraction keeps its smallest one, so that short texts still have a fingerprint of their own; such a
single hash takes part in a comparison like the others. The text form is the sorted hashes as 16 hex
digits each.

Defined results: null and empty texts, and those without words, have the empty fingerprint. Two empty
fingerprints have likeness 1 (their word sets are equal), an empty and another one 0.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import common, shingles, text_buffer

WORDS, FRACTION = 5, 1 / 8
#: Stands for a null doc_id, which comes after all others.
LAST = 2**63 - 1


def sketch(hashes: np.ndarray, fraction: float = FRACTION) -> np.ndarray:
    """The sorted hashes below the fraction; hashes are sorted and distinct."""
    kept = hashes[: np.searchsorted(hashes, np.uint64(int(fraction * 2.0**64) - 1), "right")]
    return kept if len(kept) else hashes[:1]


def to_text(kept: np.ndarray) -> str:
    return kept.astype(">u8").tobytes().hex()


def from_text(text: str) -> np.ndarray:
    return np.frombuffer(bytes.fromhex(text), ">u8").astype(np.uint64)


def merge(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The fingerprint of the union of two shingle sets."""
    return sketch(np.union1d(a, b), FRACTION)


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Estimated resemblance: shared over all hashes."""
    if not len(a) and not len(b):
        return 1.0
    both = common(a, b)
    return both / (len(a) + len(b) - both)


def containment(a: np.ndarray, b: np.ndarray) -> float:
    """Estimated share of a's shingles that b has too."""
    return common(a, b) / len(a) if len(a) else 1.0


def fingerprint(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with n_chars and fingerprint."""

    def run(batches):
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index(text))
            found = [to_text(sketch(h)) for h in shingles(*text_buffer(texts), WORDS)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(found, pa.string())], [*batch.schema.names, "fingerprint"])

    docs = docs.drop("fingerprint")
    fields = ", ".join(f"`{f.name.replace('`', '``')}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return docs.mapInArrow(run, f"{fields}, fingerprint string")


def with_successor(docs: DataFrame, parts: int | None = None) -> DataFrame:
    """(doc_id, text, seat, spare): rows dealt by ranges of doc_id, so that each range ends with a spare copy of the row after it.

    Only ids are read to find the ranges and their first rows; each text moves once. Equal ids stand in the order of their texts.
    """
    spark = docs.sparkSession
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST)).alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    n = rows.count()
    parts = parts or max(1, min(1 << 16, max(n // 4000, int(spark.conf.get("spark.sql.shuffle.partitions")))))
    cuts = sorted(set(rows.filter(F.col("doc_id") < LAST).approxQuantile("doc_id", [i / parts for i in range(1, parts)], 0.25 / parts))) if n and parts > 1 else []
    cuts = [min(int(c), LAST) for c in cuts]
    seat = F.expr(f"size(filter(array({','.join(f'{c}L' for c in cuts)}), c -> doc_id >= c))") if 0 < len(cuts) <= 16 else None
    if seat is None:
        shared = spark.sparkContext.broadcast(np.array(cuts, np.int64))

        def place(batches):
            for b in batches:
                ids = b.column(0).to_numpy(zero_copy_only=False)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.searchsorted(shared.value, ids, "right").astype(np.int32))], ["doc_id", "seat"])

        firsts = rows.select("doc_id").mapInArrow(place, "doc_id long, seat int").groupBy("seat").agg(F.min("doc_id").alias("first"))
    else:
        firsts = rows.select("doc_id", seat.alias("seat")).groupBy("seat").agg(F.min("doc_id").alias("first"))
    begin = sorted((r["first"], r["seat"]) for r in firsts.collect())  # one row for each range
    used = [s for _, s in begin]
    before = {f: used[i - 1] for i, (f, _) in enumerate(begin)}  # the first row's spare goes to the range before, or to the last
    table = spark.sparkContext.broadcast((np.array([f for f, _ in begin], np.int64), before))

    def deal(batches):
        starts, before = table.value
        for b in batches:
            ids = b.column(0).to_numpy(zero_copy_only=False)
            at = np.searchsorted(starts, ids, "right") - 1
            spare = np.flatnonzero(starts[at] == ids)
            seats = np.concatenate([np.array([s for s in used], np.int32)[at], np.array([before[int(ids[i])] for i in spare], np.int32)])
            rows = np.concatenate([np.arange(len(ids)), spare])
            taken = b.take(pa.array(rows))
            yield pa.RecordBatch.from_arrays([*taken.columns, pa.array(seats, pa.int32()), pa.array(np.arange(len(rows)) >= len(ids))], ["doc_id", "text", "seat", "spare"])

    if not begin:
        return rows.withColumns({"seat": F.lit(0), "spare": F.lit(False)})
    dealt = rows.mapInArrow(deal, "doc_id long, text string, seat int, spare boolean")
    return dealt.repartitionById(max(used) + 1, F.col("seat")).sortWithinPartitions("seat", "spare", "doc_id", "text")


def compare_with_successor(docs: DataFrame) -> DataFrame:
    """For every document: its fingerprint, that of its text with the second half replaced by the next document's beginning, and both likenesses.

    The next document is that with the next larger doc_id (rows of equal id by text); the last one's is the first.
    Rows without doc_id come after all others, by text; inside, the largest number stands for their doc_id.
    """

    def run(batches):
        held = None  # the row that waits for the next one

        def emit(done):
            texts, nexts = [d[1] for d in done], [d[2] for d in done]
            edited = [t[: len(t) - len(t) // 2] + x[: len(t) // 2] for t, x in zip(texts, nexts, strict=True)]
            own, new = (shingles(*text_buffer(pa.array(x, pa.string())), WORDS) for x in (texts, edited))
            after = shingles(*text_buffer(pa.array(nexts[-1:], pa.string())), WORDS)
            own, new = [sketch(h) for h in own], [sketch(h) for h in new]
            follow = [*own[1:], sketch(after[0])]
            return pa.RecordBatch.from_arrays(
                [
                    pa.array([None if d[0] == LAST else d[0] for d in done], pa.int64()),
                    pa.array([len(t) for t in texts], pa.int64()),
                    pa.array([hashlib.sha256(t.encode()).hexdigest() for t in edited], pa.string()),
                    pa.array(map(to_text, own), pa.string()),
                    pa.array(map(to_text, new), pa.string()),
                    pa.array([likeness(a, b) for a, b in zip(own, new, strict=True)]),
                    pa.array([likeness(a, b) for a, b in zip(own, follow, strict=True)]),
                    pa.array([containment(a, b) for a, b in zip(own, new, strict=True)]),
                ],
                ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next", "contained_in_edited"],
            )

        for batch in batches:
            done, size = [], 0
            for doc_id, text, seat, spare in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                if held is not None:
                    if held[2] == seat:
                        done.append((held[0], held[1], text))
                        size += len(text)
                        if size > 4_000_000:
                            yield emit(done)
                            done, size = [], 0
                    held = None
                held = None if spare else (doc_id, text, seat)
            if done:
                yield emit(done)

    kinds = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, contained_in_edited double"
    return with_successor(docs).select("doc_id", "text", "seat", "spare").mapInArrow(run, kinds)
