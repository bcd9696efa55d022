"""Removal of long byte strings that an earlier document has, by sparse suffix sorting.

A byte goes if a string of `length` bytes over it also starts in a document with a smaller doc_id. Every such
string has an anchor: the leftmost least of the hashes of its short substrings. Equal strings have their anchors
at the same place, so only anchors are compared, about one in eighteen bytes.

1. Anchors' hashes are counted; those that occur twice or more fill a filter of bounded size.
2. Anchors that pass send the bytes around them to the bucket of their hash. Of equal surroundings in a task only
   those of the smallest document are sent; the others are known to repeat it, so a passage that many documents
   share reaches its bucket once for each task.
3. A bucket orders the suffixes at its anchors, and the reversed prefixes before them, by deep-shallow sorting:
   multikey quicksort by machine words down to a shallow depth, all groups side by side, then blind tries for
   those that still agree. From both orders every string's class is known at each shift, and so the smallest
   document of the class.
4. Documents with removed bytes meet their places; all others are finished where they are read.

Strings are judged on the input, overlaps count, and matches never cross documents.

Defined results: null and empty texts have nothing to remove. Rows of equal doc_id never remove from each other;
if they have different texts, the places removed from any of them count for each of them as far as it reaches.
Rows without doc_id are returned whole. A text cut inside a character keeps the remaining bytes in the digest;
the text column drops the bytes that no longer form a character.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import _BYTE, U64, Bits, _power, as_keys, bits_of, bucket_bits, by_bucket, forget, gathered, mix, slices, text_buffer, written

LENGTH, GRAM = 50, 16
#: Largest filter of repeated anchors (2^27 bits), and bytes of text and anchors that a task holds before it sends them on.
FILTER_LOG2, FLUSH = 27, 1 << 20
#: Depth that the multikey quicksort goes to, in bytes; blind tries order what agrees so far.
SHALLOW = 24


def anchors(data: np.ndarray, offsets: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places of all anchors, their hashes, and running sums from which the hash of any range follows."""
    n = len(data)
    up, down = _power(n)
    sums = np.empty(n + 1, np.uint64)
    sums[0] = 0
    np.cumsum(_BYTE[data] * up[:n], out=sums[1:])
    if n < length:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64), sums
    hashes = mix((sums[gram:] - sums[:-gram]) * down[: n - gram + 1])
    bits = U64(max(20, int(n).bit_length()))
    least = ((hashes >> bits) << bits) | np.arange(len(hashes), dtype=np.uint64)
    span, have = length - gram + 1, 1
    while have * 2 <= span:
        least = np.minimum(least[:-have], least[have:])
        have *= 2
    if have < span:
        least = np.minimum(least[: len(least) - (span - have)], least[span - have :])
    inside = np.zeros(n + 1, np.int32)  # strings that stay in one document
    begin, end = offsets[:-1], offsets[1:] - length + 1
    some = end > begin
    inside[begin[some]] += 1
    np.add.at(inside, end[some], -1)
    places = (least[np.cumsum(inside[: len(least)]) > 0] & ((U64(1) << bits) - U64(1))).astype(np.int64)
    if len(places):
        places = places[np.concatenate([[True], places[1:] != places[:-1]])]
    return places, hashes[places], sums


def _named(docs: DataFrame, text: str) -> DataFrame:
    return docs.filter("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"))


def _parts(batches):
    """Documents in slices: ids, bytes, offsets."""
    for batch in batches:
        data, offsets = text_buffer(batch.column(1))
        ids = batch.column(0).to_numpy(zero_copy_only=False)
        for i, j in slices(offsets, FLUSH):
            yield ids[i:j], data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]


def _key(hashes: np.ndarray) -> np.ndarray:
    """What counting keeps of a hash: 56 bits."""
    return hashes >> U64(8)


def repeated(docs: DataFrame, bits: int, text: str) -> DataFrame:
    """(key) of all anchors that occur in two documents or more, or twice in a task's slice."""

    def send(batches):
        held, size = [], 0

        def flush():
            keys, n = np.unique(np.concatenate(held), return_counts=True)
            bucket = (keys >> U64(56 - bits)).astype(np.int64)
            low = np.ascontiguousarray(((keys << U64(8 + bits)) >> U64(24)).view(np.uint8).reshape(-1, 8)[:, :5])
            n = np.minimum(n, 2).astype(np.uint8)
            ends = [*(np.flatnonzero(np.diff(bucket)) + 1).tolist(), len(keys)]
            rows = [(int(bucket[a]), low[a:b].tobytes(), n[a:b].tobytes()) for a, b in zip([0, *ends[:-1]], ends, strict=True)]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.binary(), pa.binary()), strict=True)], ["bucket", "c0", "c1"])

        for _, data, offsets in _parts(batches):
            places, hashes, _ = anchors(data, offsets)
            owner = np.searchsorted(offsets, places, "right")
            order = np.lexsort((owner, hashes))  # once for each document
            h, o = hashes[order], owner[order]
            first = np.ones(len(h), bool)
            first[1:] = (h[1:] != h[:-1]) | (o[1:] != o[:-1])
            if len(h):
                held.append(_key(h[first]))
                size += len(held[-1])
            if size > 1 << 21:
                yield flush()
                held, size = [], 0
        if held:
            yield flush()

    def count(batches):
        for bucket, (raw, n) in by_bucket(batches, [np.uint8, np.uint8]):
            full = np.zeros((len(raw) // 5, 8), np.uint8)
            full[:, :5] = raw.reshape(-1, 5)
            keys, at = np.unique(full.view("<u8").ravel(), return_inverse=True)
            some = keys[np.bincount(at, n) > 1]
            # the lowest bits that 40 bits cannot hold are left out on both sides
            yield pa.RecordBatch.from_arrays([pa.array(((U64(bucket) << U64(40)) | some).view(np.int64))], ["key"])

    return gathered(_named(docs, text).mapInArrow(send, "bucket int, c0 binary, c1 binary")).mapInArrow(count, "key long")


def _counted(hashes: np.ndarray, bits: int) -> np.ndarray:
    """The key of a hash as `repeated` gives it: the bucket and the next 40 bits."""
    key = _key(hashes)
    return ((key >> U64(56 - bits)) << U64(40)) | ((key << U64(8 + bits)) >> U64(24))


def _around(data: np.ndarray, offsets: np.ndarray, places: np.ndarray, before: int, after: int):
    """Bytes around places as rows, and how many of them belong to the document on either side."""
    owner = np.searchsorted(offsets, places, "right") - 1
    left = np.minimum(places - offsets[owner], before).astype(np.uint8)
    right = np.minimum(offsets[owner + 1] - places, after).astype(np.uint8)
    padded = np.concatenate([np.zeros(before, np.uint8), data, np.zeros(after, np.uint8)])
    rows = np.lib.stride_tricks.sliding_window_view(padded, before + after)[places].copy()
    column = np.arange(before + after)
    rows[(column < before - left[:, None]) | (column >= before + right[:, None])] = 0
    return owner, left, right, rows


def surroundings(docs: DataFrame, field, log2: int, bits: int, text: str) -> DataFrame:
    """Rows by bucket of what anchors with repeated hashes have around them."""
    before, after = LENGTH - GRAM, LENGTH

    def send(batches):
        known = Bits(log2, field.value)
        held, size = [], 0

        def flush():
            hashes, names, ids, places, left, right, rows = (np.concatenate(c) for c in zip(*held, strict=True))
            order = np.lexsort((places, ids, names, hashes))
            same = np.zeros(len(order), bool)
            same[1:] = (hashes[order][1:] == hashes[order][:-1]) & (names[order][1:] == names[order][:-1])
            lead = order[~same]
            first = lead[np.cumsum(~same)[same] - 1]
            rest = order[same]
            # a smaller document of this task has the same bytes around: every string that fits is a repeat
            sure = rest[ids[rest] > ids[first]]
            again = ids[rest] == ids[first]
            rest, of = rest[again], (np.cumsum(~same)[same] - 1)[again]
            extra = np.bincount(of, minlength=len(lead)).astype("<u4")
            bucket = (hashes[lead] >> U64(64 - bits)).astype(np.int64)
            ends = [*(np.flatnonzero(np.diff(bucket)) + 1).tolist(), len(lead)]
            more = np.concatenate([[0], extra.cumsum()]).astype(np.int64)
            cols = [hashes[lead], ids[lead], places[lead].astype("<u4"), left[lead], right[lead], rows[lead], extra]
            own, at = ids[rest], places[rest].astype("<u4")
            out = [(int(bucket[a]), *(c[a:b].tobytes() for c in cols), own[more[a] : more[b]].tobytes(), at[more[a] : more[b]].tobytes()) for a, b in zip([0, *ends[:-1]], ends, strict=True)]
            if len(sure):
                low = np.maximum(0, LENGTH - right[sure].astype(np.int64)).astype(np.uint64)
                high = np.minimum(left[sure], LENGTH - GRAM).astype(np.uint64)
                masks = np.where(low <= high, ((U64(2) << high) - U64(1)) & ~((U64(1) << np.minimum(low, U64(63))) - U64(1)), U64(0))
                told = [masks.astype("<u8").tobytes(), ids[sure].tobytes(), places[sure].astype("<u4").tobytes(), *[b""] * 6]
                out.append((-1 - int(mix(hashes[sure[:1]])[0] >> U64(44)), *told))
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int32(), *[pa.binary()] * 9), strict=True)], ["bucket", *(f"c{i}" for i in range(9))])

        for ids, data, offsets in _parts(batches):
            places, hashes, sums = anchors(data, offsets)
            some = known.has(_counted(hashes, bits))
            places, hashes = places[some], hashes[some]
            if not len(places):
                continue
            owner, left, right, rows = _around(data, offsets, places, before, after)
            a, b = places - left, places + right
            names = mix((sums[b] - sums[a]) * _power(len(data))[1][a] + (left.astype(np.uint64) << U64(8) | right))
            held.append((hashes, names, ids[owner].astype(np.int64), places - offsets[owner], left, right, rows))
            size += len(places)
            if size > 100_000:
                yield flush()
                held, size = [], 0
        if held:
            yield flush()

    return _named(docs, text).mapInArrow(send, "bucket int, " + ", ".join(f"c{i} binary" for i in range(9)))


def blind_trie_order(strings: list[bytes]) -> list[int]:
    """The order of strings of one length (equal ones by their place), by a blind trie.

    A node holds the depth at which its children differ and the children by their byte there. A string goes down
    without looking at skipped bytes, is compared once with the leaf it reaches, and is put in where they differ.
    """
    width = len(strings[0])
    root = None  # a leaf is a list of equal strings' numbers; a node is (depth, children)
    for number, s in enumerate(strings):
        if root is None:
            root = [number]
            continue
        node = root
        while isinstance(node, tuple):
            node = node[1].get(s[node[0]]) or next(iter(node[1].values()))
        other = strings[node[0]]
        if other == s:
            node.append(number)
            continue
        differ = int.from_bytes(other, "big") ^ int.from_bytes(s, "big")
        depth = width - (differ.bit_length() + 7) // 8
        parent, node = None, root
        while isinstance(node, tuple) and node[0] < depth:
            parent, node = node, node[1].get(s[node[0]])
            if node is None:
                break
        if isinstance(node, tuple) and node[0] == depth:
            node[1][s[depth]] = [number]
        elif node is None:
            parent[1][s[parent[0]]] = [number]
        else:
            new = (depth, {other[depth]: node, s[depth]: [number]})
            if parent is None:
                root = new
            else:
                parent[1][s[parent[0]]] = new
    out, stack = [], [root]
    while stack:
        node = stack.pop()
        if isinstance(node, tuple):
            stack.extend(node[1][c] for c in sorted(node[1], reverse=True))
        else:
            out.extend(node)
    return out


def multikey_quicksort(group: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """The order of rows of words within their groups, by three-way partitions of all unfinished parts at once.

    A part is split by the word at its depth into less, equal and more than the median of three of its rows;
    the equal ones go on with the next word.
    """
    order = group.argsort(kind="stable")
    new = np.ones(len(order), bool)
    new[1:] = group[order][1:] != group[order][:-1]
    start = np.flatnonzero(new)
    size, depth = np.diff(np.append(start, len(order))), np.zeros(len(start), np.int64)
    while True:
        some = (size > 1) & (depth < keys.shape[1])
        start, size, depth = start[some], size[some], depth[some]
        if not len(start):
            return order
        off = size.cumsum() - size
        part = np.repeat(np.arange(len(start)), size)
        rows = order[(start - off)[part] + np.arange(len(part))]
        word = keys[rows, depth[part]]
        a, b, c = word[off], word[off + size // 2], word[off + size - 1]
        pivot = np.maximum(np.minimum(a, b), np.minimum(np.maximum(a, b), c))[part]
        less, equal = word < pivot, word == pivot
        before_less, before_equal = less.cumsum() - less, equal.cumsum() - equal
        before_less -= before_less[off][part]
        before_equal -= before_equal[off][part]
        n_less, n_equal = np.add.reduceat(less, off, dtype=np.int64), np.add.reduceat(equal, off, dtype=np.int64)
        inside = np.arange(len(part)) - off[part]
        above = n_less[part] + n_equal[part] + inside - before_less - before_equal
        order[start[part] + np.where(less, before_less, np.where(equal, n_less[part] + before_equal, above))] = rows
        start = np.concatenate([start, start + n_less, start + n_less + n_equal])
        size, depth = np.concatenate([n_less, n_equal, size - n_less - n_equal]), np.concatenate([depth, depth + 1, depth])


def deep_shallow(group: np.ndarray, rows: np.ndarray, shallow: int = SHALLOW) -> tuple[np.ndarray, np.ndarray]:
    """The order of byte rows within their groups, and what each row in order has in common with the one before it (-1 at a new group)."""
    n, width = rows.shape
    words = (shallow + 7) // 8
    wide = np.zeros((n, words * 8), np.uint8)
    wide[:, : min(width, words * 8)] = rows[:, : words * 8]
    keys = wide.view(">u8").astype(np.uint64)
    order = multikey_quicksort(group, keys)
    tied = np.zeros(n, bool)
    if width > words * 8 and n > 1:
        tied[1:] = (group[order][1:] == group[order][:-1]) & (keys[order][1:] == keys[order][:-1]).all(1)
        starts = np.flatnonzero(~tied)
        sizes = np.diff(np.append(starts, n))
        pairs = starts[sizes == 2]
        if len(pairs):  # a trie of two leaves: one comparison
            a, b = rows[order[pairs], words * 8 :], rows[order[pairs + 1], words * 8 :]
            differ = a != b
            at = differ.argmax(1)
            pick = np.arange(len(pairs))
            swap = pairs[a[pick, at] > b[pick, at]]
            order[swap], order[swap + 1] = order[swap + 1], order[swap].copy()
        for s, k in zip(starts[sizes > 2].tolist(), sizes[sizes > 2].tolist(), strict=True):
            own = order[s : s + k].copy()
            packed = rows[own, words * 8 :].tobytes()
            step = width - words * 8
            order[s : s + k] = own[blind_trie_order([packed[i * step : (i + 1) * step] for i in range(k)])]
    common = np.full(n, -1, np.int64)
    if n > 1:
        differ = rows[order[1:]] != rows[order[:-1]]
        common[1:] = np.where(differ.any(1), differ.argmax(1), width)
        common[1:][group[order][1:] != group[order][:-1]] = -1
    return order, common


def judge(hashes, ids, left, right, rows, ref, who, length: int = LENGTH, gram: int = GRAM) -> np.ndarray:
    """For each occurrence (its surroundings' number and its document) a mask of the shifts whose string starts in a smaller document.

    hashes, ids, left, right, rows: distinct surroundings, each with the smallest document that has them.
    """
    before, n = length - gram, len(hashes)
    masks = np.zeros(len(ref), np.uint64)
    _, group = np.unique(hashes, return_inverse=True)
    right_order, right_common = deep_shallow(group, np.ascontiguousarray(rows[:, before:]))
    left_order, left_common = deep_shallow(group, np.ascontiguousarray(rows[:, before - 1 :: -1]))
    of_right, of_left, least = np.empty(n, np.int64), np.empty(n, np.int64), np.empty(n, np.int64)
    for shift in range(before + 1):
        fits = np.flatnonzero((left >= shift) & (right >= length - shift))
        if not len(fits):
            continue
        of_right[right_order] = np.cumsum(right_common < length - shift)
        of_left[left_order] = np.cumsum(left_common < shift)
        key = of_right[fits] * (n + 1) + of_left[fits]
        order = key.argsort(kind="stable")
        key = key[order]
        new = np.concatenate([[True], key[1:] != key[:-1]])
        low = np.minimum.reduceat(ids[fits][order], np.flatnonzero(new))
        least.fill(np.iinfo(np.int64).max)
        least[fits[order]] = low[np.cumsum(new) - 1]
        masks |= (least[ref] < who).astype(np.uint64) << U64(shift)
    return masks


def _verdicts(batches):
    """Places of removed strings: (bucket by document, ids, places, masks) as packed bytes."""
    kinds = ["<u8", "<i8", "<u4", np.uint8, np.uint8, np.uint8, "<u4", "<i8", "<u4"]
    for bucket, (hashes, ids, places, left, right, rows, extra, own, at) in by_bucket(batches, kinds):
        if bucket < 0:  # known where they were read: masks, documents, places
            some = hashes > 0
            if some.any():
                yield pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(places[some].astype(np.int64)), pa.array(hashes[some].view(np.int64))], ["doc_id", "place", "mask"])
            continue
        rows = rows.reshape(len(hashes), -1)
        order = hashes.argsort(kind="stable")
        sorted_, docs = hashes[order], ids[order]
        start = np.concatenate([[True], sorted_[1:] != sorted_[:-1]])
        at_start = np.flatnonzero(start)
        lone = np.minimum.reduceat(docs, at_start) == np.maximum.reduceat(docs, at_start)
        keep = np.zeros(len(hashes), bool)
        keep[order] = ~lone[np.cumsum(start) - 1]
        ref = np.repeat(np.arange(len(hashes)), extra)
        keep[ref[own != ids[ref]]] = True
        some = np.flatnonzero(keep)
        if not len(some):
            continue
        at_some = np.full(len(hashes), -1)
        at_some[some] = np.arange(len(some))
        who, where = np.concatenate([ids, own]), np.concatenate([places, at])
        ref = at_some[np.concatenate([np.arange(len(hashes)), ref])]
        use = ref >= 0
        who, where, ref = who[use], where[use], ref[use]
        masks = judge(hashes[some], ids[some], left[some], right[some], rows[some], ref, who)
        got = np.flatnonzero(masks)
        if len(got):
            yield pa.RecordBatch.from_arrays([pa.array(who[got]), pa.array(where[got].astype(np.int64)), pa.array(masks[got].view(np.int64))], ["doc_id", "place", "mask"])


def covered(n: int, places: np.ndarray, masks: np.ndarray) -> np.ndarray:
    """Which of n bytes the removed strings cover."""
    edge = np.zeros(n + 1, np.int32)
    for shift in range(LENGTH - GRAM + 1):
        at = places[(masks >> U64(shift)) & U64(1) == 1] - shift
        at = at[at < n]
        np.add.at(edge, at, 1)
        np.add.at(edge, np.minimum(at + LENGTH, n), -1)
    return np.cumsum(edge[:n]) > 0


def places_of(docs: DataFrame, text: str = "text") -> DataFrame:
    """(doc_id, place, mask): anchors with removed strings; bit s of the mask: the string that starts s bytes before the anchor."""
    spark = docs.sparkSession
    bits = bucket_bits(docs.count(), each=400)
    keys = written(repeated(docs, bits, text), "repeated")
    log2 = Bits.size_for(keys.count(), FILTER_LOG2)
    field = spark.sparkContext.broadcast(bits_of(keys, "key", log2).data)
    forget(keys)
    return gathered(surroundings(docs, field, log2, bits, text)).mapInArrow(_verdicts, "doc_id long, place long, mask long")


def remove_repeats(docs: DataFrame, text: str = "text", digest: bool = False) -> DataFrame:
    """All columns of docs, with the remaining text, and n_bytes, n_removed, n_spans, kept_sha256; with `digest` only doc_id and those."""
    spark = docs.sparkSession
    docs = docs.drop("n_bytes", "n_removed", "n_spans", "kept_sha256")
    found = written(places_of(docs, text), "places")
    touched = written(found.select("doc_id").distinct(), "touched")
    log2 = Bits.size_for(touched.count(), 25)
    field = spark.sparkContext.broadcast(bits_of(touched, "doc_id", log2).data)
    forget(touched)
    names = ["doc_id"] if digest else docs.columns
    kind = docs.select(*names).schema
    extra = "n_bytes long, n_removed long, n_spans long, kept_sha256 string"
    fields = ", ".join(f"`{f.name.replace('`', '``')}` {f.dataType.simpleString()}" for f in kind.fields) + ", " + extra
    at_text, at_id = docs.columns.index(text), docs.columns.index("doc_id")

    def finish(batch, places):
        """places: for each row (places, masks) or None."""
        texts, told, kept = batch.column(at_text), [], []
        data, offsets = text_buffer(texts)
        for r, p in enumerate(places):
            own = data[offsets[r] : offsets[r + 1]]
            if p is None:
                told.append((len(own), 0, 0, hashlib.sha256(own).hexdigest()))
                kept.append(texts[r].as_py())
                continue
            gone = covered(len(own), *p)
            rest = own[~gone].tobytes()
            spans = int((gone[1:] & ~gone[:-1]).sum() + (gone[:1].sum() if len(gone) else 0))
            told.append((len(own), int(gone.sum()), spans, hashlib.sha256(rest).hexdigest()))
            kept.append(rest.decode(errors="ignore"))
        columns = [batch.column(at_id)] if digest else [pa.array(kept, pa.string()) if i == at_text else batch.column(i) for i in range(len(names))]
        columns += [pa.array(c, t) for c, t in zip(zip(*told, strict=True) if told else [()] * 4, (pa.int64(), pa.int64(), pa.int64(), pa.string()), strict=True)]
        return pa.RecordBatch.from_arrays(columns, [*names, "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    def split(want: bool):
        def run(batches):
            known = Bits(log2, field.value)
            for batch in batches:
                column = batch.column(at_id)
                hit = known.has(as_keys(column.cast(pa.int64()))) & column.is_valid().to_numpy(zero_copy_only=False)
                part = batch.filter(pa.array(hit == want))
                yield part if want else finish(part, [None] * len(part))

        return run

    clean = docs.mapInArrow(split(False), fields)
    cells = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    seat = F.pmod(F.xxhash64(F.col("doc_id").cast("long")), F.lit(1 << 20)).alias("seat")
    marks = found.select(seat, F.lit(0).alias("kind"), F.col("doc_id").alias("mark_id"), "place", "mask", F.lit(None).cast(docs.select(F.struct(*docs.columns)).schema[0].dataType).alias("row"))
    rows = docs.mapInArrow(split(True), docs.schema).select(seat, F.lit(1).alias("kind"), F.col("doc_id").cast("long").alias("mark_id"), F.lit(None).cast("long").alias("place"), F.lit(None).cast("long").alias("mask"), F.struct(*docs.columns).alias("row"))

    def meet(batches):
        seat, held = None, {}
        for batch in batches:
            seats, kinds, ids, places, masks = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(5))
            got, own = [], []
            for r, (s, k) in enumerate(zip(seats.tolist(), kinds.tolist(), strict=True)):
                if s != seat:
                    seat, held = s, {}
                if k == 0:
                    held.setdefault(int(ids[r]), []).append((int(places[r]), int(masks[r])))
                else:
                    p = held.get(int(ids[r]))
                    got.append(r)
                    own.append(None if p is None else (np.array([x for x, _ in p], np.int64), np.array([x for _, x in p], np.int64).view(np.uint64)))
            if got:
                struct = batch.column(5).take(pa.array(got))
                yield finish(pa.RecordBatch.from_arrays([struct.field(i) for i in range(struct.type.num_fields)], docs_names), own)

    docs_names = docs.columns
    dirty = marks.unionByName(rows).repartition(cells, "seat").sortWithinPartitions("seat", "kind").mapInArrow(meet, fields)
    return clean.unionByName(dirty)
