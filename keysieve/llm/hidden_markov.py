"""A hidden Markov language model over words, trained by Baum-Welch counts that partitions add up.

Tokens are lower-cased words, and one end after each text. Words counted `OWN_COUNT` times, and the `OWN` most
frequent ones in any case (the end among them), are emission classes of their own, so that their number follows
the counted vocabulary up to `OWN_MOST`, the size that the broadcast model is bounded to (beyond it, the least
count rises by fourths of a doubling); all others fall by their hash into a fixed number of classes. A latent
state emits a class, and a class emits its words by smoothed corpus counts, which cover all training texts. The score is the exact log10 likelihood of a text by the scaled forward recursion plus the
words' log10 shares of their classes; every class keeps the mass of one unseen word, as the base score does.

The corpus is tokenized once into chunks: distinct word hashes, their training counts, and the words as
numbers. Distinct words of chunks meet by ranges of their hash, where counts are added up and go back to each
chunk in the order of its words. Training starts from a seeded random table; each round goes over all training
texts in as many tasks as run at once, twice over, and sends, for each task, the expected counts of the classes it
met, which meet by ranges of classes; a round's shuffle files go with it.
Rounds go on until the corpus likelihood settles. For training, texts are cut into stretches of `STRETCH` tokens; likelihoods are of whole texts.

Defined results: null and empty texts have one token, the end. A row without doc_id is not held out. Without training texts every token is unknown
and the score is the base score. Rows of equal doc_id are scored like any others.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import U64, bucket_bits, gathered, mix, released, slices, text_buffer, word_hashes, written

STATES, OWN, OWN_COUNT, SHARED, OWN_MOST = 8, 4096, 64, 1024, 1 << 20
#: Words of a chunk, tokens of a stretch, and the gain of log likelihood, as a part of it, under which training ends.
CHUNK, STRETCH, SETTLED = 1 << 19, 512, 1e-4
END = U64(0xE11D0FE11D0FE11D)


class Model:
    """Classes of words and the tables of states."""

    def __init__(self, own: np.ndarray, own_counts: np.ndarray, share_tokens: np.ndarray, share_types: np.ndarray, tokens: int, types: int):
        order = own.argsort()
        self.own, self.tokens, self.types = own[order], tokens, types
        self.n = len(own) + SHARED
        shared = class_of(own)
        self.share = np.log10(np.maximum(share_tokens - np.bincount(shared, own_counts, SHARED), 0) + np.maximum(share_types - np.bincount(shared, minlength=SHARED), 0) + 1)
        self.start = self.move = self.emit = None

    def classes(self, keys: np.ndarray) -> np.ndarray:
        out = class_of(keys) + len(self.own)
        if len(self.own):
            at = np.searchsorted(self.own, keys)
            at[at == len(self.own)] = 0
            hit = self.own[at] == keys
            out[hit] = at[hit]
        return out

    def word_share(self, classes: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """log10 of a word's share of its class."""
        out = np.zeros(len(classes))
        rest = classes >= len(self.own)
        out[rest] = np.log10(counts[rest] + 1.0) - self.share[classes[rest] - len(self.own)]
        return out

    def set(self, start: np.ndarray, later: np.ndarray, move: np.ndarray, emit: np.ndarray) -> None:
        self.start, self.later = (x / x.sum() for x in (start + 1e-3, later + 1e-3))
        self.move = (move + 1e-2) / (move + 1e-2).sum(1, keepdims=True)
        self.emit = np.ascontiguousarray(((emit + 1e-2) / (emit + 1e-2).sum(1, keepdims=True)).T)  # classes x states


def _level(sums: np.ndarray) -> np.ndarray:
    return np.floor(4 * np.log2(np.maximum(sums, 1))).astype(np.int64)


def class_of(keys: np.ndarray) -> np.ndarray:
    return (mix(keys ^ U64(0x5DEECE66D)) >> U64(54)).astype(np.int64)


def _by_step(lengths: np.ndarray):
    """For sequences in descending order of length: rows at each step, and where a step begins in step order."""
    steps = int(lengths[0]) if len(lengths) else 0
    rows = np.searchsorted(-lengths, -np.arange(steps), "left")  # sequences longer than the step
    return rows, np.concatenate([[0], rows.cumsum()])


def _stretches(starts: np.ndarray, counts: np.ndarray):
    """(begin, length, first) of all stretches of sequences."""
    parts = np.maximum(1, -(-counts // STRETCH))
    which = np.repeat(np.arange(len(counts)), parts)
    nth = np.arange(len(which)) - np.repeat(parts.cumsum() - parts, parts)
    begin = starts[which] + nth * STRETCH
    return begin, np.minimum(STRETCH, counts[which] - nth * STRETCH), nth == 0, which


def _stepped(classes: np.ndarray, begin: np.ndarray, length: np.ndarray):
    order = (-length).argsort(kind="stable")
    begin, length = begin[order], length[order]
    rows, at = _by_step(length)
    step = np.repeat(np.arange(len(rows)), rows)
    row = np.arange(at[-1]) - np.repeat(at[:-1], rows)
    return order, rows, at, classes[begin[row] + step]


_held: list[np.ndarray] = []


def _room(k: int, n: int) -> np.ndarray:
    """A table of k rows and n columns; a worker keeps the memory for the next one, of at most twice a chunk's tokens."""
    if not _held or _held[0].size < k * n:
        _held[:] = [np.empty(k * n)]
    out = _held[0][: k * n].reshape(k, n)
    if n > 2 * CHUNK:
        _held.clear()
    return out


def expected(model: Model, classes: np.ndarray, starts: np.ndarray, counts: np.ndarray):
    """Expected starts, later starts, moves and emissions of sequences of classes, and their log10 likelihood (forward-backward)."""
    begin, length, first, _ = _stretches(starts, counts)
    order, rows, at, cls = _stepped(classes, begin, length)
    k = len(model.start)
    out = np.zeros(k), np.zeros(k), np.zeros((k, k)), np.zeros((k, model.n)), np.zeros(1)
    if not len(cls):
        return out
    # states are rows, so that sums over states and products with the move table run along whole steps
    forward, scale = _room(k, len(cls)), np.empty(len(cls))
    prior = np.where(first[order], model.start[:, None], model.later[:, None])
    onward = np.ascontiguousarray(model.move.T)
    for t in range(len(rows)):
        a, b = at[t], at[t + 1]
        now = prior if t == 0 else onward @ forward[:, at[t - 1] : at[t - 1] + rows[t]]
        now = now * model.emit.take(cls[a:b], 0).T
        scale[a:b] = now.sum(0)
        np.divide(now, scale[a:b], out=forward[:, a:b])
    out[4][0] = np.log10(scale).sum()
    for t in range(len(rows) - 2, -1, -1):  # forward becomes the states' shares of each token
        a, c, d = at[t], at[t + 1], at[t + 2]
        if t == len(rows) - 2:
            back = np.ones((k, d - c))
        elif back.shape[1] < d - c:
            back = np.concatenate([back, np.ones((k, d - c - back.shape[1]))], 1)
        back /= scale[c:d]
        weighted = back * model.emit.take(cls[c:d], 0).T
        out[2][:] += forward[:, a : a + d - c] @ weighted.T
        back = model.move @ weighted
        forward[:, a : a + d - c] *= back
    out[2][:] *= model.move
    head = first[order]
    out[0][:], out[1][:] = forward[:, : rows[0]][:, head].sum(1), forward.sum(1)
    for s in range(k):
        out[3][s] = np.bincount(cls, forward[s], model.n)
    return out


def likelihood(model: Model, classes: np.ndarray, starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """log10 likelihood of whole sequences of classes.

    A sequence longer than a stretch is the product of its stretches' matrices, whose rows are recursions from
    each single state, so that all stretches advance together.
    """
    k = len(model.start)
    begin, length, first, which = _stretches(starts, counts)
    long = ~first
    begin2 = np.concatenate([begin[first], np.repeat(begin[long], k)])
    length2 = np.concatenate([length[first], np.repeat(length[long], k)])
    prior = np.concatenate([np.broadcast_to(model.start, (int(first.sum()), k)), np.tile(model.move, (int(long.sum()), 1))])
    order, rows, at, cls = _stepped(classes, begin2, length2)
    state, logs = np.empty((k, len(order))), np.zeros(len(order))
    now, onward = prior[order].T, np.ascontiguousarray(model.move.T)
    for t in range(len(rows)):
        n = rows[t]
        now = (now[:, :n] if t == 0 else onward @ now[:, :n]) * model.emit.take(cls[at[t] : at[t + 1]], 0).T
        scale = now.sum(0)
        logs[:n] += np.log10(scale)
        now /= scale
        state[:, :n] = now
    state = state.T
    final, total = np.empty_like(state), np.empty_like(logs)
    final[order], total[order] = state, logs
    m = int(first.sum())
    out = total[:m].copy()
    vector, matrix, weight = final[:m].copy(), final[m:].reshape(-1, k, k), total[m:].reshape(-1, k)
    for i, owner in enumerate(which[long]):
        top = weight[i].max()
        joined = (vector[owner] * 10.0 ** (weight[i] - top)) @ matrix[i]
        size = joined.sum()
        out[owner] += top + np.log10(size)
        vector[owner] = joined / size
    return out


def _begin(model: Model, k: int, seed: int = 5) -> None:
    rng = np.random.default_rng(seed)
    model.set(np.ones(k), np.ones(k), np.eye(k) * 50 * k + 1, rng.gamma(2.0, 1.0, (k, model.n)))


def _sequences(keys: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    counts = np.array([len(x) for x in keys], np.int64)
    return np.concatenate(keys), counts.cumsum() - counts, counts


def chunks(docs: DataFrame, held_out) -> DataFrame:
    """The tokenized corpus: a row for each chunk of documents."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(held_out, F.lit(False)).alias("held"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))

    def run(batches):
        ids, held, parts, counts, size = [], [], [], [], 0

        def flush():
            words = np.concatenate(parts)
            keys, numbers = np.unique(words, return_inverse=True)
            n = np.array(counts, "<u4")
            train = np.bincount(numbers, np.repeat(~np.array(held, bool), n), len(keys)).astype("<u4")
            null = np.array([i is None for i in ids], np.uint8)
            cells = [np.array([i or 0 for i in ids], "<i8"), np.array(held, np.uint8), n, numbers.astype("<u4"), keys, train, null]
            return pa.RecordBatch.from_arrays([pa.array([uuid.uuid4().int >> 65], pa.int64()), *(pa.array([c.tobytes()], pa.binary()) for c in cells)], ["chunk", "ids", "held", "counts", "words", "keys", "train", "null"])

        for batch in batches:
            data, offsets = text_buffer(batch.column(2))
            for i, j in slices(offsets):
                hashes, cut = word_hashes(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
                n = np.diff(cut)
                parts.append(np.insert(hashes, cut[1:], END))
                ids.extend(batch.column(0).slice(i, j - i).to_pylist())
                held.extend(batch.column(1).slice(i, j - i).to_pylist())
                counts.extend((n + 1).tolist())
                size += len(parts[-1])
                if size > CHUNK:
                    yield flush()
                    ids, held, parts, counts, size = [], [], [], [], 0
        if ids:
            yield flush()

    return written(rows.mapInArrow(run, "chunk long, ids binary, held binary, counts binary, words binary, keys binary, train binary, null binary"), "chunks")


def _arrays(batch: pa.RecordBatch, r: int, names: list[str]) -> list[np.ndarray]:
    kinds = {"ids": "<i8", "held": np.uint8, "counts": "<u4", "words": "<u4", "keys": "<u8", "train": "<u4", "null": np.uint8}
    return [np.frombuffer(batch.column(batch.schema.get_field_index(n))[r].as_buffer(), kinds[n]) for n in names]


def word_counts(table: DataFrame, bits: int) -> DataFrame:
    """kind 0: for each chunk and range of words their corpus counts; 1: frequent words; 2: tokens and types of each shared class."""

    def send(batches):
        for batch in batches:
            for r in range(len(batch)):
                keys, train = _arrays(batch, r, ["keys", "train"])
                chunk = batch.column(0)[r].as_py()
                bucket = (keys >> U64(64 - bits)).astype(np.int64)
                ends = [*(np.flatnonzero(np.diff(bucket)) + 1).tolist(), len(keys)]
                rows = [(int(bucket[a]), chunk, keys[a:b].tobytes(), train[a:b].tobytes()) for a, b in zip([0, *ends[:-1]], ends, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int64(), pa.binary(), pa.binary()), strict=True)], ["bucket", "chunk", "c0", "c1"])

    def total(batches):
        bucket, held = None, []

        def emit():
            keys, train = np.concatenate([h[1] for h in held]), np.concatenate([h[2] for h in held])
            own, at = np.unique(keys, return_inverse=True)
            sums = np.bincount(at, train, len(own)).astype(np.int64)
            back = sums.astype("<u8")[at]
            rows, i = [], 0
            for chunk, k, _ in held:
                rows.append((0, chunk, bucket, back[i : i + len(k)].tobytes(), b""))
                i += len(k)
            top = np.argsort(-sums, kind="stable")
            top = top[(sums[top] >= OWN_COUNT) | (np.arange(len(top)) < OWN) & (sums[top] > 1)]
            rows.append((1, 0, bucket, sums[top].tobytes(), own[top].tobytes()))
            some = sums > 0
            share = class_of(own[some])
            rows.append((2, 0, bucket, np.bincount(share, sums[some], SHARED).astype(np.int64).tobytes(), np.bincount(share, minlength=SHARED).astype(np.int64).tobytes()))
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.binary()), strict=True)], ["kind", "chunk", "bucket", "c", "k"])

        for batch in batches:
            for b, chunk, k, t in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                if b != bucket and held:
                    yield emit()
                    held = []
                bucket = b
                held.append((chunk, np.frombuffer(k, "<u8"), np.frombuffer(t, "<u4")))
        if held:
            yield emit()

    sent = table.select("chunk", "keys", "train").mapInArrow(send, "bucket int, chunk long, c0 binary, c1 binary")
    return written(gathered(sent).mapInArrow(total, "kind int, chunk long, bucket int, c binary, k binary"), "counts")


def _summed(df: DataFrame, columns: list[str], kind: type) -> list[np.ndarray]:
    """Element-wise sums of packed arrays: tasks add up their own, a few tasks add those, the driver the rest."""

    def add(batches):
        total = None
        for batch in batches:
            for r in range(len(batch)):
                one = [np.frombuffer(batch.column(c)[r].as_buffer(), kind) for c in range(len(columns))]
                total = [x.copy() for x in one] if total is None else [t + x for t, x in zip(total, one, strict=True)]
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([t.tobytes()], pa.binary()) for t in total], columns)

    schema = ", ".join(f"{c} binary" for c in columns)
    rows = df.select(*columns).mapInArrow(add, schema).repartition(8).mapInArrow(add, schema).collect()
    return [np.sum([np.frombuffer(r[i], kind) for r in rows], axis=0) for i in range(len(columns))] if rows else []


def word_classes(counts: DataFrame) -> Model:
    """A model without tables, with the classes that the corpus counts give."""

    def words(batches):
        for batch in batches:
            for sums, own in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(own, np.int64)), pa.array(np.frombuffer(sums, np.int64))], ["key", "c"])

    def frequent(batches):
        for batch in batches:
            for sums, own in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                sums, own = np.frombuffer(sums, np.int64), np.frombuffer(own, np.int64)
                some = (sums >= OWN_COUNT) & (_level(sums) >= least)
                yield pa.RecordBatch.from_arrays([pa.array([own[some].tobytes()], pa.binary()), pa.array([sums[some].tobytes()], pa.binary())], ["k", "c"])

    def levels(batches):
        seen = np.zeros(256, np.int64)
        for batch in batches:
            for sums in batch.column(0).to_pylist():
                sums = np.frombuffer(sums, np.int64)
                seen += np.bincount(_level(sums[sums >= OWN_COUNT]), minlength=256)
        yield pa.RecordBatch.from_arrays([pa.array([seen.tobytes()], pa.binary())], ["n"])

    lists = counts.filter("kind = 1").select("c", "k")
    seen = _summed(lists.mapInArrow(levels, "n binary"), ["n"], np.int64) or [np.zeros(256, np.int64)]
    above = seen[0][::-1].cumsum()[::-1]  # words of a level or more
    least = int((above > OWN_MOST).sum())
    top = lists.mapInArrow(words, "key long, c long").orderBy(F.desc("c"), "key").limit(OWN).collect()
    packed = lists.mapInArrow(frequent, "k binary, c binary").collect()
    keys = np.concatenate([np.array([r["key"] for r in top], np.int64), *(np.frombuffer(r["k"], np.int64) for r in packed)])
    sums = np.concatenate([np.array([r["c"] for r in top], np.int64), *(np.frombuffer(r["c"], np.int64) for r in packed)])
    own, at = np.unique(keys.view(np.uint64), return_index=True)
    share_tokens, share_types = _summed(counts.filter("kind = 2"), ["c", "k"], np.int64) or [np.zeros(SHARED, np.int64)] * 2
    return Model(own, sums[at], share_tokens, share_types, int(share_tokens.sum()), int(share_types.sum()))


def corpus_expected(model: Model, table: DataFrame) -> list[np.ndarray]:
    """What `expected` gives for all training texts of the chunks."""
    spark, k = table.sparkSession, len(model.start)
    parts = max(8, model.n >> 16)
    cuts = np.linspace(0, model.n, parts + 1).astype(np.int64)
    shared = spark.sparkContext.broadcast(model)

    def count(batches):
        model, total = shared.value, None
        for batch in batches:
            for r in range(len(batch)):
                n, held, numbers, keys = _arrays(batch, r, ["counts", "held", "words", "keys"])
                n = n.astype(np.int64)
                starts, use = n.cumsum() - n, held == 0
                one = expected(model, model.classes(keys)[numbers], starts[use], n[use])
                total = list(one) if total is None else [t + x for t, x in zip(total, one, strict=True)]
        if total is not None:
            small = np.concatenate([t.ravel() for t in (total[0], total[1], total[2], total[4])]).tobytes()
            met = np.flatnonzero(total[3].any(0))
            for p in range(parts):
                some = met[(met >= cuts[p]) & (met < cuts[p + 1])]
                cells = [small if p == 0 else b"", some.astype("<u4").tobytes(), np.ascontiguousarray(total[3][:, some], "<f4").tobytes()]
                yield pa.RecordBatch.from_arrays([pa.array([p], pa.int32()), *(pa.array([c], pa.binary()) for c in cells)], ["part", "small", "classes", "e"])

    def add(batches):
        small, tables = np.zeros(2 * k + k * k + 1), {}
        for batch in batches:
            for p, few, classes, e in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                if few:
                    small += np.frombuffer(few, np.float64)
                if p not in tables:
                    tables[p] = np.zeros((k, cuts[p + 1] - cuts[p]))
                tables[p][:, np.frombuffer(classes, "<u4").astype(np.int64) - cuts[p]] += np.frombuffer(e, "<f4").reshape(k, -1)
        for p, x in tables.items():
            yield pa.RecordBatch.from_arrays([pa.array([p], pa.int32()), pa.array([small.tobytes() if p == 0 else b""], pa.binary()), pa.array([x.tobytes()], pa.binary())], ["part", "small", "e"])

    small, emit = np.zeros(2 * k + k * k + 1), np.zeros((k, model.n))
    with released(spark):  # a round's tables are on disk until its sums are here
        # as many tasks as run at once, twice over, so that what they send follows the machines and not the texts
        few = table.select("counts", "held", "words", "keys").coalesce(2 * spark.sparkContext.defaultParallelism)
        sent = few.mapInArrow(count, "part int, small binary, classes binary, e binary")
        rows = sent.repartition(8, "part").mapInArrow(add, "part int, small binary, e binary").collect()
    for r in rows:
        emit[:, cuts[r["part"]] : cuts[r["part"] + 1]] = np.frombuffer(r["e"], np.float64).reshape(k, -1)
        if r["part"] == 0:
            small = np.frombuffer(r["small"], np.float64)
    shared.unpersist()
    return [small[:k], small[k : 2 * k], small[2 * k : -1].reshape(k, k), emit, small[-1:]]


def train(table: DataFrame, counts: DataFrame, states: int = STATES) -> Model:
    """Classes from corpus counts, then Baum-Welch rounds over all training texts until their likelihood settles."""
    model = word_classes(counts)
    _begin(model, states)
    model.history = []
    while model.tokens:
        *sums, logs = corpus_expected(model, table)
        model.set(*sums)
        model.history.append(float(logs[0]))
        if len(model.history) > 1 and model.history[-1] - model.history[-2] < SETTLED * abs(model.history[-2]):
            break
    return model


def score(docs: DataFrame, held_out) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) of every row; learned from rows that are not held out."""
    spark = docs.sparkSession
    docs = docs.select("doc_id", "text")
    table = chunks(docs, held_out)
    counts = word_counts(table, bucket_bits(docs.count()))
    model = train(table, counts)
    shared = spark.sparkContext.broadcast(model)
    names = ["ids", "held", "counts", "words", "keys", "null"]
    back = counts.filter("kind = 0").select("chunk", "bucket", "c", *(F.lit(None).cast("binary").alias(n) for n in names))
    own = table.select("chunk", F.lit(1 << 30).alias("bucket"), F.lit(None).cast("binary").alias("c"), *names)

    def run(batches):
        model, held_counts, chunk = shared.value, [], None
        for batch in batches:
            heads = batch.column(0).to_pylist()
            buckets = batch.column(1).to_pylist()
            for r, (c, b) in enumerate(zip(heads, buckets, strict=True)):
                if c != chunk:
                    chunk, held_counts = c, []
                if b < 1 << 30:
                    held_counts.append(np.frombuffer(batch.column(2)[r].as_py(), "<u8"))
                    continue
                ids, held, n, numbers, keys, null = _arrays(batch, r, names)
                count = np.concatenate(held_counts).astype(np.float64)
                n = n.astype(np.int64)
                starts = n.cumsum() - n
                classes = model.classes(keys)
                known = np.add.reduceat((count > 0)[numbers].astype(np.int64), starts)
                base = np.add.reduceat(np.log10((count + 1) / (model.tokens + model.types + 1))[numbers], starts)
                if model.tokens:
                    value = np.add.reduceat(model.word_share(classes, count)[numbers], starts) + likelihood(model, classes[numbers], starts, n)
                else:
                    value = base
                columns = [pa.array(ids, pa.int64(), mask=null.astype(bool)), pa.array(held.astype(bool)), pa.array(n), pa.array(known), pa.array(np.full(len(n), model.tokens)), pa.array(base), pa.array(value)]
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    met = back.unionByName(own).repartition(n, "chunk").sortWithinPartitions("chunk", "bucket")
    return met.mapInArrow(run, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")
