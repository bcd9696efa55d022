"""The ten operators on small fixtures against brute force, the libraries, exact round trips and held-out accuracy."""

import time
import hashlib
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from keysieve.llm import fingerprints, hidden_markov, jaccard_join, language_id, mixing, multi_index, piece_dropout, suffix_dedup, token_counts, token_records
from keysieve.llm.common import Bits, components, shingles, text_buffer
from keysieve.llm.queries import vocabulary

WORD = re.compile(r"[^\x20\x09-\x0D]+")
RNG = random.Random(11)
VOCAB = ["".join(RNG.choice("abcdefghilmnorstu") for _ in range(RNG.randrange(2, 8))) for _ in range(300)]


def prose(n):
    return " ".join(RNG.choice(VOCAB) for _ in range(n))


def near(text, edits):
    words = text.split()
    for _ in range(edits):
        words[RNG.randrange(len(words))] = RNG.choice(VOCAB)
    return " ".join(words)


PASSAGE, LONG = prose(40), prose(200)
TEXTS = [
    None, "", " \n\t ", "a", "A b", "a B", LONG, LONG, near(LONG, 2), near(LONG, 2), near(LONG, 60), prose(30) + " " + PASSAGE, PASSAGE + " " + prose(50), prose(8) + PASSAGE + prose(3),
    "🙂 é x " * 40, "x" * 5000, prose(3000), "12 34 !? --", "日本語の文章です", PASSAGE, "a" * 49, "a" * 50, "a" * 120, prose(100), near(LONG, 8), near(LONG, 9), "<|endoftext|> tail", "a▁b",
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, ["en", "fr", None][i % 3], f"s{i % 4}" if i % 5 else None, len(t or ""), "clash") for i, t in enumerate(TEXTS)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, score string")


@pytest.fixture(scope="module")
def none(docs):
    return docs.filter("false")


def by_id(df):
    return {r["doc_id"]: r for r in df.collect()}


def test_language_id(spark, docs, none):
    words = {"en": "the of and to with house river".split(), "fr": "le la de avec maison rivière où".split()}
    rows = [(i, " ".join(RNG.choice(words[k]) for _ in range(12)), k) for i in range(200) for k in words]
    model = language_id.fit([(t, k) for i, t, k in rows if i % 5])
    held = spark.createDataFrame([r for r in rows if r[0] % 5 == 0], "doc_id long, text string, lang string")
    got = language_id.predict(held, model)
    assert got.filter("lang = lang_pred").count() >= 0.98 * held.count()
    out = by_id(language_id.predict(docs, model))
    assert len(out) == len(TEXTS) and all(out[i].lang_pred == "und" and out[i].score == 0 for i in (0, 1, 2, 17))
    assert out[18].lang_pred in words and all(0 <= r.score <= 1 for r in out.values())
    assert language_id.predict(none, model).count() == 0
    assert {r.lang_pred for r in language_id.predict(docs, language_id.fit([])).collect()} == {"und"}
    assert language_id.sample(none, "text", "lang", "doc_id") == []


def test_language_model_equals_a_plain_kernel_ridge():
    words = {"en": "the of and to with house river".split(), "fr": "le la de avec maison fleuve".split(), "de": "der die und mit haus fluss".split()}
    rows = [(" ".join(RNG.choice(words[k]) for _ in range(9)), k) for _ in range(40) for k in words]
    model = language_id.fit(rows, longest=3, landmarks=30)
    grams = [{t.encode()[i : i + n] for n in (1, 2, 3) for i in range(len(t.encode()) - n + 1)} for t, _ in rows]
    held = {}
    for g in grams[:30]:
        for x in g:
            held[x] = held.get(x, 0) + 1
    sets = [{x for x in g if held.get(x, 0) > 1} for g in grams]
    kernel = np.array([[len(a & b) / (len(a) * len(b)) ** 0.5 for b in sets[:30]] for a in sets])
    values, vectors = np.linalg.eigh(kernel[:30])
    strong = values > values.max() * 1e-6
    features = kernel @ (vectors[:, strong] / np.sqrt(values[strong]))
    wide = np.column_stack([features, np.ones(len(rows))])
    target = np.array([[1.0 if k == lang else -1.0 for lang in sorted(words)] for _, k in rows])
    penalty = 1e-4 * len(rows) * np.eye(wide.shape[1])
    penalty[-1, -1] = 0  # the bias is free
    want = wide @ np.linalg.solve(wide.T @ wide + penalty, wide.T @ target)
    data, offsets = text_buffer(pa.array([t for t, _ in rows]))
    got = model.decide(model.presence(data, offsets))
    assert np.abs(got - want).max() < 0.02 and (got.argmax(1) == want.argmax(1)).all()


def test_sample_keeps_all_languages_and_its_bytes(spark):
    rows = [(i, f"text of {i} " * (1 + i % 5), f"l{i % 300}") for i in range(1500)] + [(None, "no id", "l0"), (9999, "x " * 5000, "l1")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    assert len({k for _, k in language_id.sample(df, "text", "lang", "doc_id")}) == 300
    some = language_id.sample(df, "text", "lang", "doc_id", most_bytes=20_000)
    assert 0 < sum(len(t) for t, _ in some) <= 20_000 and all(len(t) < 2000 for t, _ in some)


def test_rows_without_or_with_equal_ids(spark):
    """Null and equal doc_ids, and columns named like results, through every operator that keeps a row for each."""
    rows = [(1, "one two three four five six seven " * 4, "en", "a"), (1, "one two three four five six seven " * 4, "en", "a"), (None, "other words here", "fr", None), (None, "other words here", "fr", None), (2, None, None, "a")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    for c in ("n_tokens", "lang_pred", "fingerprint", "n_bytes", "component_id", "size", "place"):
        df = df.withColumn(c, F.lit("clash"))
    path = vocabulary("byte_bpe_50k.json")
    found = {
        "language": language_id.predict(df, language_id.fit([("one two", "en"), ("other words", "fr")] * 5)),
        "prints": fingerprints.compare_with_successor(df),
        "records": token_records.tokenize_to_files(df, vocabulary("word_bpe_49k.json")),
        "counts": token_counts.count_tokens(df, path),
        "join": jaccard_join.classes(df),
        "markov": hidden_markov.score(df, F.col("doc_id") % 7 == 2),
        "repeats": suffix_dedup.remove_repeats(df),
        "mix": mixing.mix(df),
        "pieces": piece_dropout.encode(df, vocabulary("piece_bpe_32k.model")),
    }
    for name, out in found.items():
        ids = [r.doc_id for r in out.collect()]
        assert sorted(ids, key=str) == [1, 1, 2, None, None], name
    nulls = [r for r in found["prints"].collect() if r.doc_id is None]
    assert {r.fingerprint for r in nulls} == {nulls[0].fingerprint}
    assert [r.held_out for r in found["markov"].collect() if r.doc_id is None] == [False, False]


def test_fingerprints(docs, none):
    out = by_id(fingerprints.compare_with_successor(docs))
    texts = [t or "" for t in TEXTS]
    for i, t in enumerate(texts):
        follow = texts[(i + 1) % len(texts)]
        edited = t[: len(t) - len(t) // 2] + follow[: len(t) // 2]
        assert (out[i].n_chars, out[i].edited_sha256) == (len(t), hashlib.sha256(edited.encode()).hexdigest())
        assert 0 <= out[i].near_edited <= 1 and 0 <= out[i].near_next <= 1
    assert out[6].fingerprint == out[7].fingerprint and out[6].near_next == 1 and out[4].fingerprint == out[5].fingerprint
    assert fingerprints.compare_with_successor(none).count() == 0
    a, b = (fingerprints.sketch(s) for s in shingles(*text_buffer(pa.array([LONG, PASSAGE])), 5))
    both = fingerprints.sketch(np.union1d(*shingles(*text_buffer(pa.array([LONG, PASSAGE])), 5)))
    assert set(fingerprints.merge(a, b)) <= set(a) | set(b) and set(both) <= set(fingerprints.merge(a, b))
    assert (fingerprints.from_text(fingerprints.to_text(a)) == a).all()


def test_token_counts(docs, none):
    from tokenizers import Tokenizer

    path = vocabulary("byte_bpe_50k.json")
    library = Tokenizer.from_file(path)
    out = by_id(token_counts.count_tokens(docs, path))
    for i, t in enumerate(TEXTS):
        n = len(library.encode(t or "", add_special_tokens=False).ids)
        assert (out[i].n_tokens, out[i].n_bytes, out[i].over_limit) == (n, len((t or "").encode()), n > 512)
    assert token_counts.count_tokens(none, path).count() == 0


def rows_files(spark, name):
    from pathlib import Path

    return [str(p) for p in Path(spark.conf.get("spark.checkpoint.dir")).rglob(name)]


def test_encoder_asks_its_memo_for_single_pieces():
    """A batch costs what its own pieces cost, whatever a worker remembers."""

    class Memo(dict):
        def keys(self):
            raise AssertionError("the whole memo is walked through")

        __iter__ = items = values = keys

    e = token_records.Encoder(vocabulary("word_bpe_49k.json"))
    e.memo = Memo()
    for texts in (["a small text", ""], ["another small text's 12"]):
        assert e.encode(texts) == [e.raw(e.library.encode(t, add_special_tokens=False).ids) for t in texts]


def test_token_records(spark, docs, none):
    from tokenizers import Tokenizer

    path = vocabulary("word_bpe_49k.json")
    library, start = Tokenizer.from_file(path), 0
    rows = token_records.tokenize_to_files(docs, path)
    out = by_id(rows)
    for i, t in enumerate(TEXTS):
        ids = np.array([*library.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
        assert (out[i].start, out[i].n_tokens, out[i].ids_crc32) == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)
    assert token_records.tokenize_to_files(none, path).count() == 0
    where = next(f.rsplit("/", 1)[0] for f in rows_files(spark, out[6].file))
    got = token_records.fetch(spark, where, [out[6], out[16]])
    assert [zlib.crc32(g.astype("<u4").tobytes()) for g in got] == [out[6].ids_crc32, out[16].ids_crc32]
    names = [(f"part-{p:05d}-x-c{c:03d}.txt", p * 10000 + c) for p in (0, 2, 100000) for c in (0, 99, 100, 999, 1000, 1001)]
    begins = dict(token_records.in_order(spark.createDataFrame(names, "file string, ids long")).collect())
    total = 0
    for name, n in names:
        assert begins[name] == total
        total += n
    record = token_records.frame(token_records.pack(7, np.array([1, 10, 2], "<u2").tobytes(), 2))
    payload, after = token_records.unframe(record, 0)
    assert token_records.unpack(payload)[0] == 7 and token_records.unpack(payload)[1].tolist() == [1, 10, 2] and after == len(record)
    for at in (0, 9, 14, len(record) - 2):
        with pytest.raises(ValueError):
            token_records.unframe(record[:at] + bytes([record[at] ^ 1]) + record[at + 1 :], 0)


def test_multi_index(spark):
    rng = np.random.default_rng(4)
    base = rng.normal(size=(400, 16))
    rows = [(i, v.tolist()) for i, v in enumerate(np.concatenate([base, base[:60] + rng.normal(size=(60, 16)) * 0.08, base[:20]]))]
    rows += [(1000, None), (1001, [0.0] * 16), (1002, [float("nan")] * 16), (1003, [None] * 16), (1004, [1.0] * 3), (1005, [])]
    out = {r.vec_id: r for r in multi_index.link(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), 0.95).collect()}
    v = multi_index.unit(np.array([np.array(r[1], np.float32) for r in rows[:480]], np.float64))
    links = v @ v.T >= 0.95
    np.fill_diagonal(links, False)
    found = sum(out[i].n_links for i in range(480))
    assert 0.9 * links.sum() <= found <= links.sum() and len(out) == len(rows)
    assert all(out[i].n_links == 0 and out[i].component_id == i and out[i].kept for i in range(1000, 1006))
    assert all(out[i + 460].component_id == i for i in range(20))
    assert multi_index.link(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def brute_sets(k):
    def one(t):
        w = [re.sub("[A-Z]", lambda m: m[0].lower(), x) for x in WORD.findall(t or "")]
        return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set()

    return [one(t) for t in TEXTS]


@pytest.mark.parametrize(("k", "percent"), [(4, 85), (5, 80)])
def test_jaccard_join(docs, none, k, percent):
    sets = brute_sets(k)
    label = list(range(len(sets)))
    changed = True
    while changed:
        changed = False
        for i, a in enumerate(sets):
            for j in range(i):
                if a and sets[j] and 100 * len(a & sets[j]) >= percent * len(a | sets[j]) and label[i] != label[j]:
                    label[i] = label[j] = min(label[i], label[j])
                    changed = True
    out = by_id(jaccard_join.classes(docs, k, percent))
    assert [(out[i].n_shingles, out[i].component_id) for i in range(len(sets))] == [(len(s), c) for s, c in zip(sets, label, strict=True)]
    assert jaccard_join.classes(none, k, percent).count() == 0


def test_jaccard_join_on_many_near_copies(spark):
    texts = [near(LONG, RNG.randrange(3, 14)) for _ in range(120)] + [prose(12) + " " + PASSAGE for _ in range(60)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    sets = [{tuple(t.split()[i : i + 4]) for i in range(len(t.split()) - 3)} for t in texts]
    parent = list(range(len(sets)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, a in enumerate(sets):
        for j in range(i):
            if 100 * len(a & sets[j]) >= 85 * len(a | sets[j]):
                x, y = find(i), find(j)
                parent[max(x, y)] = min(x, y)
    out = by_id(jaccard_join.classes(df))
    assert [out[i].component_id for i in range(len(sets))] == [find(i) for i in range(len(sets))]


@pytest.mark.parametrize("edits", [4, 9])
def test_jaccard_join_on_500_near_copies_at_the_threshold(spark, edits):
    base = prose(160)
    texts = [near(base, edits) for _ in range(500)] + [base + " " + prose(3), base, base]
    df = spark.createDataFrame([*enumerate(texts), (None, base), (7, texts[7])], "doc_id long, text string")
    grams = [{tuple(t.split()[i : i + 4]) for i in range(len(t.split()) - 3)} for t in texts]
    number = {g: i for i, g in enumerate(set().union(*grams))}
    table = np.zeros((len(texts), len(number)), np.float32)
    for i, s in enumerate(grams):
        table[i, [number[g] for g in s]] = 1
    both = table @ table.T
    size = table.sum(1)
    links = 100 * both >= 85 * (size[:, None] + size - both)
    label = np.arange(len(texts))
    while True:
        low = np.where(links, label, len(texts)).min(1)
        if (low == label).all():
            break
        label = low
    out = jaccard_join.classes(df).collect()
    got = {r.doc_id: r.component_id for r in out if r.doc_id is not None}
    assert [got[i] for i in range(len(texts))] == label.tolist() and len(out) == len(texts) + 2
    assert [r.component_id for r in out if r.doc_id is None] == [None]


def test_order_ranks_by_count(spark):
    texts = [prose(50) + " " + PASSAGE for _ in range(30)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    order = jaccard_join.order(df, 4, 3)
    sets = shingles(*text_buffer(pa.array(texts)), 4)
    keys, counts = np.unique(np.concatenate(sets), return_counts=True)
    rank = order.rank(keys)
    assert (rank[counts > 1] > 0).all() and (rank[counts == 1] == 0).mean() > 0.95
    assert (rank[counts >= jaccard_join.LEAST_HEAVY] > 1).all() and (np.diff(rank[np.argsort(counts, kind="stable")][-40:]) >= 0).all()


def test_hidden_markov(spark, docs, none):
    held = F.col("doc_id") % 7 == 2
    out = by_id(hidden_markov.score(docs, held))
    words = [[re.sub("[A-Z]", lambda m: m[0].lower(), x) for x in WORD.findall(t or "")] + ["\0"] for t in TEXTS]
    counts: dict = {}
    for i, w in enumerate(words):
        if i % 7 != 2:
            for x in w:
                counts[x] = counts.get(x, 0) + 1
    n, v = sum(counts.values()), len(counts)
    for i, w in enumerate(words):
        base = sum(np.log10((counts.get(x, 0) + 1) / (n + v + 1)) for x in w)
        assert (out[i].n_tokens, out[i].n_known, out[i].train_tokens, out[i].held_out) == (len(w), sum(x in counts for x in w), n, i % 7 == 2)
        assert abs(out[i].base_score - base) < 1e-6 and np.isfinite(out[i].score)
    assert hidden_markov.score(none, held).count() == 0


def test_forward_recursion_is_exact():
    rng = np.random.default_rng(2)
    model = hidden_markov.Model(np.arange(5, dtype=np.uint64), np.ones(5, np.int64), np.zeros(hidden_markov.SHARED, np.int64), np.zeros(hidden_markov.SHARED, np.int64), 5, 5)
    model.set(rng.random(3), rng.random(3), rng.random((3, 3)), rng.random((3, model.n)))
    counts = np.array([3, 1, 1500, 512, 513])
    cls = rng.integers(0, 5, counts.sum())
    starts = counts.cumsum() - counts
    got = hidden_markov.likelihood(model, cls, starts, counts)
    for s, c, g in zip(starts, counts, got, strict=True):
        a, total = model.start * model.emit[cls[s]], 0.0
        for t in range(1, c):
            total += np.log10(a.sum())
            a = (a / a.sum()) @ model.move * model.emit[cls[s + t]]
        assert abs(total + np.log10(a.sum()) - g) < 1e-6
    one = hidden_markov.expected(model, cls, starts, counts)
    assert abs(one[3].sum() - counts.sum()) < 1e-6 and abs(one[0].sum() - len(counts)) < 1e-6


def test_expected_counts_equal_a_plain_forward_backward():
    rng = np.random.default_rng(8)
    k, counts = 3, np.array([4, 1, 7, 2])
    model = hidden_markov.Model(np.arange(5, dtype=np.uint64), np.ones(5, np.int64), np.zeros(hidden_markov.SHARED, np.int64), np.zeros(hidden_markov.SHARED, np.int64), 5, 5)
    model.set(rng.random(k), rng.random(k), rng.random((k, k)), rng.random((k, model.n)))
    cls, starts = rng.integers(0, 5, counts.sum()), counts.cumsum() - counts
    start, move, emit, logs = np.zeros(k), np.zeros((k, k)), np.zeros((k, model.n)), 0.0
    for s, c in zip(starts, counts, strict=True):
        x = cls[s : s + c]
        f, b = np.zeros((c, k)), np.ones((c, k))
        f[0] = model.start * model.emit[x[0]]
        for t in range(1, c):
            f[t] = (f[t - 1] @ model.move) * model.emit[x[t]]
        for t in range(c - 2, -1, -1):
            b[t] = model.move @ (model.emit[x[t + 1]] * b[t + 1])
        total = f[-1].sum()
        logs += np.log10(total)
        start += f[0] * b[0] / total
        for t in range(c):
            emit[:, x[t]] += f[t] * b[t] / total
            if t:
                move += np.outer(f[t - 1], model.emit[x[t]] * b[t]) * model.move / total
    got = hidden_markov.expected(model, cls, starts, counts)
    assert all(np.allclose(g, w) for g, w in ((got[0], start), (got[2], move), (got[3], emit), (got[4], [logs])))


def test_counts_beyond_32_bits(spark):
    word = np.array([77], "<u8")
    rows = [(i, bytearray(word.tobytes()), bytearray(np.array([2**32 - 1], "<u4").tobytes())) for i in range(3)]
    counts = hidden_markov.word_counts(spark.createDataFrame(rows, "chunk long, keys binary, train binary"), 2)
    assert {int(np.frombuffer(r.c, "<u8")[0]) for r in counts.filter("kind = 0").collect()} == {3 * (2**32 - 1)}
    assert hidden_markov.word_classes(counts).tokens == 3 * (2**32 - 1)


def test_own_classes_are_bounded(spark, monkeypatch):
    rows = spark.createDataFrame([(i, " ".join(f"w{j}" for j in range(40) if j % 4 or i < 100)) for i in range(400)], "doc_id long, text string")
    counts = hidden_markov.word_counts(hidden_markov.chunks(rows, F.lit(False)), 2)
    monkeypatch.setattr(hidden_markov, "OWN", 4)
    assert len(hidden_markov.word_classes(counts).own) == 41
    monkeypatch.setattr(hidden_markov, "OWN_MOST", 35)
    assert len(hidden_markov.word_classes(counts).own) == 31


def test_states_are_trained_on_all_texts_until_they_settle(spark):
    H = hidden_markov
    texts = [prose(60) for _ in range(900)]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    table = H.chunks(rows, F.col("doc_id") % 7 == 2)
    counts = H.word_counts(table, 2)
    got, want = H.train(table, counts), H.word_classes(counts)
    H._begin(want, H.STATES)
    hashes, cut = H.word_hashes(*text_buffer(pa.array([t for i, t in enumerate(texts) if i % 7 != 2], pa.string())))
    keys, starts, n = H._sequences([np.append(hashes[a:b], H.END) for a, b in zip(cut[:-1], cut[1:], strict=True)])
    for at in got.history:
        *sums, logs = H.expected(want, want.classes(keys), starts, n)
        assert abs(logs[0] - at) < 1e-6 * abs(at)
        want.set(*sums)
    assert np.allclose(got.emit, want.emit, atol=1e-9) and np.allclose(got.move, want.move, atol=1e-9)
    gains = np.diff(got.history) / np.abs(got.history[:-1])
    assert (gains[:-1] >= H.SETTLED).all() and gains[-1] < H.SETTLED


def test_own_classes_follow_the_vocabulary(spark):
    text = " ".join(f"w{i}" for i in range(6000))
    rows = spark.createDataFrame([(i, text) for i in range(hidden_markov.OWN_COUNT)], "doc_id long, text string")
    model = hidden_markov.word_classes(hidden_markov.word_counts(hidden_markov.chunks(rows, F.lit(False)), 2))
    assert len(model.own) == 6001 and model.tokens == 6001 * hidden_markov.OWN_COUNT


def test_suffix_dedup(docs, none):
    first, want = set(), []
    for t in TEXTS:
        b = (t or "").encode()
        gone, new = np.zeros(len(b), bool), []
        for j in range(len(b) - 49):
            if b[j : j + 50] in first:
                gone[j : j + 50] = True
            new.append(b[j : j + 50])
        first.update(new)
        spans = int((gone[1:] & ~gone[:-1]).sum() + (gone[0] if len(b) else 0))
        want.append((len(b), int(gone.sum()), spans, hashlib.sha256(bytes(x for x, g in zip(b, gone, strict=True) if not g)).hexdigest()))
    out = by_id(suffix_dedup.remove_repeats(docs))
    assert [(out[i].n_bytes, out[i].n_removed, out[i].n_spans, out[i].kept_sha256) for i in range(len(TEXTS))] == want
    assert out[7].text == "" and out[3].text == "a" and out[0].text is None and out[0].score == "clash"
    assert suffix_dedup.remove_repeats(none).count() == 0


def test_suffix_dedup_of_a_passage_that_most_documents_share(spark):
    texts = [prose(RNG.randrange(3, 9)) + " " + PASSAGE + " " + prose(RNG.randrange(3, 30)) for _ in range(150)] + [PASSAGE * 3, PASSAGE[:60]] * 10
    RNG.shuffle(texts)
    first, want = set(), []
    for t in texts:
        b = t.encode()
        gone, new = np.zeros(len(b), bool), []
        for j in range(len(b) - 49):
            if b[j : j + 50] in first:
                gone[j : j + 50] = True
            new.append(b[j : j + 50])
        first.update(new)
        want.append(hashlib.sha256(bytes(x for x, g in zip(b, gone, strict=True) if not g)).hexdigest())
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    out = by_id(suffix_dedup.remove_repeats(df))
    assert [out[i].kept_sha256 for i in range(len(texts))] == want


def test_deep_shallow_order():
    rng = np.random.default_rng(1)
    rows = rng.integers(0, 2, (300, 40)).astype(np.uint8)
    rows[:, :26] = 7
    group = rng.integers(0, 3, 300)
    order, common = suffix_dedup.deep_shallow(group, rows)
    keys = [(int(group[i]), rows[i].tobytes()) for i in order]
    assert keys == sorted(keys)
    assert all(c == next((k for k in range(40) if a[1][k] != b[1][k]), 40) for a, b, c in zip(keys, keys[1:], common[1:], strict=False) if a[0] == b[0])
    for n in (0, 1, 2, 500):
        keys, group = rng.integers(0, 3, (n, 3)).astype(np.uint64), rng.integers(0, 5, n)
        got = suffix_dedup.multikey_quicksort(group, keys)
        told = [(int(group[i]), *keys[i].tolist()) for i in got]
        assert sorted(got.tolist()) == list(range(n)) and told == sorted(told)
    strings = [rng.integers(0, 3, 12).astype(np.uint8).tobytes() for _ in range(200)]
    assert [strings[i] for i in suffix_dedup.blind_trie_order(strings)] == sorted(strings)


def test_mixing(docs, none):
    out = mixing.mix(docs).collect()
    assert len(out) == len(TEXTS)
    again = {r.doc_id: r.taken for r in mixing.mix(docs.repartition(3)).collect()}
    for r in out:
        assert r.size == len(WORD.findall(TEXTS[r.doc_id] or "")) and r.taken in (0, r.size, 2 * r.size, 3 * r.size) and again[r.doc_id] == r.taken
    for s in {r.source for r in out}:
        own = [r for r in out if r.source == s]
        assert own[0].source_size == sum(r.size for r in own) and abs(sum(r.taken for r in own) - own[0].target) <= max(r.size for r in own)
    assert mixing.mix(none).count() == 0
    goal = mixing.targets([("a", 10), ("b", 1000), (None, 5)])
    assert goal == {"a": 30.0, None: 15.0, "b": 970.0}
    parts = mixing.pivot(list(range(500)), [5 + i % 7 for i in range(500)], [0.37] * 500, 1)
    assert sum(0 < p < 1 for p in parts) <= 1 and abs(sum(p * (5 + i % 7) for i, p in enumerate(parts)) - 0.37 * sum(5 + i % 7 for i in range(500))) < 1e-6


def test_piece_dropout(docs, none):
    path = vocabulary("piece_bpe_32k.model")
    plain, varied = piece_dropout.Segmenter(path, 0, 7), piece_dropout.Segmenter(path, 0.3, 7)
    for i, t in enumerate(TEXTS):
        if t is not None and "▁" not in t:
            assert plain.encode(t).tolist() == plain.library.encode(t)
        assert plain.decode(plain.encode(t or "").tolist()) == (t or "") == varied.decode(varied.encode(t or "", i).tolist())
    assert len({tuple(varied.encode(LONG, i).tolist()) for i in range(5)}) == 5
    out = by_id(piece_dropout.encode(docs, path))
    assert all(out[i].decoded == (t or "") and out[i].n_tokens == len(out[i].ids) for i, t in enumerate(TEXTS))
    assert piece_dropout.encode(none, path).count() == 0


def naive_dropout(s, text, doc, copy=0):
    """Words in turn, each segmented alone by a heap, every candidate drawn for by itself."""
    first, *rest = text.split("▁")
    units = re.findall("▁*[^▁\n]+|▁+|\n", "▁" + first.replace(" ", "▁"))
    for part in rest:
        units += [None, *re.findall("▁*[^▁\n]+|▁+|\n", part.replace(" ", "▁"))]
    keys = s.keys(doc, copy, 0, len(units)).tolist()
    return [[s.byte[b] for b in "▁".encode()] if u is None else s.segment(u, lambda c, k=k: s.skipped(k, c))[1] for u, k in zip(units, keys, strict=True)]


@pytest.mark.parametrize("dropout", [0.0, 0.1, 0.5])
def test_every_occurrence_draws(spark, monkeypatch, dropout):
    path, word = vocabulary("piece_bpe_32k.model"), "▁reconsideration"
    s = piece_dropout.Segmenter(path, dropout, 7)
    odd = ["a▁b ▁ c\n\n  d", "x" * 500 + " " + "ab" * 100 + "🙂" * 3, "🙂日", "  ", "\n", "▁", "ab" * 32 + " " + "ab" * 33]
    for i, t in enumerate([*TEXTS, *odd]):
        assert s.encode(t or "", i).tolist() == sum(naive_dropout(s, t, i) if t else [], [])
    text = " ".join([word[1:]] * 4000)
    found = naive_dropout(s, text, 3)
    assert s.encode(text, 3).tolist() == sum(found, [])
    met, plain = s.segment(word, lambda c: False)
    drawn = sum(not any(s.skipped(k, c) for c in met) for k in s.keys(3, 0, 0, 4000).tolist())
    assert abs(drawn / 4000 - (1 - dropout) ** len(met)) < 0.04 and sum(f == plain for f in found) >= drawn
    assert (len({tuple(f) for f in found}) > 10) == (dropout > 0)
    monkeypatch.setattr(piece_dropout, "CHARS", 50)
    assert piece_dropout.Segmenter(path, dropout, 7).encode(text, 3).tolist() == sum(found, [])
    assert s.encode("x" * 400 + " " + text[:300], 3).tolist() == sum(naive_dropout(s, "x" * 400 + " " + text[:300], 3), [])


def test_repeats_of_a_document_draw_for_themselves(spark):
    import corpus_pipeline as P

    twice = spark.createDataFrame([(5, LONG, "en", "s", len(LONG))] * 3, "doc_id long, text string, lang string, source string, n_chars long")
    assert len({tuple(r.ids) for r in P.encode_pieces(spark, twice, "").collect()}) == 3


def test_components_and_filters(spark):
    edges = [(1, 2), (2, 3), (10, 11), (5, 5), (3, 1), *((100 + i, 101 + i) for i in range(40))]
    got = dict(components(spark, spark.createDataFrame(edges, "a long, b long")).collect())
    assert got[3] == got[2] == got[1] == 1 and got[11] == 10 and got[140] == 100 and 5 not in got
    bits = Bits(14)
    keys = np.arange(500, dtype=np.uint64) * np.uint64(7919)
    bits.add(keys)
    assert bits.has(keys).all() and bits.has(keys + np.uint64(1)).mean() < 0.1


def test_pipeline(spark, sf):
    import corpus_pipeline as P

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    n, kept = docs.count(), docs
    for name, stage in P.STAGES:
        kept = P.written(stage(spark, kept, sf), name)
        if name in ("language_id", "jaccard_join", "suffix_dedup", "mixing"):
            assert kept.columns == docs.columns and 0 < kept.count() <= 3 * n
        if name == "jaccard_join":
            assert jaccard_join.classes(kept, 5, 80).filter("component_id <> doc_id").count() == 0
        if name == "mixing":
            texts = {r.doc_id: r.text for r in kept.collect()}
    assert all(texts[r.doc_id] == r.decoded for r in kept.collect())


def test_pipeline_keeps_rows_without_labels_or_ids(spark):
    import corpus_pipeline as P

    kinds = "doc_id long, text string, lang string, source string, n_chars long"
    bare = spark.createDataFrame([(1, "some words", None, "a", 10), (2, "12 34", None, "a", 5), (3, "日本", None, "a", 2), (4, None, None, "a", 0)], kinds)
    assert sorted(r.doc_id for r in P.name_language(spark, bare, "").collect()) == [1, 3]
    rows = [(i, LONG if i % 2 else "zz qq xx " * 30, None if i == 0 else "en" if i % 2 else "xx", "a", 9) for i in range(40)]
    assert all(r.lang in ("en", "xx") for r in P.name_language(spark, spark.createDataFrame(rows, kinds), "").collect())
    rows = [(None, f"one two {i}", "en", "a", 9) for i in range(5)] + [(7, f"three four {i}", "en", "b", 9) for i in range(5)] + [(8, "five", "en", None, 4)]
    docs = spark.createDataFrame(rows, kinds)
    want = sum(r.copies for r in P.mixing.mix(docs).collect())
    got = P.mix_sources(spark, docs, "").collect()
    assert len(got) == want and any(r.doc_id is None for r in got) and {r.text for r in got} <= {r[1] for r in rows}


def test_rounds_of_training_leave_no_shuffle_files(spark):
    from pathlib import Path

    from keysieve.llm import hidden_markov

    docs = spark.createDataFrame([(i, f"word{i % 7} word{i % 5} other") for i in range(60)], "doc_id long, text string").repartition(3)
    table = hidden_markov.chunks(docs, F.lit(False))
    model = hidden_markov.word_classes(hidden_markov.word_counts(table, 5))
    hidden_markov._begin(model, 2)
    folder = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirsString()
    held = lambda: {f.name for d in folder for f in Path(d).rglob("shuffle_*.data")}
    before = held()
    for _ in range(3):
        hidden_markov.corpus_expected(model, table)
    end = time.time() + 20
    while held() - before and time.time() < end:
        time.sleep(0.2)
    assert not held() - before


def test_mixing_deals_texts_once(spark):
    import corpus_pipeline as P

    rows = [(i // 2 if i % 5 else None, f"one two {i}", "en", "ab"[i % 2], 9) for i in range(40)]
    mixed = P.mix_sources(spark, spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long"), "")
    plan = mixed._jdf.queryExecution().executedPlan().toString()
    assert sum("Exchange hashpartitioning" in line for line in plan.splitlines()) == 1


def test_batches_are_bounded_by_bytes(spark):
    """A task's batch has some 4 MB at most, however many rows that are, or one row."""

    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.nbytes], pa.int64())], ["n"])

    wide = spark.range(0, 24, 1, 1).select(F.repeat(F.lit("abcdefgh"), 1 << 17).alias("text"))
    assert max(r.n for r in wide.mapInArrow(sizes, "n long").collect()) < 6 << 20
