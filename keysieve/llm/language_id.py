"""Language identification with blended-spectrum string kernels.

A text is the set of its byte n-grams of every length from 1 to `longest` (A-Z lower-cased). The kernel
of two texts is the size of the intersection of their sets over the geometric mean of the set sizes,
within the grams that at least two landmark texts hold. Nystroem landmarks turn it into a finite feature
map, one-versus-rest ridge regression gives one weight vector per language, and texts are scored in
batches: presence matrix x landmark matrix x weights.

Defined results: a null text, or one without any letter, is `und` with score 0. Repeated rows, ties and
very long texts are scored like any other; the winner of an exact tie is the first language in order.
Without labelled rows every text is `und`. Rows with a null lang are never learned from; rows without the key
column's value are sampled by their text.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER, slices, text_buffer

#: Labelled texts that a model is fitted on, about, their bytes at most, and how many of them are landmarks.
SAMPLE, SAMPLE_BYTES, LANDMARKS = 2400, 64 << 20, 160
_PLACES = 18


@dataclass
class KernelModel:
    languages: list[str]
    longest: int
    places: np.ndarray  # hash of a gram -> column of the presence matrix; the last column takes all others
    landmarks: np.ndarray  # columns x landmarks, of unit length
    weights: np.ndarray  # landmarks x languages
    bias: np.ndarray

    def presence(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        out = np.zeros((len(offsets) - 1, len(self.landmarks) + 1), np.float32)
        for d in range(len(out)):
            for g in _grams(data[offsets[d] : offsets[d + 1]], self.longest):
                out[d, self.places[g]] = 1
        return out[:, :-1]

    def decide(self, presence: np.ndarray) -> np.ndarray:
        size = np.sqrt(np.maximum(presence.sum(1, keepdims=True), 1))
        return ((presence @ self.landmarks) / size) @ self.weights + self.bias


def _grams(text: np.ndarray, longest: int) -> list[np.ndarray]:
    """Hashed places of all grams, one array for each length."""
    low, out = LOWER[text].astype(np.uint64), []
    key = np.zeros(len(text), np.uint64)
    for n in range(1, longest + 1):
        if len(text) < n:
            break
        key = ((key[:-1] << np.uint64(8)) if n > 1 else key) | low[n - 1 :]
        out.append((((key << np.uint64(3)) | np.uint64(n)) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - _PLACES))
    return out


def sample(labelled: DataFrame, text: str, lang: str, key: str, size: int = SAMPLE, most_bytes: int = SAMPLE_BYTES) -> list:
    """About `size` labelled texts at most, of `most_bytes` in all, balanced over all languages, the same ones at each run.

    Each language gives the rows whose hashed key lies below one common count over its own row count, so only
    the chosen rows leave their tasks; what comes to the driver besides is one row for each language. A text of
    more than a sixteenth of the bytes is no example.
    """
    spark = labelled.sparkSession
    rows = labelled.filter(F.col(lang).isNotNull() & F.col(text).rlike(r"\p{L}")).select(F.col(text).alias("text"), F.col(lang).alias("lang"), F.col(key).alias("key"))
    totals = [(r["lang"], r["n"]) for r in rows.groupBy("lang").agg(F.count("*").alias("n")).collect()]
    if not totals:
        return []
    low, high = 0.0, float(max(n for _, n in totals))
    for _ in range(60):
        middle = (low + high) / 2
        low, high = (middle, high) if sum(min(n, middle) for _, n in totals) <= size else (low, middle)
    each = F.broadcast(spark.createDataFrame([(name, (low if low > 0 else high) / n) for name, n in totals], "lang string, share double"))
    place = F.pmod(F.xxhash64(F.coalesce(F.col("key").cast("string"), F.col("text"))), F.lit(1 << 40)) / (1 << 40)
    near = rows.join(each, "lang").select("text", "lang", (place / F.col("share")).alias("place")).filter((F.col("place") <= 1) & (F.octet_length("text") <= most_bytes // 16))
    order = sorted(near.select("place", F.octet_length("text").alias("n")).collect())
    cut, total = 0.0, 0
    for r in order[: 2 * size]:
        total += r["n"]
        if total > most_bytes:
            break
        cut = r["place"]
    found = near.filter(F.col("place") <= cut).collect()
    return [(r["text"], r["lang"]) for r in sorted(found, key=lambda r: (r["place"], r["lang"], r["text"]))][: 2 * size]


def fit(rows: list, longest: int = 4, landmarks: int = LANDMARKS, ridge: float = 1e-4) -> KernelModel | None:
    """Fit on (text, lang) rows, which are in random order and balanced."""
    languages = sorted({r[1] for r in rows})
    if not languages:
        return None
    data, offsets = text_buffer(pa.array([r[0] for r in rows], pa.string()))
    m = min(landmarks, len(rows))
    seen = np.zeros(1 << _PLACES, np.int32)
    for d in range(m):
        own = np.unique(np.concatenate(_grams(data[offsets[d] : offsets[d + 1]], longest)))
        seen[own] += 1
    kept = np.flatnonzero(seen >= min(2, m))
    places = np.full(1 << _PLACES, len(kept), np.int32)
    places[kept] = np.arange(len(kept))
    model = KernelModel(languages, longest, places, np.zeros((len(kept), m), np.float32), np.zeros(0), np.zeros(0))
    parts = [model.presence(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]) for i, j in ((i, min(i + 200, len(rows))) for i in range(0, m, 200))]
    marks = np.concatenate(parts)[:m]
    model.landmarks = np.ascontiguousarray((marks / np.sqrt(np.maximum(marks.sum(1, keepdims=True), 1))).T)
    near = []
    for i in range(0, len(rows), 200):
        j = min(i + 200, len(rows))
        p = model.presence(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
        near.append((p @ model.landmarks) / np.sqrt(np.maximum(p.sum(1, keepdims=True), 1)))
    kernel = np.concatenate(near).astype(np.float64)
    values, vectors = np.linalg.eigh(kernel[:m])
    strong = values > max(values.max(), 1e-12) * 1e-6
    root = vectors[:, strong] / np.sqrt(values[strong])
    features = kernel @ root
    target = np.where(np.array([r[1] for r in rows])[:, None] == np.array(languages), 1.0, -1.0)
    middle, level = features.mean(0), target.mean(0)
    centred = features - middle
    solved = np.linalg.solve(centred.T @ centred + ridge * len(rows) * np.eye(centred.shape[1]), centred.T @ (target - level))
    model.weights, model.bias = (root @ solved).astype(np.float32), (level - middle @ solved).astype(np.float32)
    return model


def predict(docs: DataFrame, model: KernelModel | None, text: str = "text") -> DataFrame:
    """docs with lang_pred and score; a column of docs by one of those names is replaced."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(model)
    docs = docs.drop("lang_pred", "score")

    def run(batches):
        model = shared.value
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index(text))
            data, offsets = text_buffer(texts)
            names, scores = np.full(len(texts), "und", object), np.zeros(len(texts))
            lettered = np.zeros(len(texts), bool)
            for i, j in slices(offsets, 1 << 18):
                low = LOWER[data[offsets[i] : offsets[j]]]
                count = np.concatenate([[0], np.cumsum((low >= 97) & (low <= 122), dtype=np.int32)])
                lettered[i:j] = np.diff(count[offsets[i : j + 1] - offsets[i]]) > 0
                for d in np.flatnonzero(~lettered[i:j] & (np.diff(offsets[i : j + 1]) > 0)) + i:
                    lettered[d] = any(map(str.isalpha, texts[int(d)].as_py()))
                for a in range(i, j, 128) if model is not None else ():
                    b = min(a + 128, j)
                    got = model.decide(model.presence(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]))
                    names[a:b] = np.array(model.languages, object)[got.argmax(1)]
                    scores[a:b] = np.clip((got.max(1) + 1) / 2, 0, 1)
            names[~lettered], scores[~lettered] = "und", 0
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(names, pa.string()), pa.array(scores)], [*batch.schema.names, "lang_pred", "score"])

    fields = ", ".join(f"`{f.name.replace('`', '``')}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return docs.mapInArrow(run, f"{fields}, lang_pred string, score double")
