"""Merge-type encoding with seeded dropout, and lossless decoding, for SentencePiece models.

Characters of a text (spaces as U+2581, one in front) are the first symbols. An agenda holds adjacent pairs that
form a piece, best score first and leftmost among equals. A candidate is skipped for good with a given
probability, decided by a keyed hash of the seed, the document, the word's place in it and the candidate (its
piece and place); the others are merged. Without dropout the result is the library's. Symbols that are no piece
become byte pieces, so decoding gives the text back exactly.

No piece goes over the end of a word into a space, so words are segmented alone, and each occurrence of a word
draws for every candidate it meets. The agendas of thousands of words advance together: a column holds a word's
agenda by place, one step takes the best candidate of every word, draws, and merges or strikes it out. Nothing is
remembered from one word to the next. Words of more than `LONG` characters have a heap each, under the same draws.

Defined results: a null or empty text has no tokens and decodes to the empty text; texts of any length are
encoded whole; a row without doc_id takes its text's CRC-32 as its document; rows of equal doc_id draw alike
unless `copy` tells them apart; models without byte pieces would not be lossless and are refused.
"""

from __future__ import annotations

import heapq
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import U64, mix

#: Characters that are segmented together, and those from which a word has an agenda of its own.
CHARS, LONG = 1 << 19, 64
_M = (1 << 64) - 1
_STEP, _COPY = U64(0x9E3779B97F4A7C15), U64(0xD1B54A32D192ED03)
#: A space, and the code that stands for a text's own U+2581, which stays apart from spaces as byte pieces.
_SPACE, _OWN = 0x2581, 0x110000
_NONE = np.int32(2**31 - 1)


class Pairs:
    """Pieces by their two parts: an open table of numbers, looked up for many pairs at once."""

    def __init__(self, left: np.ndarray, right: np.ndarray, piece: np.ndarray, symbols: int):
        self.symbols = symbols
        bits = max(4, int(len(piece) * 4).bit_length())
        self.shift = U64(64 - bits)
        keys = left.astype(np.int64) * symbols + right
        self.key, self.piece = np.full((1 << bits) + 64, -1, np.int64), np.full((1 << bits) + 64, -1, np.int32)
        for k, at, p in zip(keys.tolist(), self._at(keys).tolist(), piece.tolist(), strict=True):
            while self.key[at] >= 0:
                at += 1
            self.key[at], self.piece[at] = k, p

    def _at(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.view(np.uint64) * _STEP) >> self.shift).astype(np.int64)

    def find(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The piece of each pair, -1 if there is none."""
        keys = left.astype(np.int64) * self.symbols + right
        at = self._at(keys)
        held = self.key[at]
        out = np.where(held == keys, self.piece[at], np.int32(-1))
        more = np.flatnonzero((held != keys) & (held >= 0))
        while len(more):
            at[more] += 1
            held = self.key[at[more]]
            hit = held == keys[more]
            out[more[hit]] = self.piece[at[more[hit]]]
            more = more[~hit & (held >= 0)]
        return out


class Segmenter:
    def __init__(self, path: str, dropout: float, seed: int):
        from sentencepiece import SentencePieceProcessor

        self.library = SentencePieceProcessor(model_file=path)
        n = self.n = self.library.get_piece_size()
        self.piece = [self.library.id_to_piece(i) for i in range(n)]
        self.byte = {int(self.piece[i][3:5], 16): i for i in range(n) if self.library.is_byte(i)}
        if len(self.byte) != 256:
            raise ValueError("the model has no byte pieces")
        plain = [i for i in range(n) if not (self.library.is_byte(i) or self.library.is_control(i) or self.library.is_unknown(i))]
        self.id = {self.piece[i]: i for i in plain}
        scores = {self.piece[i]: self.library.get_score(i) for i in plain}
        same = {s: r for r, s in enumerate(sorted(set(scores.values()), reverse=True))}
        self.order = {p: same[s] for p, s in scores.items()}
        if any("▁" in p.lstrip("▁") or "\n" in p for p in self.id if len(p) > 1):
            raise ValueError("pieces reach over the end of a word")
        self.text = [b""] * n
        for p, i in self.id.items():
            self.text[i] = p.replace("▁", " ").encode()
        for b, i in self.byte.items():
            self.text[i] = bytes([b])
        # symbols: pieces by their number, then all code points, for characters that are no piece
        self.symbol = np.arange(n, n + _OWN + 1, dtype=np.int32)
        for p, i in self.id.items():
            if len(p) == 1:
                self.symbol[ord(p)] = i
        number = lambda p: self.id.get(p, n + ord(p) if len(p) == 1 else None)
        splits = [(number(p[:c]), number(p[c:]), i) for p, i in self.id.items() for c in range(1, len(p))]
        splits = np.array([x for x in splits if None not in x], np.int64).reshape(-1, 3)
        self.pairs = Pairs(splits[:, 0], splits[:, 1], splits[:, 2], n + _OWN + 1)
        self.rank = np.zeros(n, np.int32)
        for p, i in self.id.items():
            self.rank[i] = self.order[p]
        if len(same) >= 1 << 25:
            raise ValueError("too many scores for one agenda number")
        self.limit, self.seed = int(dropout * (1 << 32)), mix(np.array([seed & _M], U64))

    def segment(self, unit: str, skips) -> tuple[list[int], list[int]]:
        """The candidates that one word meets, in order, and its ids, when candidates for which `skips` holds are skipped."""
        sym, n, rank, number = list(unit), len(unit), self.order.get, self.id
        shift = 20 if n < 1 << 20 else 40
        place, met = (1 << shift) - 1, []
        # a candidate on the agenda is one number: the rank of its piece, then its place
        agenda = [r << shift | i for i, r in enumerate([rank(a + b) for a, b in zip(sym, unit[1:], strict=False)]) if r is not None]
        heapq.heapify(agenda)
        pop, push, after, before = heapq.heappop, heapq.heappush, list(range(1, n + 1)), list(range(-1, n - 1))
        while agenda:
            c = pop(agenda)
            i = c & place
            left, j = sym[i], after[i]
            if left is None or j >= n:
                continue
            got = left + sym[j]
            if rank(got) != c >> shift:
                continue
            code = number[got] << 40 | i
            met.append(code)
            if skips(code):
                continue
            sym[i], sym[j] = got, None
            j = after[i] = after[j]
            if j < n:
                before[j] = i
                r = rank(got + sym[j])
                if r is not None:
                    push(agenda, r << shift | i)
            k = before[i]
            if k >= 0:
                r = rank(sym[k] + got)
                if r is not None:
                    push(agenda, r << shift | k)
        out = []
        for s in sym:
            if s is not None:
                if (i := number.get(s)) is not None:
                    out.append(i)
                else:
                    out.extend(self.byte[b] for b in s.encode())
        return met, out

    def skipped(self, key: int, code: int) -> bool:
        """Whether the occurrence of a word with this key skips a candidate."""
        return self.limit > 0 and _mix(key ^ _mix(code)) >> 32 < self.limit

    def keys(self, doc_key: int, copy: int, start: int, n: int) -> np.ndarray:
        """Keys of the occurrences of words start, ..., start + n - 1 of a document."""
        document = mix(mix(U64(doc_key & _M) ^ self.seed) + U64(copy & _M) * _COPY)
        return mix(document + np.arange(start, start + n, dtype=U64) * _STEP)

    def _slices(self, text: str):
        """Code points of a text in slices of whole words, and where the words of each begin."""
        points = np.frombuffer(text.encode("utf-32-le"), "<u4").astype(np.int32)
        points = np.concatenate([[_SPACE], np.where(points == _SPACE, _OWN, np.where(points == 32, _SPACE, points))]).astype(np.int32)
        at = 0
        while at < len(points):
            size = CHARS
            while True:
                part = points[at : at + size]
                space, alone = part == _SPACE, (part == 10) | (part == _OWN)
                first = alone.copy()
                first[0] = True
                first[1:] |= (space[1:] & ~space[:-1]) | (~space[1:] & alone[:-1])
                begin = np.flatnonzero(first)
                if at + size >= len(points):
                    break
                if len(begin) > 1:  # the last word may go on
                    part, begin = part[: begin[-1]], begin[:-1]
                    break
                size *= 2
            yield part, begin
            at += len(part)

    def encode(self, text: str, doc_key: int = 0, copy: int = 0) -> np.ndarray:
        return self.encode_all([text], [doc_key], [copy])[0]

    def encode_all(self, texts: list[str], doc_keys: list[int], copies: list[int]) -> list[np.ndarray]:
        out: list[list[np.ndarray]] = [[] for _ in texts]
        held, size = [], 0  # text, points, begins, keys

        def flush():
            points = np.concatenate([h[1] for h in held])
            lengths = np.array([len(h[1]) for h in held])
            begin = np.concatenate([h[2] + a for h, a in zip(held, lengths.cumsum() - lengths, strict=True)])
            ids, counts = self._segment_all(points, begin, np.concatenate([h[3] for h in held]))
            ends = np.concatenate([[0], counts.cumsum()])[np.cumsum([len(h[2]) for h in held])]
            for h, a, b in zip(held, [0, *ends[:-1].tolist()], ends.tolist(), strict=True):
                out[h[0]].append(ids[a:b])

        for t, text in enumerate(texts):
            before = 0
            for points, begin in self._slices(text) if text else ():
                held.append((t, points, begin, self.keys(doc_keys[t], copies[t], before, len(begin))))
                before += len(begin)
                size += len(points)
                if size >= CHARS:
                    flush()
                    held, size = [], 0
        if held:
            flush()
        return [np.concatenate(o) if len(o) > 1 else o[0] if o else np.zeros(0, np.int32) for o in out]

    def _segment_all(self, points: np.ndarray, begin: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words in turn, and how many each word has."""
        length = np.diff(np.append(begin, len(points)))
        symbols = self.symbol[points]
        final = np.full(len(points), -1, np.int32)  # the symbol that begins at a character after all merges
        low = 0
        for high in (1, 4, 6, 8, 12, 16, 24, 32, LONG):
            some = np.flatnonzero((length > low) & (length <= high))
            low = high
            for a in range(0, len(some), 1 << 15):
                own = some[a : a + (1 << 15)]
                self._advance(symbols, begin[own], length[own], keys[own], high, final)
        for w in np.flatnonzero(length > LONG).tolist():
            self._alone(points[begin[w] : begin[w] + length[w]], int(keys[w]), final[begin[w] : begin[w] + length[w]])
        here = np.flatnonzero(final >= 0)
        ids, counts = final[here], np.add.reduceat(final >= 0, begin, dtype=np.int64)
        other = np.flatnonzero(ids >= self.n)
        if len(other):  # characters that are no piece become their bytes
            raw = [chr(_SPACE if c == _OWN else c).encode() for c in (ids[other] - self.n).tolist()]
            times = np.ones(len(ids), np.int64)
            times[other] = [len(r) for r in raw]
            word = np.searchsorted(begin, here[other], "right") - 1
            np.add.at(counts, word, times[other] - 1)
            wide = np.repeat(ids, times)
            wide[np.repeat(ids >= self.n, times)] = np.array([self.byte[b] for b in b"".join(raw)], np.int32)
            ids = wide
        return ids, counts

    def _alone(self, points: np.ndarray, key: int, final: np.ndarray) -> None:
        """One long word by a heap; a symbol is put where it begins."""
        unit = points.astype("<u4").tobytes().decode("utf-32-le")
        met, ids = self.segment(unit, lambda code: self.skipped(key, code))
        at, i = 0, 0
        while at < len(unit):
            if self.id.get(unit[at]) is None and ids[i] == self.byte[unit[at].encode()[0]]:
                final[at], i, at = self.n + ord(unit[at]), i + len(unit[at].encode()), at + 1
            else:
                final[at], at, i = ids[i], at + len(self.piece[ids[i]]), i + 1

    def _advance(self, symbols: np.ndarray, begin: np.ndarray, length: np.ndarray, keys: np.ndarray, most: int, final: np.ndarray) -> None:
        """All merges of words of at most `most` characters: places are rows, words are columns."""
        place = np.arange(most, dtype=np.int64)[:, None]
        inside = place < length
        sym = np.where(inside, symbols[np.minimum(begin + place, len(symbols) - 1)], np.int32(-1))
        if most > 1:
            n = len(begin)
            piece, agenda = np.full((most, n), -1, np.int32), np.full((most, n), _NONE, np.int32)
            both = np.flatnonzero(inside[1:].ravel())
            flat = sym.ravel()
            self._offer(both, flat[both], flat[both + n], both // n, piece.ravel(), agenda.ravel())
            after, before = (np.repeat((np.arange(most, dtype=np.int32) + s)[:, None], n, 1) for s in (1, -1))
            self._agendas(sym, piece, agenda, after, before, length, keys)
        alive = sym >= 0
        final[(begin + place)[alive]] = sym[alive]

    def _offer(self, at, left, right, place, piece, agenda) -> None:
        """Puts pairs that form a piece on the agenda, at their left symbol."""
        got = self.pairs.find(left, right)
        piece[at] = got
        agenda[at] = np.where(got >= 0, self.rank[got] * 64 + place, _NONE)

    def _agendas(self, sym, piece, agenda, after, before, length, keys) -> None:
        n = len(length)
        sym_, piece_, agenda_, after_, before_ = (x.ravel() for x in (sym, piece, agenda, after, before))  # views
        active = np.arange(n)
        while True:
            best = agenda.min(0)[active] if 4 * len(active) > n else agenda[:, active].min(0)
            some = best != _NONE
            active, best = active[some], best[some]
            if not len(active):
                return
            i = best & 63
            at = i.astype(np.int64) * n + active
            got = piece_[at]
            if self.limit:
                skip = (mix(keys[active] ^ mix(got.astype(np.uint64) << U64(40) | i.astype(np.uint64))) >> U64(32)) < U64(self.limit)
                agenda_[at[skip]] = _NONE
                keep = ~skip
                word, at, got, i = active[keep], at[keep], got[keep], i[keep]
            else:
                word = active
            gone = after_[at].astype(np.int64) * n + word
            sym_[at], sym_[gone] = got, -1
            agenda_[gone] = _NONE
            agenda_[at] = _NONE
            after_[at] = right = after_[gone]
            more = np.flatnonzero(right < length[word])
            there = right[more].astype(np.int64) * n + word[more]
            before_[there] = i[more]
            self._offer(at[more], got[more], sym_[there], i[more], piece_, agenda_)
            left = before_[at]
            more = np.flatnonzero(left >= 0)
            there = left[more].astype(np.int64) * n + word[more]
            self._offer(there, sym_[there], got[more], left[more], piece_, agenda_)

    def decode(self, ids) -> str:
        return b"".join(map(self.text.__getitem__, ids))[1:].decode() if len(ids) else ""


def _mix(x: int) -> int:
    """`mix` of one number."""
    x = ((x ^ x >> 30) * 0xBF58476D1CE4E5B9) & _M
    x = ((x ^ x >> 27) * 0x94D049BB133111EB) & _M
    return x ^ x >> 31


_segmenters: dict[tuple, Segmenter] = {}


def segmenter(path: str, dropout: float, seed: int) -> Segmenter:
    if (path, dropout, seed) not in _segmenters:
        _segmenters[path, dropout, seed] = Segmenter(path, dropout, seed)
    return _segmenters[path, dropout, seed]


def encode(docs: DataFrame, path: str, dropout: float = 0.1, seed: int = 7, text: str = "text", digest: bool = False, copy: str | None = None) -> DataFrame:
    """(doc_id, n_tokens, ids, decoded), or with `digest` the ids' CRC-32 and whether decoding gave the text back, of every row.

    `copy` is a column that numbers the repeats of a document, each of which draws for itself.
    """

    def run(batches):
        s = segmenter(path, dropout, seed)
        for batch in batches:
            for a in range(0, len(batch), 128):
                keys, texts = batch.column(0).slice(a, 128), batch.column(1).slice(a, 128).to_pylist()
                numbers = [zlib.crc32((t or "").encode()) if k is None else k for t, k in zip(texts, keys.to_pylist(), strict=True)]
                ids = s.encode_all([t or "" for t in texts], numbers, batch.column(2).slice(a, 128).to_pylist())
                back = [s.decode(i.tolist()) for i in ids]
                n = pa.array([len(i) for i in ids], pa.int64())
                if digest:
                    rest = [pa.array([zlib.crc32(i.astype("<u4").tobytes()) for i in ids], pa.int64()), pa.array([b == (t or "") for b, t in zip(back, texts, strict=True)])]
                else:
                    rest = [pa.array([i.tolist() for i in ids], pa.list_(pa.int32())), pa.array(back, pa.string())]
                yield pa.RecordBatch.from_arrays([keys, n, *rest], ["doc_id", "n_tokens", *(["ids_crc32", "lossless"] if digest else ["ids", "decoded"])])

    rest = "ids_crc32 long, lossless boolean" if digest else "ids array<int>, decoded string"
    nth = F.lit(0).cast("long") if copy is None else F.coalesce(F.col(copy).cast("long"), F.lit(0))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"), nth.alias("nth")).mapInArrow(run, f"doc_id long, n_tokens long, {rest}")
