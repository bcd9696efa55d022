"""Token counts of byte-level BPE vocabularies without producing tokens.

A piece of text starts as one symbol per byte. A heap holds its adjacent pairs by rank and position, and a
linked list its symbols; the lowest-ranked pair is merged until none is left. The count is the number of
symbols at the start minus the number of merges. Counts of pieces are kept in a bounded memo.

Special strings inside a text count as one token each, as the tokenizers library has it by default.
Defined results: null texts are empty and have 0 tokens; any length and any script is counted whole.
"""

from __future__ import annotations

import heapq
import json
import re
import unicodedata

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import text_buffer

#: Pieces whose counts a worker remembers; it then starts anew, which costs time and changes nothing.
MEMO = 700_000
_NARROW = 0x250


def _class(which) -> str:
    return "".join(f"\\x{c:02x}" if c < 256 else f"\\u{c:04x}" for c in range(_NARROW) if which(c))


def _blank(c: int) -> bool:
    return 9 <= c <= 13 or c in (0x20, 0x85, 0xA0)


def _kind(c: int) -> str:
    return unicodedata.category(chr(c))[0]


LETTERS, NUMBERS, BLANKS = _class(lambda c: _kind(c) == "L"), _class(lambda c: _kind(c) == "N"), _class(_blank)
#: The split into pieces that the vocabulary file names, for texts below U+0250 and for all texts.
SUFFIXES = "'s|'t|'re|'ve|'m|'ll|'d"
_NEAR = re.compile(rf"{SUFFIXES}| ?[{LETTERS}]+| ?[{NUMBERS}]+| ?[^{BLANKS}{LETTERS}{NUMBERS}]+|[{BLANKS}]+(?![^{BLANKS}])|[{BLANKS}]+")
_WIDE = regex.compile(rf"{SUFFIXES}| ?\p{{L}}+| ?\p{{N}}+| ?[^\p{{White_Space}}\p{{L}}\p{{N}}]+|\p{{White_Space}}+(?!\P{{White_Space}})|\p{{White_Space}}+")


def byte_letters() -> list[str]:
    """The printable stand-in of each byte in byte-level vocabularies: itself if printable Latin-1, else from U+0100 on."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = iter(range(256, 512))
    return [chr(b) if b in set(own) else chr(next(rest)) for b in range(256)]


class Counter:
    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            told = json.load(f)
        merges = told["model"]["merges"]
        self.rank = {" ".join(m) if isinstance(m, list) else m: r for r, m in enumerate(merges)}
        self.letters = byte_letters()
        special = [a["content"] for a in told["added_tokens"]]
        self.special = regex.compile("|".join(map(regex.escape, sorted(special, key=len, reverse=True)))) if special else None
        self.memo: dict[str, int] = _Memo(self)

    def merged(self, piece: str) -> int:
        """Symbols left of a piece after all merges."""
        letters, rank = self.letters, self.rank.get
        sym = [letters[b] for b in piece.encode()]
        n = left = len(sym)
        shift = 20 if n < 1 << 20 else 40
        place = (1 << shift) - 1
        heap = []  # a pair is one number: its rank, then its place
        for i in range(n - 1):
            r = rank(sym[i] + " " + sym[i + 1])
            if r is not None:
                heap.append(r << shift | i)
        if not heap:
            return n
        heapq.heapify(heap)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        pop, push = heapq.heappop, heapq.heappush
        while heap:
            c = pop(heap)
            i = c & place
            j = after[i]
            a = sym[i]
            if a is None or j >= n or rank(a + " " + sym[j]) != c >> shift:
                continue
            a = sym[i] = a + sym[j]
            sym[j] = None
            j = after[i] = after[j]
            left -= 1
            if j < n:
                before[j] = i
                r = rank(a + " " + sym[j])
                if r is not None:
                    push(heap, r << shift | i)
            k = before[i]
            if k >= 0:
                r = rank(sym[k] + " " + a)
                if r is not None:
                    push(heap, r << shift | k)
        return left

    def count(self, text: str) -> int:
        total, parts = 0, [text]
        if self.special is not None and "<" in text:
            parts = self.special.split(text)
            total = len(parts) - 1
        for part in parts:
            pieces = (_NEAR if part.isascii() or max(part) < chr(_NARROW) else _WIDE).findall(part)
            total += sum(map(self.memo.__getitem__, pieces))
        if len(self.memo) > MEMO:
            self.memo.clear()
        return total


class _Memo(dict):
    def __init__(self, counter: Counter):
        self.counter = counter

    def __missing__(self, piece: str) -> int:
        n = self.counter.merged(piece)
        if len(piece) < 64:
            self[piece] = n
        return n


_counters: dict[str, Counter] = {}


def counter(path: str) -> Counter:
    if path not in _counters:
        _counters[path] = Counter(path)
    return _counters[path]


def count_tokens(docs: DataFrame, path: str, limit: int = 512, text: str = "text") -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) of every row."""

    def run(batches):
        c = counter(path)
        for batch in batches:
            texts = batch.column(1)
            _, offsets = text_buffer(texts)
            n = np.array([c.count(t.as_py() or "") for t in texts], np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.diff(offsets), pa.int64()), pa.array(n), pa.array(n > limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs[text].cast("string").alias("text")).mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
