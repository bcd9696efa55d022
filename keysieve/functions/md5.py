"""The portable hash family on Arrow batches: MD5 of short texts for whole arrays of numbers at once.

Gives what `hashing.h60` gives for the portable family, without a text for each row.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa

_TURNS = [7, 12, 17, 22] * 4 + [5, 9, 14, 20] * 4 + [4, 11, 16, 23] * 4 + [6, 10, 15, 21] * 4
_ADD = np.floor(np.abs(np.sin(np.arange(1, 65))) * 2**32).astype(np.uint64).astype(np.uint32)
_START = tuple(np.uint32(x) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476))
#: Messages that are hashed at once, so that their words stay in the processor's cache; bytes of a message in one block.
_ONCE, _LONGEST = 1 << 13, 55


def h60_of(text: str) -> int:
    return int(hashlib.md5(text.encode()).hexdigest()[:15], 16)


def _block(words: list) -> np.ndarray:
    """The first 60 bits of the MD5 of messages of one block: 16 words, each an array or one number for all."""
    n = next(len(w) for w in words if isinstance(w, np.ndarray))
    a, b, c, d = (np.full(n, x, np.uint32) for x in _START)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        if i < 16:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
            w = words[i]
        elif i < 32:
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
            w = words[(5 * i + 1) % 16]
        elif i < 48:
            np.bitwise_xor(b, c, out=f)
            f ^= d
            w = words[(3 * i + 5) % 16]
        else:
            np.bitwise_not(d, out=f)
            f |= b
            f ^= c
            w = words[7 * i % 16]
        f += a
        f += _ADD[i]
        f += w
        np.right_shift(f, np.uint32(32 - _TURNS[i]), out=t)
        np.left_shift(f, np.uint32(_TURNS[i]), out=f)
        f |= t
        f += b
        a, f, d, c, b = d, a, c, b, f
    first, second = (a + _START[0]).byteswap().astype(np.uint64), (b + _START[1]).byteswap().astype(np.uint64)
    return (((first << np.uint64(32)) | second) >> np.uint64(4)).astype(np.int64)


def _digits(values: np.ndarray) -> np.ndarray:
    """The number of decimal digits of each number that is not negative."""
    return np.searchsorted(10 ** np.arange(1, 19, dtype=np.int64), values, side="right") + 1


def numbers(before: str, values: np.ndarray, then: np.ndarray | None = None) -> np.ndarray:
    """h60 of before + value, or of before + value + ":" + then, for arrays of integers."""
    values = values.astype(np.int64, copy=False)
    parts = [values] if then is None else [values, then.astype(np.int64, copy=False)]
    head = np.frombuffer(before.encode(), np.uint8)
    if not len(values):
        return np.zeros(0, np.int64)
    if len(head) + 20 * len(parts) > _LONGEST or min(int(p.min()) for p in parts) < 0:
        texts = map(str, values.tolist()) if then is None else (f"{v}:{t}" for v, t in zip(values.tolist(), then.tolist(), strict=True))
        return np.fromiter((h60_of(before + t) for t in texts), np.int64, len(values))
    out = np.empty(len(values), np.int64)
    for lo in range(0, len(values), _ONCE):
        own = [p[lo : lo + _ONCE] for p in parts]
        sizes = np.zeros(len(own[0]), np.int64)
        for p in own:
            sizes = sizes * 32 + _digits(p)
        kinds = np.unique(sizes)
        for kind in kinds.tolist():
            at = slice(None) if len(kinds) == 1 else np.flatnonzero(sizes == kind)
            some = [p[at] for p in own]
            widths = [kind] if len(own) == 1 else [kind // 32, kind % 32]
            message = np.zeros((64, len(some[0])), np.uint8)
            message[: len(head)] = head[:, None]
            end = len(head)
            for j, (p, width) in enumerate(zip(some, widths, strict=True)):
                if j:
                    message[end] = ord(":")
                    end += 1
                left = p.copy()
                for place in range(end + width - 1, end - 1, -1):
                    tens = left // 10
                    message[place] = left - tens * 10 + 48
                    left = tens
                end += width
            message[end] = 0x80
            used = end // 4 + 1
            words = [message[4 * i].astype(np.uint32) | message[4 * i + 1].astype(np.uint32) << 8 | message[4 * i + 2].astype(np.uint32) << 16 | message[4 * i + 3].astype(np.uint32) << 24 for i in range(used)]
            words += [np.uint32(0)] * (14 - used) + [np.uint32(end * 8), np.uint32(0)]
            out[lo : lo + _ONCE][at] = _block(words)
    return out


def column(before: str, values: pa.Array) -> np.ndarray:
    """h60 of before + each value of an integer or string column without nulls; a text is hashed once for each batch."""
    if pa.types.is_integer(values.type):
        return numbers(before, values.to_numpy(zero_copy_only=False))
    coded = values.dictionary_encode()
    some = np.fromiter((h60_of(before + v) for v in coded.dictionary.to_pylist()), np.int64, len(coded.dictionary))
    return some[coded.indices.to_numpy(zero_copy_only=False)]
