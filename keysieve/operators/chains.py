"""Chains of prints, in NumPy: rounds of a build, and what a probe that starts at a group sees.

A chain never leaves its print, so a call needs all pairs of its (shard, print) and no others. A pair is told by its
slot: the number of its (shard, print) in the call times m, plus the pair. Places of chains are MD5 ones
(`portable`), and chains have no cycle breaking; others stay with Spark's expressions.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from ..config import SketchSpec
from ..functions import md5

#: Rows that are taken together, but for a print that has more.
ROWS = 1 << 17


def suits(spec: SketchSpec) -> bool:
    return spec.hash_family == "portable" and not spec.cycle_break and spec.l_max is not None


def by_prints(batches: Iterator[pa.RecordBatch], by: tuple[str, ...] = ("shard", "kappa")) -> Iterator[pa.Table]:
    """Rows that come sorted by (shard, kappa), in tables that hold whole prints."""
    held, n = [], 0
    for batch in batches:
        if not len(batch):
            continue
        if n >= ROWS:
            last = held[-1]
            same = np.all([batch.column(c).to_numpy() == last[c][-1].as_py() for c in by], axis=0)
            cut = int(np.argmin(same)) if not same.all() else len(batch)
            if cut:
                held.append(batch.slice(0, cut))
            if cut == len(batch):
                n += cut
                continue
            yield pa.Table.from_batches(held)
            batch, held, n = batch.slice(cut), [], 0
        held.append(batch)
        n += len(batch)
    if held:
        yield pa.Table.from_batches(held)


def homes(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The number of each row's (shard, print), and the shard and print of each number."""
    shard, kappa = (table[c].to_numpy() for c in ("shard", "kappa"))
    first = np.ones(len(shard), bool)
    first[1:] = (shard[1:] != shard[:-1]) | (kappa[1:] != kappa[:-1])
    return first.cumsum() - 1, shard[first], kappa[first]


def following(slots: np.ndarray, kappas: np.ndarray, spec: SketchSpec) -> np.ndarray:
    """The slot after each one in the chains of its print."""
    some, back = np.unique(slots, return_inverse=True)
    home, pair = some // spec.m, some % spec.m
    offset = np.ones(len(kappas), np.int64) if spec.m == 2 else 1 + md5.numbers(f"pair:{spec.salt}:", kappas) % (spec.m - 1)
    first = md5.numbers(f"chain:{spec.salt}:", pair, kappas[home]) % spec.m
    return (home * spec.m + np.minimum(first, first ^ offset[home]))[back]


class Onward:
    """`following` for the prints and the shape of one call, each slot hashed once, whoever comes by."""

    def __init__(self, kappas: np.ndarray, spec: SketchSpec) -> None:
        self.kappas, self.spec = kappas, spec
        self.slots = self.next = np.zeros(0, np.int64)

    def __call__(self, slots: np.ndarray) -> np.ndarray:
        some = different(slots)
        if len(self.slots):
            at = np.minimum(np.searchsorted(self.slots, some), len(self.slots) - 1)
            new = some[self.slots[at] != some]
        else:
            new = some
        if len(new):
            self.next = np.r_[self.next, following(new, self.kappas, self.spec)]
            self.slots = np.r_[self.slots, new]
            order = np.argsort(self.slots, kind="stable")
            self.slots, self.next = self.slots[order], self.next[order]
        return self.next[np.searchsorted(self.slots, slots)]


def _ranked(pair: np.ndarray, code: np.ndarray, late: np.ndarray):
    """Distinct (pair, code) with the least late, by pair, late and code, and the place of each in its pair."""
    order = np.lexsort((late, code, pair))
    pair, code, late = pair[order], code[order], late[order]
    first = np.ones(len(pair), bool)
    first[1:] = (pair[1:] != pair[:-1]) | (code[1:] != code[:-1])
    pair, code, late = pair[first], code[first], late[first]
    order = np.lexsort((code, late, pair))
    pair, code, late = pair[order], code[order], late[order]
    at = np.arange(len(pair))
    starts = np.ones(len(pair), bool)
    starts[1:] = pair[1:] != pair[:-1]
    return pair, code, late, at - np.maximum.accumulate(np.where(starts, at, 0))


def settled(pair: np.ndarray, code: np.ndarray, late: np.ndarray, kappas: np.ndarray, spec: SketchSpec, onward: Onward | None = None):
    """(slot, code, late) of vectors at slots after all rounds: late = 0 for entries, 1 for what found no place, at its last pair.

    A pair keeps at most d vectors: those that are there, then the least arrivals; others go to the next pair.
    """
    if len(pair) and late.all():
        least = int(code.min())
        size = int(code.max()) - least + 1
        if len(kappas) * spec.m * size < 1 << 62:
            slot, code, late = _settled_as_numbers(pair, code - least, size, spec, onward or Onward(kappas, spec))
            return slot, code + least, late
    for hop in range(spec.l_max):
        pair, code, late, rank = _ranked(pair, code, late)
        over = rank >= spec.d
        late = over.astype(np.int64)
        if hop + 1 == spec.l_max or not over.any():
            break
        pair[over] = following(pair[over], kappas, spec)
    return pair, code, late


def _settled_as_numbers(pair: np.ndarray, code: np.ndarray, size: int, spec: SketchSpec, onward: Onward):
    """The same for vectors all of which arrive, with codes below `size`: (slot, code) is one number, and a round looks at what moves alone."""
    held, come = np.zeros(0, np.int64), different(pair * size + code)
    for hop in range(spec.l_max):
        if len(held):
            at = np.minimum(np.searchsorted(held, come), len(held) - 1)
            come = come[held[at] != come]
        to = come // size
        first = np.flatnonzero(np.r_[True, to[1:] != to[:-1]]) if len(to) else np.zeros(0, np.int64)
        many = np.diff(np.r_[first, len(to)])
        there = np.searchsorted(held, (to[first] + 1) * size) - np.searchsorted(held, to[first] * size)
        stays = np.arange(len(to)) - np.repeat(first - there, many) < spec.d
        held = np.sort(np.r_[held, come[stays]], kind="stable")
        to, come = to[~stays], come[~stays]
        if hop + 1 == spec.l_max or not len(come):
            break
        come = different(onward(to) * size + come % size)
    every = np.r_[held, come]
    return every // size, every % size, np.repeat([0, 1], [len(held), len(come)])


def different(numbers: np.ndarray) -> np.ndarray:
    """Different numbers, in order."""
    numbers = np.sort(numbers)
    return numbers[np.r_[True, numbers[1:] != numbers[:-1]]] if len(numbers) else numbers


def coded(found: list[tuple[dict, tuple]]) -> list[tuple]:
    """Tables (codes in order, masks, places) of masks of vectors by their prints in some places."""
    tables = []
    for masks, at in found:
        codes = np.array([sum(c << 31 * i for i, c in enumerate(code)) for code in masks if min(code) >= 0], np.int64)
        order = codes.argsort()
        tables.append((codes[order], [np.array([m[h] for code, m in masks.items() if min(code) >= 0], np.int64)[order] for h in (0, 1)], at))
    return tables


def met(held: list[np.ndarray], n: int, tables: list[tuple]) -> list[np.ndarray]:
    """The masks of n vectors with the prints `held`."""
    own = [np.zeros(n, np.int64) for _ in (0, 1)]
    for codes, masks, at in tables:
        if not len(codes):
            continue
        if len(at) == 1 and codes[-1] < 1 << 16:  # short prints: the last place is for all others, and for null
            code = held[at[0]]
            code = np.where((code < 0) | (code > codes[-1]), codes[-1] + 1, code)
            for o, m in zip(own, masks, strict=True):
                told = np.zeros(codes[-1] + 2, np.int64)
                told[codes] = m
                o |= told[code]
            continue
        code = sum(held[p].astype(np.int64) << 31 * i for i, p in enumerate(at))
        place = np.minimum(np.searchsorted(codes, code), len(codes) - 1)
        hit = (codes[place] == code) & np.all([held[p] >= 0 for p in at], axis=0)
        for o, m in zip(own, masks, strict=True):
            o |= np.where(hit, m[place], 0)
    return own


def closed(slot: np.ndarray, own: list[np.ndarray], always: tuple[int, int], kappas: np.ndarray, spec: SketchSpec, onward: Onward | None = None):
    """(slots, masks) of entries in order of their slots, joined along the chains; a saturated chain has the masks `always`."""
    if not len(slot):
        return slot, own
    starts = np.flatnonzero(np.r_[True, slot[1:] != slot[:-1]])
    full = np.diff(np.r_[starts, len(slot)]) >= spec.d
    slot, out, saturated = walked(slot[starts], full, [np.bitwise_or.reduceat(o, starts) for o in own], kappas, spec, onward)
    return slot, [np.where(saturated, m, o) for m, o in zip(always, out, strict=True)]


def walked(pair: np.ndarray, full: np.ndarray, masks: list[np.ndarray], kappas: np.ndarray, spec: SketchSpec, onward: Onward | None = None):
    """Slots of groups, the masks of each joined with those along its chain, and whether all pairs of the chain are full."""
    onward = onward or Onward(kappas, spec)
    order = np.argsort(pair)
    pair, full, own = pair[order], full[order], [m[order] for m in masks]
    out, at, going = [m.copy() for m in own], pair.copy(), np.flatnonzero(full)
    for _ in range(1, spec.l_max):
        if not len(going):
            break
        at[going] = onward(at[going])
        there = np.minimum(np.searchsorted(pair, at[going]), len(pair) - 1)
        found = pair[there] == at[going]
        going, there = going[found], there[found]
        for m, o in zip(out, own, strict=True):
            m[going] |= o[there]
        going = going[full[there]]
    saturated = np.zeros(len(pair), bool)
    saturated[going] = True
    return pair, out, saturated
