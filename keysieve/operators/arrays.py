"""Sketches of every variant in NumPy, where all keys of some prints are at hand: entries, and the queries they meet.

The same entries as those of `pairs`. A group is told by its slot, as in `chains`: the number of its print in the
call times m, plus the pair.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from ..config import SketchSpec
from . import chains
from .pairs import hybrid_bits, hybrid_hashes
from .places import mask


@dataclass
class Asked:
    """Literals of a workload: masks of queries by prints (`chains.coded`), by Bloom bits, and of all that ask this sketch."""

    by_prints: list[tuple]
    by_bits: list[tuple[int, tuple[int, int]]]
    always: tuple[int, int]


def _groups(slot: np.ndarray) -> np.ndarray:
    """Where groups begin in slots that are in order."""
    return np.flatnonzero(np.r_[True, slot[1:] != slot[:-1]]) if len(slot) else np.zeros(0, np.int64)


def _coded(prints: list[np.ndarray], n: int, spec: SketchSpec):
    """Vectors of prints as numbers below a bound, in the order of the vectors, and a function from these to prints."""
    own = (1 << spec.attr_bits) + 1
    size = own ** len(prints)
    if size >= 1 << 62:
        names, code = np.unique(np.stack(prints, axis=1), axis=0, return_inverse=True)
        return code.reshape(-1), max(1, len(names)), lambda c: [names[c, i] for i in range(len(prints))]
    code = np.zeros(n, np.int64)
    for p in prints:
        code = code * own + p + 1
    return code, size, lambda c: [c // own ** (len(prints) - 1 - i) % own - 1 for i in range(len(prints))]


def vectors(slot: np.ndarray, prints: list[np.ndarray], slots: int, spec: SketchSpec) -> tuple[np.ndarray, list[np.ndarray]]:
    """Distinct (slot, prints) in order; all slots are below `slots`."""
    code, size, told = _coded(prints, len(slot), spec)
    if slots * size < 1 << 62:
        number = chains.different(slot * size + code)
        return number // size, told(number % size)
    (places, at), (codes, of) = (np.unique(x, return_inverse=True) for x in (slot, code))
    number = chains.different(at.reshape(-1) * len(codes) + of.reshape(-1))
    return places[number // max(1, len(codes))], told(codes[number % max(1, len(codes))])


def chained_entries(slot: np.ndarray, prints: list[np.ndarray], kappas: np.ndarray, spec: SketchSpec, onward: chains.Onward | None = None) -> tuple[np.ndarray, list[np.ndarray]]:
    """(slots, prints) of what has a place after all rounds."""
    code, _, told = _coded(prints, len(slot), spec)
    slot, code, late = chains.settled(slot, code, np.ones(len(slot), np.int64), kappas, spec, onward)
    return slot[late == 0], told(code[late == 0])


def bloom_entries(slot: np.ndarray, masks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(slots, masks) of groups."""
    order = np.argsort(slot)
    slot, masks = slot[order], masks[order]
    starts = _groups(slot)
    return slot[starts], np.bitwise_or.reduceat(masks, starts) if len(starts) else masks


def print_masks(prints: list[np.ndarray], n: int, spec: SketchSpec) -> np.ndarray:
    """The masks over (place, print) items of n vectors."""
    import pyarrow as pa

    out = np.zeros(n, np.int64)
    for i, p in enumerate(prints):
        some, back = np.unique(p, return_inverse=True)
        own = mask(pa.array(some), i, spec, hybrid_bits(spec), hybrid_hashes(spec))
        out |= np.where(some < 0, 0, own)[back.reshape(-1)]
    return out


def _met_by_bits(masks: np.ndarray, asked: Asked) -> list[np.ndarray]:
    out = [np.zeros(len(masks), np.int64) for _ in (0, 1)]
    for w, queries in asked.by_bits:
        hit = -((masks & w) == w).astype(np.int64)  # all bits or none
        for o, q in zip(out, queries, strict=True):
            if q:
                o |= hit & q
    return out


def live(slot: np.ndarray, prints: list[np.ndarray], masks: np.ndarray | None, asked: Asked, kappas: np.ndarray, spec: SketchSpec, onward: chains.Onward | None = None) -> tuple[np.ndarray, list[np.ndarray]]:
    """(slots, masks of queries) of the groups of the sketch of rows with these prints, or Bloom masks, at these slots."""
    if spec.variant == "bloomattr":
        slot, masks = bloom_entries(slot, masks)
        return slot, _met_by_bits(masks, asked)
    if spec.variant == "chained":
        slot, prints = chained_entries(slot, prints, kappas, spec, onward)
        return chains.closed(slot, chains.met(prints, len(slot), asked.by_prints), asked.always, kappas, spec, onward)
    slot, prints = vectors(slot, prints, len(kappas) * spec.m, spec)
    own, starts = chains.met(prints, len(slot), asked.by_prints), _groups(slot)
    if not len(starts):
        return slot, own
    out = [np.bitwise_or.reduceat(o, starts) for o in own]
    if spec.variant == "hybrid":
        many = np.diff(np.r_[starts, len(slot)]) > spec.d
        of = np.repeat(many, np.diff(np.r_[starts, len(slot)]))
        masks = print_masks([p[of] for p in prints], int(of.sum()), spec)
        if len(masks):
            by_bits = _met_by_bits(np.bitwise_or.reduceat(masks, _groups(slot[of])), asked)
            for o, m in zip(out, by_bits, strict=True):
                o[many] = m
    return slot[starts], out
