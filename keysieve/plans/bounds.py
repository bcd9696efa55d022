"""Closed forms: sizes, false positive bounds, bits per item."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..config import SketchSpec

#: Bits per item of an optimal Bloom filter per bit of log2(1/rho), and what cuckoo filters add.
BLOOM_FACTOR, CUCKOO_EXTRA, SORTED_EXTRA = 1 / math.log(2), 3, 2


def key_only(entries: float, key_bits: int) -> float:
    return min(1.0, entries * 2.0**-key_bits)


def bloom_rate(bits: int, hashes: int, items: float) -> float:
    return (1 - (1 - 1 / bits) ** (hashes * items)) ** hashes


def bloom(bits: int, hashes: int, items: float, missing: int) -> float:
    return bloom_rate(bits, hashes, items) ** missing


def vector(entries: float, attr_bits: int, missing: int) -> float:
    return min(1.0, entries * 2.0 ** (-attr_bits * missing))


def bits_per_item(kind: str, rho: float, beta: float) -> float:
    x = math.log2(1 / rho)
    if kind == "bloom":
        return BLOOM_FACTOR * x
    return (x + (CUCKOO_EXTRA if kind == "cuckoo" else SORTED_EXTRA)) / beta


def efficiency(kind: str, rho: float, beta: float) -> float:
    return bits_per_item(kind, rho, beta) / math.log2(1 / rho)


def expected_output(true_rows: float, rows: float, fpr: float) -> float:
    return true_rows + fpr * (rows - true_rows)


def linear_probing_cost(beta: float) -> float:
    return 1 + 1 / (1 - beta) ** 2


def entry_bits(spec: SketchSpec, marked: bool = False) -> int:
    payload = {"keyonly": 0, "plain": spec.vector_bits, "chained": spec.vector_bits, "bloomattr": spec.bloom_bits, "hybrid": spec.vector_bits + 1}[spec.variant]
    return spec.key_bits + payload + marked


def size_bits(spec: SketchSpec, marked: bool = False) -> int:
    return spec.m * spec.b * entry_bits(spec, marked)


def bloom_hashes(bits: int, items: float) -> int:
    """The best number of hashes for so many items, at least 1."""
    return max(1, round(bits / max(items, 1e-9) * math.log(2)))


def bloom_hashes_of(bits: Column, items: Column) -> Column:
    """The same for columns."""
    return F.greatest(F.lit(1), F.round(bits / items * math.log(2)).cast("int"))
