"""What describes a sketch: its variant, widths, shape and hashing."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field, replace

VARIANTS = ("keyonly", "plain", "chained", "bloomattr", "hybrid")


@dataclass(frozen=True)
class AttrSpec:
    """An attribute column; `exact_ints` lets integers below 2**attr_bits be their own print."""

    name: str
    exact_ints: bool = False


@dataclass(frozen=True)
class SketchSpec:
    variant: str = "chained"
    attrs: tuple[AttrSpec, ...] = ()
    key_bits: int = 12
    attr_bits: int = 8
    bloom_bits: int = 24
    bloom_hashes: int = 4
    m: int = 8192
    b: int = 6
    d: int = 3
    l_max: int | None = 4
    shards: int = 1
    salt: int = 0
    hash_family: str = "xx"
    cycle_break: bool = False
    max_kicks: int = 500
    version: int = 1

    def __post_init__(self) -> None:
        if self.variant not in VARIANTS:
            raise ValueError(f"no such variant: {self.variant}")
        if self.m < 2 or self.m & (self.m - 1):
            raise ValueError("the number of buckets must be a power of two, at least 2")
        if not 1 <= self.d <= 2 * self.b:
            raise ValueError("a bucket pair must hold the copies of one print: 1 <= d <= 2b")
        if not (1 <= self.key_bits <= 30 and 1 <= self.attr_bits <= 30 and 1 <= self.bloom_bits <= 63):
            raise ValueError("a width is out of range")
        if self.hash_family not in ("xx", "portable"):
            raise ValueError("hash families are xx and portable")

    @property
    def vector_bits(self) -> int:
        return self.attr_bits * len(self.attrs)

    def with_(self, **changes) -> SketchSpec:
        return replace(self, **changes)

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    @staticmethod
    def from_json(text: str) -> SketchSpec:
        told = json.loads(text)
        told["attrs"] = tuple(AttrSpec(**a) for a in told["attrs"])
        return SketchSpec(**told)


#: The two sizes of the join workload: large has 12-bit keys, 8-bit attributes and 4 hashes; small 7, 4 and 2.
LARGE = SketchSpec(key_bits=12, attr_bits=8, bloom_bits=24, bloom_hashes=4)
SMALL = SketchSpec(key_bits=7, attr_bits=4, bloom_bits=12, bloom_hashes=2)


@dataclass(frozen=True)
class Predicate:
    """A conjunction over attributes, each with its allowed values; what a sketch cannot say stays in `residual` for the own scan.

    `options` holds further conjunctions: a row matches if it matches any of them.
    """

    allowed: dict = field(default_factory=dict)
    residual: str | None = None
    options: tuple = ()

    @staticmethod
    def eq(**values) -> Predicate:
        return Predicate({k: (v,) for k, v in values.items()})

    @staticmethod
    def isin(name: str, values) -> Predicate:
        return Predicate({name: tuple(values)})

    @staticmethod
    def between(name: str, low: int, high: int) -> Predicate:
        return Predicate({name: tuple(range(low, high + 1))})

    @staticmethod
    def any_of(*options: Predicate) -> Predicate:
        return Predicate(options=tuple(options))

    def and_residual(self, sql: str) -> Predicate:
        return replace(self, residual=sql if self.residual is None else f"({self.residual}) AND ({sql})")

    def and_(self, other: Predicate) -> Predicate:
        if self.options or other.options:
            raise ValueError("conjunctions of alternatives are not supported")
        both = dict(self.allowed)
        for k, v in other.allowed.items():
            both[k] = tuple(x for x in both[k] if x in v) if k in both else v
        parts = [r for r in (self.residual, other.residual) if r]
        return Predicate(both, " AND ".join(f"({r})" for r in parts) or None)
