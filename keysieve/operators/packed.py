"""The packed form: buckets of entries with kicks, as NumPy arrays, for load factors, true sizes and compact copies.

Insertion is sequential by nature, so it runs for one shard or one experiment at a time inside an Arrow function.
A kick that does not end within `max_kicks` is rolled back, so no entry is ever lost, and the insert reports failure.
"""

from __future__ import annotations

import math

_M = (1 << 64) - 1


def mix(*parts: int) -> int:
    x = 0x9E3779B97F4A7C15
    for p in parts:
        x = (x ^ (p & _M)) * 0xBF58476D1CE4E5B9 & _M
        x ^= x >> 29
        x = x * 0x94D049BB133111EB & _M
        x ^= x >> 32
    return x


class Buckets:
    """m buckets of b slots; an entry is (print, payload)."""

    def __init__(self, m: int, b: int, key_bits: int = 12, salt: int = 0, max_kicks: int = 500):
        if m < 2 or m & (m - 1):
            raise ValueError("the number of buckets must be a power of two, at least 2")
        self.m, self.b, self.key_bits, self.salt, self.max_kicks = m, b, key_bits, salt, max_kicks
        self.slots: list[list] = [[] for _ in range(m)]
        self.filled, self.turn = 0, 0

    def print_of(self, key: int) -> int:
        return mix(key, 1, self.salt) & ((1 << self.key_bits) - 1)

    def first(self, key: int) -> int:
        return mix(key, 2, self.salt) % self.m

    def other(self, bucket: int, kappa: int) -> int:
        return bucket ^ (1 if self.m == 2 else 1 + mix(kappa, 3, self.salt) % (self.m - 1))

    def pair(self, bucket: int, kappa: int) -> tuple[int, int]:
        o = self.other(bucket, kappa)
        return min(bucket, o), max(bucket, o)

    def entries(self, pair: tuple[int, int], kappa: int) -> list:
        return [e[1] for p in dict.fromkeys(pair) for e in self.slots[p] if e[0] == kappa]

    def put(self, bucket: int, kappa: int, payload) -> bool:
        """Places an entry in its bucket or the other one, moving others along if both are full."""
        two = (bucket, self.other(bucket, kappa))
        for p in two:
            if len(self.slots[p]) < self.b:
                self.slots[p].append((kappa, payload))
                self.filled += 1
                return True
        at, entry, path = two[1], (kappa, payload), []
        for _ in range(self.max_kicks):
            self.turn += 1
            i = mix(self.turn, 5, self.salt) % self.b
            entry, self.slots[at][i] = self.slots[at][i], entry
            path.append((at, i))
            at = self.other(at, entry[0])
            if len(self.slots[at]) < self.b:
                self.slots[at].append(entry)
                self.filled += 1
                return True
        for at, i in reversed(path):  # everything goes back to where it was
            entry, self.slots[at][i] = self.slots[at][i], entry
        return False

    @property
    def load(self) -> float:
        return self.filled / (self.m * self.b)


class CuckooFilter(Buckets):
    """Prints of keys; copies may be inserted and deleted."""

    def insert(self, key: int) -> bool:
        return self.put(self.first(key), self.print_of(key), None)

    def contains(self, key: int) -> bool:
        k = self.print_of(key)
        return bool(self.entries(self.pair(self.first(key), k), k))

    def delete(self, key: int) -> bool:
        k = self.print_of(key)
        for p in self.pair(self.first(key), k):
            for i, e in enumerate(self.slots[p]):
                if e[0] == k:
                    del self.slots[p][i]
                    self.filled -= 1
                    return True
        return False


class PlainFilter(Buckets):
    """Prints with payload vectors, as many of one print as two buckets hold."""

    def insert(self, key: int, vector) -> bool:
        k = self.print_of(key)
        pair = self.pair(self.first(key), k)
        return vector in self.entries(pair, k) or self.put(self.first(key), k, vector)

    def contains(self, key: int, match=None) -> bool:
        k = self.print_of(key)
        found = self.entries(self.pair(self.first(key), k), k)
        return bool(found) if match is None else any(map(match, found))


class ChainedFilter(Buckets):
    """At most d of one print in a pair; more go along a chain of pairs, without end or up to l_max pairs."""

    def __init__(self, m: int, b: int, d: int = 3, l_max: int | None = None, **more):
        super().__init__(m, b, **more)
        self.d, self.l_max, self.discarded = d, l_max, 0

    def chain(self, bucket: int, kappa: int):
        """First buckets of the pairs of a chain; a pair seen before is replaced by another attempt's."""
        seen, n = set(), 0
        while self.l_max is None or n < self.l_max:
            pair = self.pair(bucket, kappa)
            seen.add(pair)
            yield bucket, pair
            n += 1
            for attempt in range(64):
                bucket = mix(pair[0], kappa, 4, attempt, self.salt) % self.m
                if self.pair(bucket, kappa) not in seen:
                    break
            else:
                return

    def insert(self, key: int, vector) -> bool:
        k = self.print_of(key)
        for bucket, pair in self.chain(self.first(key), k):
            found = self.entries(pair, k)
            if vector in found:
                return True
            if len(found) < self.d:
                return self.put(bucket, k, vector)
        self.discarded += 1
        return self.l_max is not None  # the saturated chain answers true from now on

    def contains(self, key: int, match=None) -> bool:
        k = self.print_of(key)
        for _, pair in self.chain(self.first(key), k):
            found = self.entries(pair, k)
            if match is None:
                return bool(found)
            if any(map(match, found)):
                return True
            if len(found) < self.d:
                return False
        return True


class PairFilter:
    """Entries of a pair table in buckets of b slots, for places that another hash family has told.

    An entry is (pair, print, payload, other bucket): a pair is named by its lower bucket. Entries go to the
    emptier bucket of their two, and others are moved along where both are full.
    """

    def __init__(self, m: int, b: int, d: int, entries: list[tuple], max_kicks: int = 500):
        self.b, self.d = b, d
        self.slots: list[list] = [[] for _ in range(m)]
        self.partner = {(p, k): o for p, k, _, o in entries}
        for pair, kappa, payload, other in entries:
            entry, at = (pair, kappa, payload), min((pair, other), key=lambda i: len(self.slots[i]))
            for turn in range(max_kicks):
                if len(self.slots[at]) < b:
                    self.slots[at].append(entry)
                    break
                i = mix(turn, at, 5) % b
                entry, self.slots[at][i] = self.slots[at][i], entry
                at = self.partner[entry[:2]] if at == entry[0] else entry[0]
            else:
                raise ValueError("the buckets are too few")

    def contains(self, chain, kappa: int, payload) -> bool:
        """Whether a key may occur with a payload, whose chain of pairs is given; a chain of full pairs answers true."""
        for pair in chain:
            other = self.partner.get((pair, kappa))
            held = [] if other is None else [e[2] for i in dict.fromkeys((pair, other)) for e in self.slots[i] if e[:2] == (pair, kappa)]
            if payload in held:
                return True
            if len(held) < self.d:
                return False
        return True


class CuckooMap(Buckets):
    """Full keys with values; doubles its buckets when an insert fails."""

    def print_of(self, key: int) -> int:
        return key

    def put_value(self, key: int, value) -> None:
        for p in self.pair(self.first(key), key):
            for i, e in enumerate(self.slots[p]):
                if e[0] == key:
                    self.slots[p][i] = (key, value)
                    return
        while not self.put(self.first(key), key, value):
            self.grow()

    def grow(self) -> None:
        old = [e for s in self.slots for e in s]
        m = self.m * 2
        while True:
            self.m, self.slots, self.filled = m, [[] for _ in range(m)], 0
            if all(self.put(self.first(k), k, v) for k, v in old):
                return
            m *= 2

    def get(self, key: int):
        found = self.entries(self.pair(self.first(key), key), key)
        return found[0] if found else None


class CuckooMultiMap(ChainedFilter):
    """Full keys with any number of values, by chains."""

    def print_of(self, key: int) -> int:
        return key

    def put_value(self, key: int, value) -> None:
        """A value more; the buckets double until all have a place."""
        while not self.insert(key, value):
            self.grow()

    def grow(self) -> None:
        old, m = [e for s in self.slots for e in s], self.m * 2
        while True:
            self.m, self.slots, self.filled = m, [[] for _ in range(m)], 0
            if all(self.insert(k, v) for k, v in old):
                return
            m *= 2

    def values(self, key: int) -> list:
        out = []
        for _, pair in self.chain(self.first(key), key):
            found = self.entries(pair, key)
            out += found
            if len(found) < self.d:
                break
        return out


class LinearProbe:
    """Open addressing by linear probing, with the places looked at."""

    def __init__(self, m: int):
        self.m, self.slots, self.n = m, [None] * m, 0

    def put(self, key: int) -> int:
        """The places looked at to insert a key."""
        at, probes = mix(key, 7) % self.m, 1
        while self.slots[at] is not None and self.slots[at] != key:
            at, probes = (at + 1) % self.m, probes + 1
        self.n += self.slots[at] is None
        self.slots[at] = key
        return probes


def semisort_encode(prints: list[int], key_bits: int) -> tuple[int, int, list[int]]:
    """A bucket of prints as the number of its sorted 4-bit prefixes among all multisets, and the remaining bits in that order."""
    ordered = sorted(prints)
    heads = [p >> (key_bits - 4) for p in ordered]
    code = sum(math.comb(h + i, i + 1) for i, h in enumerate(heads))
    return code, len(heads), [p & ((1 << (key_bits - 4)) - 1) for p in ordered]


def semisort_decode(code: int, n: int, rests: list[int], key_bits: int) -> list[int]:
    heads = []
    for i in range(n - 1, -1, -1):
        h = 15
        while math.comb(h + i, i + 1) > code:
            h -= 1
        code -= math.comb(h + i, i + 1)
        heads.append(h)
    return [h << (key_bits - 4) | r for h, r in zip(reversed(heads), rests, strict=True)]


def pack_mask(mask: int, lower: int, upper: int, kappa: int, key_bits: int, entry_bits: int, d: int) -> tuple[int, int]:
    """A mask over d entries in two buckets as two words: each occupied bucket has one print and count, the lower one the first bits."""
    head = key_bits + math.ceil(math.log2(max(2, d)))
    words, left = [], mask
    for n in (lower, upper):
        room = n * entry_bits - head if n else 0
        part, left = left & ((1 << room) - 1), left >> room
        words.append((part << head) | (n << key_bits) | kappa if n else 0)
    if left:
        raise ValueError("the mask is wider than its entries")
    return words[0], words[1]


def unpack_mask(words: tuple[int, int], key_bits: int, entry_bits: int, d: int) -> tuple[int, int, int, int]:
    """(mask, lower, upper, kappa) of two packed words."""
    head = key_bits + math.ceil(math.log2(max(2, d)))
    mask, shift, counts, kappa = 0, 0, [], 0
    for w in words:
        n = (w >> key_bits) & ((1 << (head - key_bits)) - 1) if w else 0
        counts.append(n)
        if n:
            kappa = w & ((1 << key_bits) - 1)
            mask |= (w >> head) << shift
            shift += n * entry_bits - head
    return mask, counts[0], counts[1], kappa
