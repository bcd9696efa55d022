"""What sketches are compared with: local predicates, exact semi joins, key-only filters, prebuilt Bloom filters."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import SketchSpec
from ..functions.hashing import h60
from ..plans import star
from . import probe as R
from .pairs import build_keyonly


def predicate_rows(query: star.StarQuery) -> DataFrame:
    """Rows that each relation's own predicate leaves."""
    return star.counts({r.name: r.scan() for r in query.relations}, "m_pred")


def exact_semijoin(query: star.StarQuery) -> DataFrame:
    return star.counts(star.exact_semijoin(query), "m_exact")


def exact_binned(name: str, rows: DataFrame, binned: DataFrame) -> DataFrame:
    """Rows whose key is in the other relation under its binned range."""
    return star.counts({name: rows.join(binned.select("k").distinct(), "k", "left_semi")}, "m_binned")


def _reduced(query: star.StarQuery, live: dict, name: str) -> DataFrame:
    out = {}
    for r in query.relations:
        rows = r.scan()
        for other in query.relations:
            if other.name != r.name:
                rows = R.semi(rows, "k", *live[other.name])
        out[r.name] = rows
    return star.counts(out, name)


def keyonly(query: star.StarQuery, spec: SketchSpec) -> DataFrame:
    """Key-only filters of all relations, which ignore predicates."""
    only = spec.with_(variant="keyonly")
    return _reduced(query, {r.name: (build_keyonly(r.rows, "k", only).entries, only) for r in query.relations}, "m_keyonly")


def without_predicates(query: star.StarQuery, catalog: star.SketchCatalog) -> DataFrame:
    """The catalog's sketches asked for keys alone."""
    first = {r.name: catalog.sketches[r.name][0] for r in query.relations}
    return _reduced(query, {n: (R.first_groups(s), s.spec) for n, s in first.items()}, "m_nopred")


def _places(key: str, bits: int, hashes: int, family: str):
    return F.array(*(F.pmod(h60(key, f"filter{j}", 0, family), F.lit(bits)) for j in range(hashes)))


def bloom_build(df: DataFrame, key: str, bits: int, hashes: int, family: str = "xx") -> DataFrame:
    """(word, mask): the words of a Bloom filter that have a bit set, at most bits / 32 rows."""
    place = df.filter(F.col(key).isNotNull()).select(key).distinct().select(F.explode(_places(key, bits, hashes, family)).alias("b"))
    one = F.call_function("shiftleft", F.lit(1).cast("bigint"), F.pmod("b", F.lit(32)).cast("int"))
    return place.groupBy(F.shiftright("b", 5).alias("word")).agg(F.bit_or(one).alias("mask"))


def bloom_probe(df: DataFrame, key: str, words: DataFrame, bits: int, hashes: int, family: str = "xx") -> DataFrame:
    """Keys all of whose places are set."""
    asked = df.select(key, F.explode(_places(key, bits, hashes, family)).alias("b")).withColumns({"word": F.shiftright("b", 5), "bit": F.pmod("b", F.lit(32)).cast("int")})
    met = asked.join(words, "word", "left")
    set_ = F.coalesce(F.shiftrightunsigned(F.col("mask"), 0).bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("bit"))) != 0, F.lit(False))
    return met.groupBy(key).agg(F.min(set_).alias("all_set")).filter("all_set").select(key)


def per_value(df: DataFrame, key: str, attrs: list[str]) -> DataFrame:
    """Keys that a filter of each value combination would hold; the number of filters is the product of cardinalities."""
    return df.select(key, *attrs).distinct().groupBy(*attrs).agg(F.count("*").alias("n_keys"))


def raw_bits(rows: int, high: int, low: int, load: float = 0.75) -> float:
    """Bits of a hash table over 32-bit keys and high-cardinality columns and 8-bit low-cardinality columns."""
    return rows * (32 + 32 * high + 8 * low) / load


def engine_bloom(query: star.StarQuery) -> DataFrame:
    """The join with a Bloom filter that is built of the first relation's rows while the query runs and probed by the others.

    It has the form of the filter that the engine injects by itself where its thresholds allow (bench.py times that
    one): no stored sketch, one filter for a join, and nothing of the other relations' predicates.
    """
    first, *rest = query.relations
    out = first.scan()
    words = bloom_build(out, "k", 1 << 20, 3)
    for r in rest:
        met = bloom_probe(r.scan().select("k").distinct(), "k", words, 1 << 20, 3)
        own = r.scan().join(met, "k", "left_semi")
        out = out.join(own.select("k", *(F.col(c).alias(f"{r.name}_{c}") for c in own.columns if c != "k")), "k")
    names = [c for c in first.rows.columns if c != "k"]
    return out.select("k", *(F.col(c).alias(f"{first.name}_{c}") for c in names), *(c for c in out.columns if c != "k" and c not in names))
