"""Attribute prints, their vectors, Bloom masks, match expressions, and compression of prints."""

from __future__ import annotations

import datetime
import decimal

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..config import AttrSpec, Predicate, SketchSpec
from .hashing import h60, low

#: The print of a null attribute: no literal has it.
NULL_PRINT = -1
_INTS = (T.ByteType, T.ShortType, T.IntegerType, T.LongType)


def encode(df: DataFrame, name: str) -> Column:
    """The canonical value of a column: integers as they are, other types as text that every engine writes alike."""
    kind = df.schema[name].dataType
    col = F.col(name)
    if isinstance(kind, _INTS):
        return col.cast("bigint")
    if isinstance(kind, T.StringType):
        return col
    if isinstance(kind, T.BooleanType):
        return col.cast("int").cast("bigint")
    if isinstance(kind, T.DateType):
        return F.datediff(col, F.lit("1970-01-01").cast("date")).cast("bigint")
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(col)
    if isinstance(kind, T.DecimalType):
        return (col * F.lit(10**kind.scale)).cast("decimal(38,0)").cast("string")
    if isinstance(kind, (T.DoubleType, T.FloatType)):
        return F.when(F.isnan(col), F.lit("NaN")).otherwise((col + F.lit(0.0)).cast("string"))
    raise TypeError(f"no attribute prints for {kind.simpleString()}")


def literal(value) -> Column:
    """A literal in the form that `encode` gives its column."""
    if isinstance(value, bool):
        return F.lit(int(value)).cast("bigint")
    if isinstance(value, int):
        return F.lit(value).cast("bigint")
    if isinstance(value, datetime.date) and not isinstance(value, datetime.datetime):
        return F.lit((value - datetime.date(1970, 1, 1)).days).cast("bigint")
    if isinstance(value, decimal.Decimal):
        return F.lit(str(int(value.scaleb(-value.as_tuple().exponent))))
    if isinstance(value, float):
        return (F.lit(value) + F.lit(0.0)).cast("string")
    return F.lit(value)


def attr_print(value: Column, index: int, spec: SketchSpec, attr: AttrSpec) -> Column:
    hashed = low(h60(value, f"attr{index}", spec.salt, spec.hash_family), spec.attr_bits).cast("int")
    if attr.exact_ints:
        size = 1 << spec.attr_bits
        hashed = F.when((value >= 0) & (value < size), value.cast("int")).otherwise(hashed)
    return F.coalesce(hashed, F.lit(NULL_PRINT))


def vector(df: DataFrame, spec: SketchSpec) -> dict[str, Column]:
    """Columns a_0, a_1, ...: one print for each attribute."""
    return {f"a_{i}": attr_print(encode(df, a.name), i, spec, a) for i, a in enumerate(spec.attrs)}


def item_mask(value: Column, index: int, spec: SketchSpec, bits: int | None = None, hashes: int | None = None) -> Column:
    """The Bloom bits of one (attribute, value) item."""
    out = F.lit(0).cast("bigint")
    for j in range(hashes or spec.bloom_hashes):
        place = F.pmod(h60(F.concat(F.lit(f"{index}="), value.cast("string")), f"bloom{j}", spec.salt, spec.hash_family), F.lit(bits or spec.bloom_bits))
        out = out.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), place.cast("int")))
    return F.coalesce(out, F.lit(0).cast("bigint"))


def row_mask(df: DataFrame, spec: SketchSpec) -> Column:
    out = F.lit(0).cast("bigint")
    for i, a in enumerate(spec.attrs):
        out = out.bitwiseOR(item_mask(encode(df, a.name), i, spec))
    return out


def _indexed(pred: Predicate, spec: SketchSpec):
    names = [a.name for a in spec.attrs]
    for name, values in pred.allowed.items():
        if name in names:  # attributes outside the sketch are left to the own scan
            yield names.index(name), spec.attrs[names.index(name)], values


def match_vector(prints: list[Column], pred: Predicate, spec: SketchSpec) -> Column:
    """Whether a vector of prints may hold a matching row."""
    if pred.options:
        out = F.lit(False)
        for o in pred.options:
            out = out | match_vector(prints, o, spec)
        return out
    out = F.lit(True)
    for i, attr, values in _indexed(pred, spec):
        one = F.lit(False)
        for v in values:
            one = one | (prints[i] == attr_print(literal(v), i, spec, attr))
        out = out & one
    return out


def match_mask(mask: Column, pred: Predicate, spec: SketchSpec, bits: int | None = None, hashes: int | None = None, of_prints: bool = False) -> Column:
    """Whether a Bloom mask may hold all wanted items; `of_prints`: items are prints, as in converted entries."""
    if pred.options:
        out = F.lit(False)
        for o in pred.options:
            out = out | match_mask(mask, o, spec, bits, hashes, of_prints)
        return out
    out = F.lit(True)
    for i, attr, values in _indexed(pred, spec):
        one = F.lit(False)
        for v in values:
            value = attr_print(literal(v), i, spec, attr) if of_prints else literal(v)
            want = item_mask(value, i, spec, bits, hashes)
            one = one | (mask.bitwiseAND(want) == want)
        out = out & one
    return out


def compression_map(sketch: DataFrame, column: str, bits: int) -> DataFrame:
    """(print, short): long prints dealt to short codes so that the codes weigh alike; frequent prints are spread first.

    Reads one row for each distinct print, of which there are at most 2**attr_bits.
    """
    from pyspark.sql import Window

    counts = sketch.filter(F.col(column) != NULL_PRINT).groupBy(F.col(column).alias("print")).agg(F.count("*").alias("n"))
    rank = F.row_number().over(Window.orderBy(F.desc("n"), "print")) - 1
    size = 1 << bits
    turn, place = F.floor(rank / size), F.pmod(rank, F.lit(size))
    return counts.select("print", F.when(turn % 2 == 0, place).otherwise(size - 1 - place).cast("int").alias("short"))


def compress(sketch: DataFrame, columns: list[str], bits: int) -> DataFrame:
    """The sketch with shorter prints in the given columns; equal entries become one."""
    for c in columns:
        codes = compression_map(sketch, c, bits)
        sketch = sketch.join(F.broadcast(codes), sketch[c] == codes["print"], "left").drop("print").withColumn(c, F.coalesce("short", F.lit(NULL_PRINT))).drop("short")
    return sketch.distinct()
