"""Relations of the experiments: table, key and attribute expressions that Spark and DuckDB read alike."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import AttrSpec, SketchSpec
from ..sources.tables import table

MONTH = "((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1)"
BIN16 = f"cast(floor({MONTH} / 5) as bigint)"

#: name -> (table, key, {attribute: expression}, attributes that are small integers)
FIXTURES: dict[str, tuple[str, str, dict[str, str], tuple[str, ...]]] = {
    "hdr": ("orders", "o_orderkey", {"status": "o_orderstatus", "bin": BIN16}, ("bin",)),
    "disc": ("lineitem", "l_orderkey", {"disc": "cast(round(l_discount * 100) as bigint)"}, ("disc",)),
    "supp": ("lineitem", "l_orderkey", {"supp": "l_suppkey", "lstatus": "l_linestatus"}, ("supp",)),
    "qty": ("lineitem", "l_orderkey", {"qty": "cast(l_quantity as bigint)"}, ("qty",)),
    "line": ("lineitem", "l_orderkey", {"line": "cast(l_linenumber as bigint)"}, ("line",)),
    "part": ("lineitem", "l_orderkey", {"part": "l_partkey"}, ("part",)),
    "flag": ("lineitem", "l_orderkey", {"flag": "l_returnflag"}, ()),
    "ps": ("lineitem", "l_partkey", {"supp": "l_suppkey"}, ()),
    "sp": ("lineitem", "l_suppkey", {"part": "l_partkey"}, ()),
    "cust": ("customer", "c_custkey", {"segment": "c_mktsegment", "nation": "cast(c_nationkey as bigint)"}, ("nation",)),
    "co": ("orders", "o_custkey", {"status": "o_orderstatus", "priority": "o_orderpriority", "year": "cast(year(o_orderdate) as bigint)"}, ()),
    "ev": ("events", "user_id", {"kind": "event_type", "day": "cast(day(ts) as bigint)"}, ("day",)),
    "prt": ("part", "p_partkey", {"brand": "p_brand", "size": "cast(p_size as bigint)"}, ("size",)),
    "sup": ("supplier", "s_suppkey", {"nation": "cast(s_nationkey as bigint)"}, ("nation",)),
    "doc": ("documents", "doc_id", {"lang": "lang", "source": "source"}, ()),
    "lab": ("labels", "doc_id", {"quality": "cast(quality as bigint)", "toxic": "cast(toxic as bigint)"}, ("quality", "toxic")),
    "conv": ("conversations", "conv_id", {"role": "role"}, ()),
}


def relation(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(k, attributes) of a fixture; the scan reads only the columns that they need."""
    source, key, attrs, _ = FIXTURES[name]
    return table(spark, sf_dir, source).select(F.expr(key).alias("k"), *(F.expr(e).alias(a) for a, e in attrs.items()))


def relation_sql(name: str) -> str:
    source, key, attrs, _ = FIXTURES[name]
    return f"select {key} as k, " + ", ".join(f"{e} as {a}" for a, e in attrs.items()) + f" from {source}"


def spec_for(name: str, base: SketchSpec, small_values: bool = False, only: tuple[str, ...] | None = None, **changes) -> SketchSpec:
    _, _, attrs, ints = FIXTURES[name]
    own = tuple(AttrSpec(a, small_values and a in ints) for a in attrs if only is None or a in only)
    return base.with_(attrs=own, **changes)
