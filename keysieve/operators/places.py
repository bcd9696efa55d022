"""Places, prints and masks of the portable hash family for whole Arrow batches.

The same numbers as the expressions of `functions.hashing` and `functions.attrs`; of a batch, each different value
is hashed once.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..config import SketchSpec
from ..functions import attrs as A
from ..functions import md5

_INTS = (T.ByteType, T.ShortType, T.IntegerType, T.LongType)
#: Widths of prints whose second buckets a task works out beforehand.
_TABLE_BITS = 14
#: Rows of a task among which the first of each group are found.
_TOGETHER = 1 << 17


def suits(df: DataFrame, spec: SketchSpec) -> bool:
    """Whether batches can be hashed: small numbers that are their own print have to be integers."""
    return spec.hash_family == "portable" and all(isinstance(df.schema[a.name].dataType, _INTS) for a in spec.attrs if a.exact_ints)


def _each(values: pa.Array, make) -> np.ndarray:
    """make(different values) for each row of a column; rows of nulls get what `make` gives the first value."""
    coded = values.dictionary_encode()
    if not len(coded.dictionary):
        return np.zeros(len(values), np.int64)
    return make(coded.dictionary)[coded.indices.fill_null(0).to_numpy(zero_copy_only=False)]


def hashed(keys: pa.Array, spec: SketchSpec) -> tuple[np.ndarray, np.ndarray]:
    """What the prints and the buckets of different keys are taken from, in specs of any widths and shapes."""
    return md5.column(f"key:{spec.salt}:", keys), md5.column(f"bucket:{spec.salt}:", keys)


def pairs_of(own: np.ndarray, bucket: np.ndarray, spec: SketchSpec, offsets: np.ndarray | None) -> list[np.ndarray]:
    """(pair_id, kappa) of hashed keys."""
    kappa, bucket = own & ((1 << spec.key_bits) - 1), bucket % spec.m
    offset = offsets[kappa] if offsets is not None else _offsets(kappa, spec)
    return [np.minimum(bucket, bucket ^ offset), kappa]


def _place(keys: pa.Array, spec: SketchSpec, offsets: np.ndarray | None) -> list[np.ndarray]:
    """(shard, pair_id, kappa) of different keys."""
    shard = md5.column(f"shard:{spec.salt}:", keys) % spec.shards if spec.shards > 1 else np.zeros(len(keys), np.int64)
    return [shard, *pairs_of(*hashed(keys, spec), spec, offsets)]


def offset_table(spec: SketchSpec) -> np.ndarray | None:
    """The distances of all prints' second buckets, where prints are short."""
    return _offsets(np.arange(1 << spec.key_bits), spec) if spec.key_bits <= _TABLE_BITS else None


def _offsets(kappa: np.ndarray, spec: SketchSpec) -> np.ndarray:
    return np.ones(len(kappa), np.int64) if spec.m == 2 else 1 + md5.numbers(f"pair:{spec.salt}:", kappa) % (spec.m - 1)


def prints(values: pa.Array, i: int, spec: SketchSpec, h60=md5.column) -> np.ndarray:
    """The prints of values of an attribute; `h60` hashes them, or knows the hashes."""
    out = h60(f"attr{i}:{spec.salt}:", values) & ((1 << spec.attr_bits) - 1)
    if spec.attrs[i].exact_ints:
        own = values.to_numpy(zero_copy_only=False)
        out = np.where((own >= 0) & (own < 1 << spec.attr_bits), own, out)
    return out


def mask(values: pa.Array, i: int, spec: SketchSpec, bits: int, hashes: int, h60=md5.column) -> np.ndarray:
    """The Bloom bits of (attribute, value) items."""
    out = np.zeros(len(values), np.int64)
    for j in range(hashes):
        out |= np.int64(1) << (h60(f"bloom{j}:{spec.salt}:{i}=", values) % bits)
    return out


def _least(table: pa.Table, most: int) -> pa.Table:
    """Different rows (shard, pair_id, kappa, prints), of each group only the first `most`."""
    group, vec = [table[c].to_numpy() for c in table.column_names[:3]], [table[c].to_numpy() for c in table.column_names[3:]]
    order = np.lexsort((*vec[::-1], *group))
    group, vec = [c[order] for c in group], [c[order] for c in vec]
    start, new = np.ones(len(order), bool), np.ones(len(order), bool)
    start[1:] = np.any([c[1:] != c[:-1] for c in group], axis=0)
    new[1:] = start[1:] | (np.any([c[1:] != c[:-1] for c in vec], axis=0) if vec else False)
    nth = new.cumsum()
    keep = new & (nth - np.maximum.accumulate(np.where(start, nth, 0)) < most)
    return pa.table([pa.array(c[keep]) for c in (*group, *vec)], names=table.column_names)


def placed(df: DataFrame, key: str, spec: SketchSpec, what: str | None = None, most: int | None = None) -> DataFrame:
    """The columns of df with shard, pair_id and kappa; or only these, with `prints` a_i or the `mask` of each row's attributes.

    Rows with a null key are dropped, as they join nothing. `most`: of a group, tasks leave out what is not among its
    first so many prints, and copies, so that what they send of a hot group is bounded.
    """
    rows = df.filter(F.col(key).isNotNull())
    named = F.col(key).cast("bigint" if isinstance(df.schema[key].dataType, _INTS) else "string").alias("__key")
    if what is None:
        rows, keep = rows.select("*", named), df.schema.names
    else:
        rows, keep = rows.select(named, *(A.encode(df, a.name).alias(f"__v{i}") for i, a in enumerate(spec.attrs))), []
    schema = [*([] if what else [f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema]), "shard int", "pair_id bigint", "kappa int"]
    names = [*keep, "shard", "pair_id", "kappa"]
    if what == "prints":
        more = [f"a_{i}" for i in range(len(spec.attrs))]
        names, schema = names + more, schema + [f"{c} int" for c in more]
    elif what == "mask":
        names, schema = [*names, "mask"], [*schema, "mask bigint"]

    def run(batches):
        offsets = offset_table(spec)
        for batch in batches:
            if not len(batch):
                continue
            coded = batch.column(batch.schema.get_field_index("__key")).dictionary_encode()
            at = coded.indices.to_numpy(zero_copy_only=False)
            shard, pair, kappa = (x[at] for x in _place(coded.dictionary, spec, offsets))
            out = [*(batch.column(batch.schema.get_field_index(c)) for c in keep), pa.array(shard.astype(np.int32)), pa.array(pair), pa.array(kappa.astype(np.int32))]
            masks = np.zeros(len(batch), np.int64)
            for i in range(len(spec.attrs) if what else 0):
                values = batch.column(batch.schema.get_field_index(f"__v{i}"))
                there = values.is_valid().to_numpy(zero_copy_only=False)
                if what == "prints":
                    own = _each(values, lambda x, i=i: prints(x, i, spec))
                    out.append(pa.array(np.where(there, own, A.NULL_PRINT).astype(np.int32)))
                else:
                    masks |= np.where(there, _each(values, lambda x, i=i: mask(x, i, spec, spec.bloom_bits, spec.bloom_hashes)), 0)
            if what == "mask":
                out.append(pa.array(masks))
            yield pa.RecordBatch.from_arrays(out, names)

    def few(batches):
        held, n = [], 0
        for batch in run(batches):
            held.append(batch)
            n += len(batch)
            if n >= _TOGETHER:
                yield from _least(pa.Table.from_batches(held), most).to_batches(_TOGETHER)
                held, n = [], 0
        if held:
            yield from _least(pa.Table.from_batches(held), most).to_batches(_TOGETHER)

    return rows.mapInArrow(run if most is None else few, ", ".join(schema))
