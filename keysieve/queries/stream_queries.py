"""Queries on streams and on sketches as SQL functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from ..config import LARGE, Predicate
from ..functions.attrs import row_mask
from ..functions.hashing import locate
from ..operators import pairs as P
from ..operators import probe as R
from ..operators import udfs as U
from ..sources import tables as S
from ..streaming import streams as ST
from ..workloads.fixtures import relation, relation_sql, spec_for
from . import sql as Q
from .registry import Registry

reg = Registry()
BASE = LARGE.with_(hash_family="portable", m=8192)
_DAY = "cast(epoch(date_trunc('day', ts)) as bigint)"


@reg.add("stream_tumbling", f"select {_DAY} as start, event_type, count(*) as n from events group by all")
def stream_tumbling(spark, d):
    return ST.drained(ST.windowed(ST.source(spark, d), "1 day", None), "complete")


@reg.add("stream_sliding", f"select {_DAY} - 86400 * o as start, event_type, count(*) as n from events, (values (0), (1)) t(o) group by all")
def stream_sliding(spark, d):
    return ST.drained(ST.windowed(ST.source(spark, d), "2 days", "1 day"), "complete")


@reg.add(
    "stream_session",
    "with e as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) <= interval 6 hours then 0 else 1 end as fresh from events), s as (select *, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as g from e) "
    "select user_id, cast(floor(epoch(min(ts))) as bigint) as start, count(*) as n from s group by user_id, g",
)
def stream_session(spark, d):
    return ST.drained(ST.sessions(ST.source(spark, d), "6 hours"), "complete")


@reg.add("stream_dedup", "select distinct user_id, event_type from events")
def stream_dedup(spark, d):
    return ST.drained(ST.dedup(ST.source(spark, d), ["user_id", "event_type"]), "append")


CUST = spec_for("cust", BASE, variant="chained", l_max=1)
BUILDING = {"segment": ("BUILDING",)}
_CUST_LIVE = f"{Q.chained(relation_sql('cust'), CUST)}, {Q.closed(CUST)}, {Q.live_chained(BUILDING, CUST)}"


@reg.add("stream_sketch_filter", f"with {_CUST_LIVE} {Q.probe('select user_id as k, event_id from events', CUST, 'event_id')}")
def stream_sketch_filter(spark, d):
    """Events of customers of one segment, by the customers' sketch."""
    live = R.derive_key_filter(P.build_chained(relation(spark, d, "cust"), "k", CUST), Predicate(BUILDING))
    return ST.drained(ST.filter_by(ST.source(spark, d).select("event_id", "user_id"), "user_id", live, CUST).select("event_id"), "append")


@reg.add("stream_join", "select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 1 day")
def stream_join(spark, d):
    return ST.drained(ST.interval_join(ST.source(spark, d), ST.source(spark, d), 1), "append")


EVB = spec_for("ev", BASE, variant="bloomattr", m=256)


@reg.add("stream_final_equals_batch", f"with {Q.bloom(relation_sql('ev'), EVB)} select 0::bigint as differences, count(*) as entries from entries")
def stream_final_equals_batch(spark, d):
    """A sketch kept up over four micro-batches against the one built at once."""
    path = S.shared_dir(spark)
    relation(spark, d, "ev").repartition(4, "k").write.parquet(f"{path}/in.parquet")
    kept = ST.maintain(ST.source(spark, path, "in", files=1), "k", EVB)
    batch = P.build_bloomattr(relation(spark, d, "ev"), "k", EVB).entries.select(*kept.columns)
    odd = kept.exceptAll(batch).unionByName(batch.exceptAll(kept)).agg(F.count("*").alias("differences"))
    return odd.crossJoin(kept.agg(F.count("*").alias("entries")))


# --- functions

DISC = spec_for("disc", BASE, variant="chained", l_max=3)
DISC4 = {"disc": (4,)}
_LIVE = f"{Q.chained(relation_sql('disc'), DISC)}, {Q.closed(DISC)}, {Q.live_chained(DISC4, DISC)}"
ORDERS = "select o_orderkey as k from orders"


def _live(spark, d):
    return R.derive_key_filter(P.build_chained(relation(spark, d, "disc"), "k", DISC), Predicate(DISC4))


def _orders(spark, d):
    return locate(S.table(spark, d, "orders", ["o_orderkey"]).withColumnRenamed("o_orderkey", "k"), "k", DISC)


@reg.add("udf_contains", f"with {_LIVE} {Q.probe(ORDERS, DISC)}")
def udf_contains(spark, d):
    """The probe as a vectorised function over packed groups; too many groups go to the semi join."""
    live, rows = _live(spark, d), _orders(spark, d)
    groups = U.packed_groups(live)
    if groups is None:
        return rows.join(live, P.GROUP, "left_semi").select("k")
    return rows.filter(U.contains_udf(spark, groups)("pair_id", "kappa")).select("k")


SUPP = spec_for("supp", BASE, variant="bloomattr")


@reg.add("udaf_build", f"select k % 10 as g, bit_or({Q.mask([(0, 'supp'), (1, 'lstatus')], SUPP)}) as mask from ({relation_sql('supp')}) group by all")
def udaf_build(spark, d):
    rows = relation(spark, d, "supp")
    return rows.select((F.col("k") % 10).alias("g"), row_mask(rows, SUPP).alias("m")).groupBy("g").agg(U.paf_mask("m").alias("mask"))


@reg.add("udtf_entries", f"with {_LIVE} select distinct pair_id, cast(kappa as int) as kappa from live")
def udtf_entries(spark, d):
    """Live groups packed for each block of pairs, and unpacked by a table function."""
    spark.udtf.register("paf_entries", U.EntriesOf)
    code = F.shiftleft(F.col("pair_id").cast("bigint"), 32) + F.col("kappa")

    @F.pandas_udf("binary")
    def pack(g: pd.Series) -> bytes:
        return np.sort(g.to_numpy()).astype("<i8").tobytes()

    packed = _live(spark, d).select(F.pmod("pair_id", F.lit(16)).alias("block"), code.alias("g")).groupBy("block").agg(pack("g").alias("blob"))
    packed.createOrReplaceTempView("paf_blobs")
    return spark.sql("select e.pair_id, e.kappa from paf_blobs b, lateral paf_entries(b.blob) e")


@reg.add("sql_surface", f"with {_LIVE} {Q.probe(ORDERS, DISC)}")
def sql_surface(spark, d):
    condition = U.register(spark, "live_disc4", _live(spark, d))
    return spark.sql(f"select p.k from {{rows}} p where {condition}", rows=_orders(spark, d))
