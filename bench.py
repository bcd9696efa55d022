"""Times the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS] and prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keysieve.config import LARGE, Predicate
from keysieve.operators import pairs as P
from keysieve.operators import probe as R
from keysieve.plans import sizing, star
from keysieve.queries import star_queries
from keysieve.session import ship
from keysieve.sources.tables import table
from keysieve.workloads.fixtures import relation, spec_for

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", "8"))


def timed(make) -> float:
    """Seconds of a whole call: making the DataFrame, with all jobs inside, and running it."""
    began = time.time()
    make().write.format("noop").mode("overwrite").save()
    return time.time() - began


def engine_default(spark, query) -> DataFrame:
    """The plain join with the Bloom filters that the engine itself makes at run time, whatever the tables' sizes."""
    spark.conf.set("spark.sql.optimizer.runtime.bloomFilter.enabled", "true")
    spark.conf.set("spark.sql.optimizer.runtime.bloomFilter.applicationSideScanSizeThreshold", "0")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    return star.plan_join(query)


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", str(CPUS))
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    ship(spark)
    spark.range(1000).count()
    took: dict[str, float] = {}
    rows = relation(spark, SF_DIR, "qty")
    line_rows = rows.count()
    orders = table(spark, SF_DIR, "orders", ["o_orderkey"]).withColumnRenamed("o_orderkey", "k")
    probes = orders.crossJoin(spark.range(20).select(F.lit(1).alias("x")))
    asked, rates = probes.count(), {}
    for variant in ("warm-up", "keyonly", "plain", "bloomattr", "hybrid", "chained"):
        of = "keyonly" if variant == "warm-up" else variant
        spec = spec_for("qty", LARGE, small_values=True, variant=of, l_max=4)
        if of != "keyonly":
            spec = sizing.shape(sizing.per_key(rows, "k", ["qty"]), spec)
        sketch = P.build(rows, "k", spec)
        built = timed(lambda s=sketch: s.entries)
        live = R.derive_key_filter(sketch, Predicate() if of == "keyonly" else Predicate({"qty": (17,)}))
        live.cache().count()  # the prebuilt filter of the experiment, in memory
        probed = timed(lambda f=live, s=spec: R.semi(probes, "k", f, s))
        live.unpersist()
        if variant != "warm-up":
            took[f"build_{variant}"], took[f"probe_{variant}"], rates[variant] = built, probed, round(asked / probed)
    query = star_queries._query(spark, SF_DIR, "example3")
    began = time.time()
    catalog = star_queries._catalog(spark, SF_DIR, "example3").stored()
    took["star_sketches_stored"] = time.time() - began
    for name, make in {"plain": lambda: star.plan_join(query), "reduced": lambda: star.plan_join(query, catalog), "engine_bloom": lambda: engine_default(spark, query)}.items():
        timed(make)
        took[f"star_join_{name}"] = timed(make)
    for c in ("optimizer.runtime.bloomFilter.enabled", "optimizer.runtime.bloomFilter.applicationSideScanSizeThreshold", "autoBroadcastJoinThreshold"):
        spark.conf.unset(f"spark.sql.{c}")
    try:
        from keysieve.llm import queries as text_queries
    except ModuleNotFoundError:
        text_queries = None
    if text_queries is not None:
        for name in ("op1_language_id", "op2_fingerprints", "op5_token_counts", "op9_mixing", "op10_piece_dropout"):
            took[name] = timed(lambda name=name: text_queries.QUERIES[name](spark, SF_DIR))
    print(
        json.dumps(
            {
                "metric": "sketch build, probe, star join and text operators, total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": {k: round(v, 3) for k, v in took.items()}, "sf": SF_DIR.rsplit("sf", 1)[-1],
                "probes_per_second": rates, "build_rows_per_second": {v: round(line_rows / took[f"build_{v}"]) for v in rates},
            }
        )
    )


if __name__ == "__main__":
    main()
