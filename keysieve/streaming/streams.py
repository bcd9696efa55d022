"""Structured Streaming over the event table: windows, duplicates, joins, sketch filters and sketch upkeep.

Each function reads a bounded file stream to its end and returns what its sink holds, so that batch results can
be compared. Sinks are tables in the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import pairs as P
from ..operators import probe as R
from ..sources.tables import shared_dir


def source(spark: SparkSession, sf_dir: str, name: str = "events", files: int | None = None) -> DataFrame:
    """A table as a stream of files."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    reader = spark.readStream.schema(schema)
    if files:
        reader = reader.option("maxFilesPerTrigger", files)
    stream = reader.parquet(f"{sf_dir}/{name[:-1]}[{name[-1]}].parquet")  # a pattern names a file as well as a folder
    plain = [f.name for f in schema.fields if f.dataType.simpleString() == "timestamp_ntz"]
    return stream.withColumns({c: F.col(c).cast("timestamp") for c in plain}) if plain else stream


def drained(stream: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over all that is there; in complete mode the last result stays, else results add up."""
    spark, path = stream.sparkSession, shared_dir(stream.sparkSession)

    def put(batch: DataFrame, _: int) -> None:
        batch.write.mode("overwrite" if mode == "complete" else "append").parquet(f"{path}/rows")

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).foreachBatch(put).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")


def windowed(stream: DataFrame, size: str, slide: str | None, delay: str = "2 days") -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return stream.withWatermark("ts", delay).groupBy(w, "event_type").agg(F.count("*").alias("n")).select(F.unix_timestamp("window.start").alias("start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str) -> DataFrame:
    s = stream.withWatermark("ts", "2 days").groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count("*").alias("n"))
    return s.select("user_id", F.unix_timestamp("s.start").alias("start"), "n")


def dedup(stream: DataFrame, columns: list[str]) -> DataFrame:
    return stream.select(*columns).dropDuplicates(columns)


def filter_by(stream: DataFrame, key: str, live: DataFrame, spec) -> DataFrame:
    """A stream's rows whose key passes a static sketch."""
    return R.semi(stream, key, live, spec)


def interval_join(stream_a: DataFrame, stream_b: DataFrame, days: int) -> DataFrame:
    """Pairs (a, b) of one user with b at most some days after a; watermarks bound what is kept."""
    a = stream_a.filter("event_type = 'click'").select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta")).withWatermark("ta", "40 days")
    b = stream_b.filter("event_type = 'purchase'").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb")).withWatermark("tb", "40 days")
    return a.join(b, F.expr(f"ua = ub and tb >= ta and tb <= ta + interval {days} days")).select("a", "b")


def maintain(stream: DataFrame, key: str, spec) -> DataFrame:
    """The entries of a sketch that each micro-batch is merged into; a batch that runs again gives the same entries."""
    spark, path = stream.sparkSession, shared_dir(stream.sparkSession)
    state = {"n": -1}

    def put(batch: DataFrame, epoch: int) -> None:
        new = P.build(batch, key, spec)
        if state["n"] >= 0:
            new = P.merge(P.Sketch(spec, spark.read.parquet(f"{path}/entries-{state['n']}")), new)
        new.entries.write.mode("overwrite").parquet(f"{path}/entries-{epoch}")
        state["n"] = epoch

    q = stream.writeStream.option("checkpointLocation", f"{path}/state").trigger(availableNow=True).foreachBatch(put).start()
    q.awaitTermination()
    return spark.read.parquet(f"{path}/entries-{state['n']}")


def late_rows(stream: DataFrame, delay: str) -> int:
    """How many rows came after the watermark had passed them, from the query's progress."""
    path = shared_dir(stream.sparkSession)
    q = windowed(stream, "1 day", None, delay).writeStream.outputMode("append").option("checkpointLocation", f"{path}/state").trigger(availableNow=True).foreachBatch(lambda b, _: b.write.mode("append").parquet(f"{path}/rows")).start()
    q.awaitTermination()
    return sum(op["numRowsDroppedByWatermark"] for p in q.recentProgress for op in p["stateOperators"])
