"""Tables by name with pruned columns, text formats, and sketches on storage."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import SketchSpec
from ..operators.pairs import Sketch
from .folders import shared_dir


def table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def roundtrip(df: DataFrame, fmt: str) -> DataFrame:
    """df written in a format and read back with its own schema."""
    path = f"{shared_dir(df.sparkSession)}/{fmt}"
    writer = df.write.format(fmt)
    if fmt == "csv":
        writer = writer.option("header", True).option("escape", '"')
    writer.save(path)
    reader = df.sparkSession.read.format(fmt).schema(df.schema)
    return (reader.option("header", True).option("escape", '"') if fmt == "csv" else reader).load(path)


def save_sketch(sketch: Sketch, path: str) -> None:
    """Entries with a column for each attribute, by shard, and the spec as one JSON row beside them."""
    spark = sketch.entries.sparkSession
    sketch.entries.write.partitionBy("shard").parquet(f"{path}/entries")
    spark.createDataFrame([(sketch.spec.to_json(),)], "spec string").coalesce(1).write.json(f"{path}/spec")


def load_sketch(spark: SparkSession, path: str, spec: SketchSpec | None = None) -> Sketch:
    """A stored sketch; another spec than the stored one is an error."""
    told = SketchSpec.from_json(spark.read.schema("spec string").json(f"{path}/spec").first()[0])
    if spec is not None and spec != told:
        raise ValueError("the stored sketch has another spec")
    return Sketch(told, spark.read.parquet(f"{path}/entries"))


def save_filter(live: DataFrame, path: str) -> DataFrame:
    live.write.parquet(path)
    return live.sparkSession.read.parquet(path)


def save_bucketed(df: DataFrame, key: str, buckets: int, name: str) -> DataFrame:
    """A table whose rows are dealt and sorted by key, so that joins on it move nothing."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(name)
    return df.sparkSession.table(name)


def stored(sketch: Sketch) -> Sketch:
    """The sketch written to the shared folder and loaded again."""
    path = f"{shared_dir(sketch.entries.sparkSession)}/sketch"
    save_sketch(sketch, path)
    return load_sketch(sketch.entries.sparkSession, path, sketch.spec)


def counted(df: DataFrame) -> DataFrame:
    return df.agg(F.count("*").alias("n"))
