"""A corpus pipeline of five text operators: each stage reads what the one before it wrote.

Language ID removes texts without a language, the n-gram join keeps one document of each class of near copies
(the smallest doc_id), suffix dedup cuts passages that an earlier document has, mixing repeats or leaves out
documents so that sources come to their target weights, and encoding returns seeded segmentations with the
texts that they decode to.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from keysieve.llm import jaccard_join, language_id, mixing, piece_dropout, suffix_dedup
from keysieve.llm.common import documents, written
from keysieve.llm.queries import vocabulary
from keysieve.session import ship

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def name_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose text has some letter, with the predicted language where none is given; without labels to learn from, none is filled in."""
    ship(spark)
    model = language_id.fit(language_id.sample(docs, "text", "lang", "doc_id"))
    if model is None:
        return docs.filter(F.regexp_like("text", F.lit(r"\p{L}"))).select(*COLUMNS)
    named = language_id.predict(docs, model).filter("lang_pred <> 'und'")
    return named.withColumn("lang", F.coalesce("lang", "lang_pred")).select(*COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of texts that share 80 % of their five-word n-grams: that with the smallest doc_id."""
    ship(spark)
    classes = jaccard_join.classes(docs, k=5, percent=80)
    away = classes.filter("component_id <> doc_id").select("doc_id").distinct()
    return docs.join(away, "doc_id", "left_anti").select(*COLUMNS)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the strings of 50 bytes that an earlier one has; documents of which nothing is left go."""
    ship(spark)
    cut = suffix_dedup.remove_repeats(docs.select(*COLUMNS))
    return cut.filter("n_removed = 0 or length(trim(text)) > 0").select("doc_id", "text", "lang", "source", F.length("text").cast("long").alias("n_chars"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them; rows that share a doc_id, or have none, are told apart by source, size and number."""
    ship(spark)
    like = ["doc_id", "source", "size"]
    sized = docs.select(*COLUMNS, F.coalesce(F.regexp_count("text", F.lit(mixing.WORD)), F.lit(0)).cast("long").alias("size"))
    marks = mixing.mix(docs).select(*like, "copies")
    # texts and what the mix says of them are dealt once; both windows find their rows there
    both = sized.unionByName(marks, allowMissingColumns=True).repartition(*like)
    rows = both.withColumn("mark", F.col("copies").isNotNull())
    rows = rows.withColumn("nth", F.row_number().over(Window.partitionBy(*like, "mark").orderBy("copies", F.xxhash64("text"))))
    rows = rows.withColumn("taken", F.max("copies").over(Window.partitionBy(*like, "nth"))).filter("not mark and taken > 0")
    rows = rows.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("taken"))))
    return rows.select(*COLUMNS)


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Seeded segmentations of every document, and the texts that they decode to; repeats of a document draw for themselves."""
    ship(spark)
    repeat = Window.partitionBy("doc_id", F.xxhash64("text")).orderBy("n_chars")
    return piece_dropout.encode(docs.withColumn("repeat", F.row_number().over(repeat)), vocabulary("piece_bpe_32k.model"), dropout=0.1, seed=7, copy="repeat")


STAGES = [("language_id", name_language), ("jaccard_join", drop_near_copies), ("suffix_dedup", cut_repeats), ("mixing", mix_sources), ("piece_dropout", encode_pieces)]

#: The stages cannot be said in SQL; tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), name)
    return docs


QUERIES = {"pipeline": run}
ORACLES: dict[str, str] = {}
