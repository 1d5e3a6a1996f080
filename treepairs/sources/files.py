"""Vocabularies and annotations from files, and the sinks of answers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGES = "child string, parent string"


def read_edges(spark: SparkSession, path: str, kind: str = "csv", **options) -> DataFrame:
    """child, parent from CSV, JSON lines, Parquet or ORC; empty parents are null."""
    reader = spark.read.schema(EDGES).options(**options)
    rows = {"csv": lambda: reader.option("header", "true").csv(path), "json": lambda: reader.json(path), "parquet": lambda: reader.parquet(path), "orc": lambda: reader.orc(path)}[kind]()
    return rows.select("child", F.when(F.col("parent") != "", F.col("parent")).alias("parent"))


def read_stanzas(spark: SparkSession, path: str) -> DataFrame:
    """child, parent from text of ``[Term]`` stanzas with ``id:`` and ``is_a:`` / ``relationship: part_of`` lines.

    A term with several parents gives several rows (a graph: see ``dag_to_tree``); one without any is a root.
    """
    s = spark.read.option("lineSep", "[Term]").text(path)
    up = F.flatten(F.array(F.regexp_extract_all("value", F.lit(r"(?m)^is_a: (\S+)"), F.lit(1)), F.regexp_extract_all("value", F.lit(r"(?m)^relationship: part_of (\S+)"), F.lit(1))))
    rows = s.select(F.regexp_extract("value", r"(?m)^id: (\S+)", 1).alias("child"), up.alias("up")).filter("child <> ''")
    return rows.select("child", F.explode_outer("up").alias("parent"))


def read_objects(spark: SparkSession, path: str, kind: str = "csv", **options) -> DataFrame:
    reader = spark.read.schema("obj_id long, term_id string").options(**options)
    rows = {"csv": lambda: reader.option("header", "true").csv(path), "json": lambda: reader.json(path), "parquet": lambda: reader.parquet(path)}[kind]()
    return rows.dropna().dropDuplicates()


def write_answers(df: DataFrame, path: str, bucket: int = 1000) -> None:
    """Answers by buckets of their rank."""
    df.withColumn("rank_bucket", F.floor((F.col("rank") - 1) / bucket)).write.mode("overwrite").partitionBy("rank_bucket").parquet(path)


def write_bucketed(df: DataFrame, name: str, key: str, buckets: int) -> None:
    """A table bucketed by a key, for several searches of one session that join on it."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)
