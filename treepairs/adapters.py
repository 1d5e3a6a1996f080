"""Trees and object sets over the given tables."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .ontology import Ontology, node_key
from .operators.objects import annotate
from .operators.worded import words


@dataclass(frozen=True)
class LevelledSet:
    """Objects whose terms are the last of ``levels`` of the leaf rows; ``tree`` gives rows with the same level columns."""

    leaves: Callable[[SparkSession, str], DataFrame]
    levels: tuple[str, ...]
    tree: Callable[[SparkSession, str], DataFrame] | None = None

    def ontology(self, spark: SparkSession, sf_dir: str) -> Ontology:
        rows = (self.tree or self.leaves)(spark, sf_dir)
        return Ontology.from_levels(rows, [F.col(c) for c in self.levels])

    def objects(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        return annotate(self.leaves(spark, sf_dir), F.col("obj_id"), node_key([F.col(c) for c in self.levels]))

    def load(self, spark: SparkSession, sf_dir: str) -> tuple[DataFrame, Ontology]:
        return self.objects(spark, sf_dir), self.ontology(spark, sf_dir)


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet").select(*columns)


def _geo(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = table(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey")
    n = F.broadcast(table(spark, sf_dir, "nation", "n_nationkey", "n_regionkey"))
    return s.join(n, s.s_nationkey == n.n_nationkey).select(F.col("n_regionkey").alias("k1"), F.col("n_nationkey").alias("k2"), F.col("s_suppkey").alias("k3"))


def _geo_short(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "nation", "n_nationkey", "n_regionkey").select(F.col("n_regionkey").alias("k1"), F.col("n_nationkey").alias("k2"))


def _part_geo(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey").distinct().join(_geo(spark, sf_dir), F.col("l_suppkey") == F.col("k3")).select(F.col("l_partkey").alias("obj_id"), "k1", "k2", "k3")


def _order_geo(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey").distinct().join(_geo(spark, sf_dir), F.col("l_suppkey") == F.col("k3")).select(F.col("l_orderkey").alias("obj_id"), "k1", "k2", "k3")


def _product(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "part", "p_partkey", "p_type", "p_brand").select(F.col("p_partkey").alias("obj_id"), F.col("p_type").alias("k1"), F.col("p_brand").alias("k2"))


def _customer_product(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    li = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey")
    p = _product(spark, sf_dir).withColumnRenamed("obj_id", "p_partkey")
    return o.join(li, o.o_orderkey == li.l_orderkey).join(p, F.col("l_partkey") == F.col("p_partkey")).select(F.col("o_custkey").alias("obj_id"), "k1", "k2")


def _supplier_product(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = _product(spark, sf_dir).withColumnRenamed("obj_id", "p_partkey")
    return table(spark, sf_dir, "lineitem", "l_suppkey", "l_partkey").distinct().join(p, F.col("l_partkey") == F.col("p_partkey")).select(F.col("l_suppkey").alias("obj_id"), "k1", "k2")


def _user_activity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events", "user_id", "event_type", "ts").select(F.col("user_id").alias("obj_id"), F.col("event_type").alias("k1"), F.hour("ts").alias("k2"))


def _activity_on(days: bool) -> Callable[[SparkSession, str], DataFrame]:
    """The activity of users at weekends or on the other days."""

    def leaves(spark: SparkSession, sf_dir: str) -> DataFrame:
        at_weekend = F.dayofweek("ts").isin(1, 7)
        rows = table(spark, sf_dir, "events", "user_id", "event_type", "ts").filter(at_weekend if days else ~at_weekend)
        return rows.select(F.col("user_id").alias("obj_id"), F.col("event_type").alias("k1"), F.hour("ts").alias("k2"))

    return leaves


def _customer_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.col("o_orderdate")
    return table(spark, sf_dir, "orders", "o_custkey", "o_orderdate").select(F.col("o_custkey").alias("obj_id"), F.year(d).alias("k1"), F.month(d).alias("k2"), F.dayofmonth(d).alias("k3"))


def _part_market(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    c = table(spark, sf_dir, "customer", "c_custkey", "c_mktsegment", "c_nationkey")
    li = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey")
    return li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).select(F.col("l_partkey").alias("obj_id"), F.col("c_mktsegment").alias("k1"), F.col("c_nationkey").alias("k2"))


def _lexical(obj: Column, text: Column) -> list[Column]:
    return [obj.alias("obj_id"), F.explode(F.array_distinct(F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(r"\p{L}+"), F.lit(0)))).alias("k4")]


def _prefixes(rows: DataFrame) -> DataFrame:
    return rows.select("obj_id", *[F.substring("k4", 1, i).alias(f"k{i}") for i in (1, 2, 3)], "k4")


def _doc_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _prefixes(table(spark, sf_dir, "documents", "doc_id", "text").select(*_lexical(F.col("doc_id"), F.col("text"))))


def _conversation_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _prefixes(table(spark, sf_dir, "conversations", "conv_id", "text").select(*_lexical(F.col("conv_id"), F.col("text"))))


def _benchmark_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _prefixes(table(spark, sf_dir, "benchmark", "item_id", "text").select(*_lexical(F.col("item_id"), F.col("text"))))


#: Sets of words: table, id and text.
WORDS = {"doc_words": ("documents", "doc_id", "text"), "benchmark_words": ("benchmark", "item_id", "text")}


def word_sets(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The objects of a set of words as one row each."""
    source, obj, text = WORDS[name]
    return words(table(spark, sf_dir, source, obj, text), F.col(obj), F.col(text))


def _page_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    url = F.col("url")
    host = F.parse_url(url, F.lit("HOST"))
    step = F.split_part(F.parse_url(url, F.lit("PATH")), F.lit("/"), F.lit(2))
    return table(spark, sf_dir, "pages", "page_id", "url").select(F.floor(F.col("page_id") / 5).alias("obj_id"), F.element_at(F.split(host, r"\."), -1).alias("k1"), host.alias("k2"), step.alias("k3"))


def _vector_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    bits = lambda lo, hi: F.array_join(F.transform(F.slice("embedding", lo, hi - lo + 1), lambda x: F.when(x >= 0, "1").otherwise("0")), "")
    return table(spark, sf_dir, "embeddings", "vec_id", "embedding", "label").select(F.floor(F.col("vec_id") / 5).alias("obj_id"), F.col("label").alias("k1"), bits(1, 3).alias("k2"), bits(4, 6).alias("k3"))


SETS: dict[str, LevelledSet] = {
    "part_geo": LevelledSet(_part_geo, ("k1", "k2", "k3"), _geo),
    "order_geo": LevelledSet(_order_geo, ("k1", "k2", "k3"), _geo),
    "order_nation": LevelledSet(_order_geo, ("k1", "k2"), _geo_short),
    "customer_product": LevelledSet(_customer_product, ("k1", "k2"), _product),
    "supplier_product": LevelledSet(_supplier_product, ("k1", "k2"), _product),
    "part_product": LevelledSet(_product, ("k1", "k2"), _product),
    "user_activity": LevelledSet(_user_activity, ("k1", "k2")),
    "weekday_activity": LevelledSet(_activity_on(False), ("k1", "k2"), _user_activity),
    "weekend_activity": LevelledSet(_activity_on(True), ("k1", "k2"), _user_activity),
    "customer_days": LevelledSet(_customer_days, ("k1", "k2", "k3")),
    "part_market": LevelledSet(_part_market, ("k1", "k2")),
    "doc_words": LevelledSet(_doc_words, ("k1", "k2", "k3", "k4")),
    "conversation_words": LevelledSet(_conversation_words, ("k1", "k2", "k3", "k4")),
    "benchmark_words": LevelledSet(_benchmark_words, ("k1", "k2", "k3", "k4")),
    "page_groups": LevelledSet(_page_groups, ("k1", "k2", "k3")),
    "vector_groups": LevelledSet(_vector_groups, ("k1", "k2", "k3")),
}
