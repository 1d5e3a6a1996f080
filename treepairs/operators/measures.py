"""Costs and quality: share of pairs examined, purity, tightness, agreement, scaling."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..ontology import Ontology
from .avg_join import progressive as avg_progressive
from .emd_join import progressive as emd_progressive
from .objects import dedupe_objects


def eta_emd(objects: DataFrame, tree: Ontology, k: int, variant: str = "l1_reduced", h: int = 1) -> DataFrame:
    """One row: objects, pairs, the counters of the sequential search, and eta, the share of pairs with a full EMD."""
    return _eta(emd_progressive(objects, tree, k, None, variant, h), objects, "emd")


def eta_avg(objects: DataFrame, tree: Ontology, k: int, refine: str = "stepwise", order: str = "bfs") -> DataFrame:
    """As :func:`eta_emd`; eta is the share of pairs examined, those taken from the heap, and ``completed`` the share of pairs
    whose distance was completed."""
    return _eta(avg_progressive(objects, tree, k, refine, order), objects, "examined").withColumn("completed", F.col("complete") / F.col("pairs"))


def _eta(found: DataFrame, objects: DataFrame, counter: str) -> DataFrame:
    names = [c for c in found.columns if c not in ("grp", "rank", "a", "b", "dist")]
    one = found.agg(*[F.max(c).alias(c) for c in names], F.max("dist").alias("kth"))
    n = objects.select("obj_id").distinct().agg(F.count(F.lit(1)).alias("objects"))
    pairs = F.col("objects") * (F.col("objects") - 1) / 2
    return n.crossJoin(one).withColumn("pairs", pairs).withColumn("eta", F.col(counter) / pairs)


def purity(topk: DataFrame, categories: DataFrame, cuts: tuple[int, ...] = (10, 50)) -> DataFrame:
    """cut, pairs, same: answers of which both objects have one category; ``categories``: obj_id, category."""
    a, b = categories.select(F.col("obj_id").alias("a"), F.col("category").alias("ca")), categories.select(F.col("obj_id").alias("b"), F.col("category").alias("cb"))
    p = topk.join(a, "a").join(b, "b").withColumn("cut", F.explode(F.array(*[F.lit(c) for c in cuts]))).filter("rank <= cut")
    return p.groupBy("cut").agg(F.count(F.lit(1)).alias("pairs"), F.count_if(F.col("ca") == F.col("cb")).alias("same"))


def zero_pairs(objects: DataFrame) -> DataFrame:
    """zero: pairs at MIN distance 0, those that share a term.

    Equal descriptions are one class: pairs inside a class count by its size, and only classes meet over their terms.
    """
    kept, rep = dedupe_objects(objects)
    size = rep.groupBy("rep").agg(F.count(F.lit(1)).alias("n"))
    x, y = kept.select("term_id", F.col("obj_id").alias("a")), kept.select("term_id", F.col("obj_id").alias("b"))
    met = x.join(y, "term_id").filter("a < b").select("a", "b").distinct()
    sized = met.join(size.select(F.col("rep").alias("a"), F.col("n").alias("na")), "a").join(size.select(F.col("rep").alias("b"), F.col("n").alias("nb")), "b")
    across = sized.agg(F.coalesce(F.sum(F.col("na") * F.col("nb")), F.lit(0)).alias("x"))
    inside = size.agg(F.coalesce(F.sum(F.col("n") * (F.col("n") - 1) / 2), F.lit(0)).cast("long").alias("y"))
    return across.crossJoin(inside).select((F.col("x") + F.col("y")).alias("zero"))


def tightness(bounds: DataFrame, exact: DataFrame) -> DataFrame:
    """pairs, mean_ratio (over positive distances), violations; ``bounds``: a, b, bound; ``exact``: a, b, dist."""
    j = bounds.select("a", "b", "bound").join(exact.select("a", "b", "dist"), ["a", "b"])
    return j.agg(F.count(F.lit(1)).alias("pairs"), F.avg(F.when(F.col("dist") > 0, F.col("bound") / F.col("dist"))).alias("mean_ratio"), F.count_if(F.col("bound") > F.col("dist") + 1e-9).alias("violations"))


def agreement(got: DataFrame, want: DataFrame) -> DataFrame:
    """k, precision, kth_error of an answer against the exact one."""
    hit = got.join(want.select("a", "b"), ["a", "b"], "left_semi").agg(F.count(F.lit(1)).alias("hits"))
    g, w = got.agg(F.max("dist").alias("g")), want.agg(F.max("dist").alias("w"), F.count(F.lit(1)).alias("k"))
    return hit.crossJoin(g).crossJoin(w).select("k", (F.col("hits") / F.col("k")).alias("precision"), (F.coalesce("g", F.lit(0.0)) - F.col("w")).alias("kth_error"))


def scaling_exponent(points: DataFrame, x: str, y: str) -> DataFrame:
    """slope of log y in log x."""
    return points.filter(f"{x} > 0 AND {y} > 0").agg(F.regr_slope(F.log(y), F.log(x)).alias("slope"))
