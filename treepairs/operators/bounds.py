"""Lower bounds on given pairs. Each function returns the pairs with ``bound``."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..checkpoints import checkpoint
from ..functions.columns import ratio
from ..ontology import BROADCAST_ROWS, Ontology
from .distance import avg_distance, emd_distance, with_sizes
from .objects import avg_build, known_sizes, reduce_objects, spans

#: Tasks for each core where every pair of a set is made.
TASKS_PER_CORE = 4


def emd_reduced(pairs: DataFrame, objects: DataFrame, tree: Ontology, h: int = 1, right: DataFrame | None = None) -> DataFrame:
    """EMD on the tree cut at height ``h``."""
    return emd_distance(pairs, objects, tree, right, level=h).select(*pairs.columns, F.col("dist").alias("bound"))


def avg_reduced(pairs: DataFrame, objects: DataFrame, tree: Ontology, h: int = 1, right: DataFrame | None = None) -> DataFrame:
    return avg_distance(pairs, objects, tree, right, level=h).select(*pairs.columns, F.col("dist").alias("bound"))


def _half_l1(pairs: DataFrame, x: DataFrame, y: DataFrame, factor: float) -> DataFrame:
    """factor * (1 - shared mass): half of L1 of two distributions, from the terms that they share alone."""
    x = x.select(F.col("obj_id").alias("a"), "term_id", F.col("cnt").alias("ca"), F.col("n").alias("na"))
    y = y.select(F.col("obj_id").alias("b"), "term_id", F.col("cnt").alias("cb"), F.col("n").alias("nb"))
    s = pairs.select("a", "b").join(x, "a").join(y, ["b", "term_id"]).groupBy("a", "b").agg(F.sum(F.least(F.col("ca") * F.col("nb"), F.col("cb") * F.col("na"))).alias("m"))
    n = pairs.join(x.select("a", "na").distinct(), "a").join(y.select("b", "nb").distinct(), "b").join(s, ["a", "b"], "left")
    den = F.col("na") * F.col("nb")
    return n.select(*pairs.columns, (ratio(den - F.coalesce("m", F.lit(0)), den) * F.lit(factor)).alias("bound"))


def l1_full(pairs: DataFrame, objects: DataFrame, tree: Ontology, scale: str = "safe", right: DataFrame | None = None) -> DataFrame:
    """Half of L1 over all terms. ``published``: unscaled, which is a bound only if distinct terms are at least 1 apart;
    ``safe``: times the smallest edge."""
    from .objects import mass

    factor = {"safe": tree.least_edge / tree.scale, "published": 1.0}[scale]
    return _half_l1(pairs, mass(objects), mass(objects if right is None else right), factor)


def l1_reduced(pairs: DataFrame, objects: DataFrame, tree: Ontology, h: int = 1, scale: str = "safe", right: DataFrame | None = None) -> DataFrame:
    """Half of L1 over the terms of the tree cut at ``h``, times the smallest edge that is left if that is below 1."""
    factor = 1.0 if scale == "published" else min(1.0, (tree.least_top_edge if h == 1 else tree.least_edge) / tree.scale)
    return _half_l1(pairs, reduce_objects(objects, tree, h), reduce_objects(objects if right is None else right, tree, h), factor)


def residual_depth(objects: DataFrame, tree: Ontology, h: int) -> DataFrame:
    """obj_id, residual (scaled, with n): mass-weighted depth below level ``h``. Pairs that share no node deeper than
    ``h`` are at least the sum of their residuals apart."""
    cut = F.element_at("path", F.least(F.size("path"), F.lit(h + 1)))["depth"]
    rows = objects.join(tree.paths(), "term_id").withColumn("r", F.element_at("path", -1)["depth"] - cut)
    return rows.groupBy("obj_id").agg(F.sum("r").alias("num"), (F.count(F.lit(1)) * F.lit(tree.scale)).alias("den")).select("obj_id", ratio(F.col("num"), F.col("den")).alias("residual"))


def pivot(objects: DataFrame, tree: Ontology) -> DataFrame:
    """obj_id, m: mean distance to the root; EMD is at least the difference of two such values."""
    return known_sizes(objects, tree).select("obj_id", ratio(F.col("s"), F.col("n") * F.lit(tree.scale)).alias("m"))


def pivot_band(objects: DataFrame, tree: Ontology, theta: float, right: DataFrame | None = None) -> DataFrame:
    """Pairs whose pivots differ by at most ``theta``: an equi-join on buckets of that width, then a filter."""
    width = max(theta, 1e-9)
    x = pivot(objects, tree).select(F.col("obj_id").alias("a"), F.col("m").alias("ma"))
    y = (x.select(F.col("a").alias("b"), F.col("ma").alias("mb"))) if right is None else pivot(right, tree).select(F.col("obj_id").alias("b"), F.col("m").alias("mb"))
    slot = lambda c: F.floor(F.col(c) / F.lit(width))
    x = x.withColumn("slot", F.explode(F.array(slot("ma") - 1, slot("ma"), slot("ma") + 1)))
    near = x.join(y.withColumn("slot", slot("mb")), "slot").filter(F.abs(F.col("ma") - F.col("mb")) <= F.lit(theta))
    near = near.filter("a < b") if right is None else near
    return near.select("a", "b", F.abs(F.col("ma") - F.col("mb")).alias("bound"))


def case_total(single_a: Column, single_b: Column, same: Column, na: Column, wa: Column, nb: Column, wb: Column) -> tuple[Column, Column]:
    """(case, total): the least across cost at a node from counts, sums and spans alone."""
    both = single_a & single_b
    case = F.when(both & same, "1a").when(both, "1b").when(single_a | single_b, "3").otherwise("2")
    total = F.when(both & same, F.lit(0)).when(both, nb * wa + na * wb).when(single_a, wa).when(single_b, wb).otherwise(wa + wb)
    return case, total.cast("long")


def avg_bound(pairs: DataFrame | None, objects: DataFrame, tree: Ontology) -> DataFrame:
    """Adds ``case`` and ``bound`` of the average distance at the root; 1b is exact, and so is a pair of root objects.

    Without ``pairs`` every pair of the set is taken; they are made where they are used and not shuffled. The objects are few
    against their pairs: one side is dealt over all cores, where the planner would put so few bytes in one task.
    """
    s = spans(avg_build(objects, tree))
    if pairs is None:
        s = checkpoint(s.select("obj_id", "n", "w", "children", "list_id"))
    x = s.select(F.col("obj_id").alias("a"), F.col("n").alias("na"), F.col("w").alias("wa"), (F.col("children") <= 1).alias("sa"), F.col("list_id").alias("la"))
    y = s.select(F.col("obj_id").alias("b"), F.col("n").alias("nb"), F.col("w").alias("wb"), (F.col("children") <= 1).alias("sb"), F.col("list_id").alias("lb"))
    if pairs is None:
        tasks = TASKS_PER_CORE * objects.sparkSession.sparkContext.defaultParallelism
        y = F.broadcast(y) if s.count() <= BROADCAST_ROWS else y.repartition(tasks, "b")
        p = x.repartition(tasks, "a").crossJoin(y).filter("a < b")
    else:
        p = pairs.join(x, "a").join(y, "b")
    c = F.col
    case, total = case_total(c("sa"), c("sb"), c("la") == c("lb"), c("na"), c("wa"), c("nb"), c("wb"))
    return p.select(*(["a", "b"] if pairs is None else pairs.columns), case.alias("case"), ratio(total, c("na") * c("nb") * F.lit(tree.scale)).alias("bound"))


def avg_descend(pairs: DataFrame, objects: DataFrame, tree: Ontology, level: int) -> DataFrame:
    """Bound after the across costs of all shared nodes above ``level`` are exact; level 0 is the case bound at the root.

    Frontier nodes (the shared ones at ``level``) add their case bounds, or nothing below the deepest level.
    """
    build = avg_build(objects, tree)
    child_counts = build.join(tree.nodes.select("node_id", "parent_id"), "node_id").filter("parent_id IS NOT NULL").groupBy("obj_id", F.col("parent_id").alias("node_id")).agg(F.count(F.lit(1)).alias("k"), F.min("node_id").alias("child"), F.sum("n").alias("below"))
    g = build.join(child_counts, ["obj_id", "node_id"], "left").withColumn("groups", F.coalesce("k", F.lit(0)) + (F.coalesce("below", F.lit(0)) < F.col("n")).cast("long"))
    g = g.withColumn("only", F.when(F.col("groups") <= 1, F.coalesce("child", F.lit("self"))))
    half = lambda side, s: g.filter(F.col("level") == level).select(F.col("obj_id").alias(side), "node_id", F.col("n").alias(f"n{s}"), F.col("w").alias(f"w{s}"), F.col("only").alias(f"o{s}"))
    c = F.col
    shared = pairs.select("a", "b").join(half("a", "a"), "a").join(half("b", "b"), ["b", "node_id"])
    _, frontier = case_total(c("oa").isNotNull(), c("ob").isNotNull(), c("oa") == c("ob"), c("na"), c("wa"), c("nb"), c("wb"))
    open_ = shared.groupBy("a", "b").agg(F.sum(frontier).alias("frontier"), F.sum(c("nb") * c("wa") + c("na") * c("wb")).alias("within"))
    # Pairs of terms that part above the level: all distances via the root, less what lies under shared nodes.
    from .distance import _shared
    from .objects import subtree_counts

    counts = subtree_counts(objects, tree).filter(F.col("level") <= level)
    shared_w = _shared(pairs, counts, counts, F.col("w") * F.col("ca") * F.col("cb"), "shared")
    sized = with_sizes(pairs, known_sizes(objects, tree), known_sizes(objects, tree))
    full = sized.join(open_, ["a", "b"], "left").join(shared_w, ["a", "b"], "left")
    zero = lambda x: F.coalesce(x, F.lit(0))
    total = c("nb") * c("sa") + c("na") * c("sb") - 2 * zero("shared") - zero("within") + zero("frontier")
    return full.select(*pairs.columns, ratio(total, c("na") * c("nb") * F.lit(tree.scale)).alias("bound"))
