"""The three distances on given pairs, as joins on shared tree nodes. All arithmetic is on integers; one division ends it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.columns import ratio, term_distance_col
from ..ontology import Ontology
from .objects import known_sizes, subtree_counts, subtree_minima


def _shared(pairs: DataFrame, left: DataFrame, right: DataFrame, term: Column, name: str) -> DataFrame:
    """Sum of ``term`` over the nodes that both objects of a pair touch."""
    x = left.select(F.col("obj_id").alias("a"), "node_id", "w", F.col("c").alias("ca"), F.col("n").alias("na"))
    y = right.select(F.col("obj_id").alias("b"), "node_id", F.col("c").alias("cb"), F.col("n").alias("nb"))
    both = pairs.select("a", "b").join(x, "a").join(y, ["b", "node_id"])
    return both.groupBy("a", "b").agg(F.sum(term).alias(name))


def with_sizes(pairs: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """Adds na, sa, nb, sb; pairs of which one object has no term in the tree are left out."""
    return pairs.join(left.select(F.col("obj_id").alias("a"), F.col("n").alias("na"), F.col("s").alias("sa")), "a").join(right.select(F.col("obj_id").alias("b"), F.col("n").alias("nb"), F.col("s").alias("sb")), "b")


def _from_shared(pairs: DataFrame, objects: DataFrame, tree: Ontology, right: DataFrame | None, term: Column, level: int | None) -> DataFrame:
    other = objects if right is None else right
    ca, cb = subtree_counts(objects, tree), subtree_counts(other, tree)
    if level is not None:
        ca, cb = ca.filter(F.col("level") <= level), cb.filter(F.col("level") <= level)
    na = known_sizes(objects, tree) if level is None else cut_sizes(objects, tree, level)
    nb = known_sizes(other, tree) if level is None else cut_sizes(other, tree, level)
    s = _shared(pairs, ca, cb, term, "shared")
    full = with_sizes(pairs, na, nb).join(s, ["a", "b"], "left")
    num = F.col("nb") * F.col("sa") + F.col("na") * F.col("sb") - 2 * F.coalesce("shared", F.lit(0))
    den = F.col("na") * F.col("nb") * F.lit(tree.scale)
    return full.select(*pairs.columns, num.cast("long").alias("num"), den.cast("long").alias("den"), ratio(num, den).alias("dist"))


def cut_sizes(objects: DataFrame, tree: Ontology, level: int) -> DataFrame:
    """obj_id, n, s with depths on the tree cut at the level."""
    step = tree.paths().select("term_id", F.element_at("path", F.least(F.size("path"), F.lit(level + 1)))["depth"].alias("depth"))
    return objects.join(step, "term_id").groupBy("obj_id").agg(F.count(F.lit(1)).alias("n"), F.sum("depth").alias("s"))




def _emd_term() -> Column:
    return F.col("w") * F.least(F.col("ca") * F.col("nb"), F.col("cb") * F.col("na"))


def emd_distance(pairs: DataFrame, objects: DataFrame, tree: Ontology, right: DataFrame | None = None, solver: str = "closed", level: int | None = None) -> DataFrame:
    """Earth mover's distance. ``closed``: the closed form on trees. ``flow``: the transport problem itself, for reference."""
    if solver == "flow":
        from .flow import emd_by_flow

        return emd_by_flow(pairs, objects, tree, right)
    return _from_shared(pairs, objects, tree, right, _emd_term(), level)


def avg_distance(pairs: DataFrame, objects: DataFrame, tree: Ontology, right: DataFrame | None = None, level: int | None = None) -> DataFrame:
    return _from_shared(pairs, objects, tree, right, F.col("w") * F.col("ca") * F.col("cb"), level)


def min_distance(pairs: DataFrame, objects: DataFrame, tree: Ontology, right: DataFrame | None = None) -> DataFrame:
    x = subtree_minima(objects, tree)
    y = x if right is None else subtree_minima(right, tree)
    both = pairs.join(x.select(F.col("obj_id").alias("a"), "node_id", F.col("dist").alias("da")), "a").join(y.select(F.col("obj_id").alias("b"), "node_id", F.col("dist").alias("db")), ["b", "node_id"])
    low = both.groupBy(*pairs.columns).agg(F.min(F.col("da") + F.col("db")).alias("num"))
    den = F.lit(tree.scale).cast("long")
    return low.select(*pairs.columns, F.col("num"), den.alias("den"), ratio(F.col("num"), den).alias("dist"))


DISTANCES = {"emd": emd_distance, "avg": avg_distance, "min": min_distance}


def naive(pairs: DataFrame, objects: DataFrame, tree: Ontology, measure: str) -> DataFrame:
    """MIN or AVG by all term pairs: an independent check."""
    p = objects.join(tree.paths(), "term_id")
    x, y = p.select(F.col("obj_id").alias("a"), F.col("path").alias("pa")), p.select(F.col("obj_id").alias("b"), F.col("path").alias("pb"))
    d = pairs.join(x, "a").join(y, "b").withColumn("d", term_distance_col(F.col("pa"), F.col("pb")))
    g = d.groupBy(*pairs.columns).agg(F.min("d").alias("low"), F.sum("d").alias("total"), F.count(F.lit(1)).alias("cells"))
    num, den = (F.col("low"), F.lit(tree.scale).cast("long")) if measure == "min" else (F.col("total"), F.col("cells") * F.lit(tree.scale))
    return g.select(*pairs.columns, num.alias("num"), den.alias("den"), ratio(num, den).alias("dist"))


def all_pairs(objects: DataFrame, diagonal: bool = False) -> DataFrame:
    """Every pair of a small set; for tables of distances and brute force only."""
    ids = objects.select("obj_id").distinct()
    a, b = ids.select(F.col("obj_id").alias("a")), ids.select(F.col("obj_id").alias("b"))
    return a.crossJoin(b).filter("a <= b" if diagonal else "a < b")


def distance_matrix(objects: DataFrame, tree: Ontology, measure: str) -> DataFrame:
    """The table of distances of a set, the diagonal included; no pair is shuffled."""
    from .every_pair import matrix

    return matrix(objects, tree, measure)


def sandwich(pairs: DataFrame, objects: DataFrame, tree: Ontology) -> DataFrame:
    """Violations of MIN <= EMD <= AVG (none are expected), compared without a division."""
    out = pairs
    for name, f in DISTANCES.items():
        out = out.join(f(pairs, objects, tree).select("a", "b", F.col("num").alias(f"{name}_num"), F.col("den").alias(f"{name}_den")), ["a", "b"])
    wide = lambda c: F.col(c).cast("decimal(38,0)")
    less = lambda x, y: wide(f"{x}_num") * wide(f"{y}_den") <= wide(f"{y}_num") * wide(f"{x}_den")
    return out.filter(~(less("min", "emd") & less("emd", "avg")))
