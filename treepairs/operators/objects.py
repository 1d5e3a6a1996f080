"""Objects: annotation, inverted lists, equal descriptions, subtree summaries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..ontology import ROOT, Ontology


def annotate(rows: DataFrame, obj: Column, term: Column) -> DataFrame:
    """obj_id, term_id as a set; rows without an object or a term are left out. Dealt by object, so that what is grouped by
    object and node later needs no shuffle of its own."""
    return rows.select(obj.cast("long").alias("obj_id"), term.cast("string").alias("term_id")).dropna().repartition("obj_id").dropDuplicates()


def unknown_terms(objects: DataFrame, tree: Ontology) -> DataFrame:
    """Annotations whose term is not in the tree; the searches ignore them, so callers may want to count them."""
    return objects.join(tree.nodes.select(F.col("node_id").alias("term_id")), "term_id", "left_anti")


def sizes(objects: DataFrame) -> DataFrame:
    return objects.groupBy("obj_id").agg(F.count(F.lit(1)).alias("n"))


def inverted_index(objects: DataFrame) -> DataFrame:
    """term_id and its objects in order. A list is as long as its term is frequent: for reports, not for the searches."""
    return objects.groupBy("term_id").agg(F.sort_array(F.collect_list("obj_id")).alias("objects"))


def descriptions(objects: DataFrame) -> DataFrame:
    """obj_id and its terms in order."""
    return objects.groupBy("obj_id").agg(F.sort_array(F.collect_set("term_id")).alias("terms"))


def dedupe_objects(objects: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(objects with one representative per description, obj_id with its ``rep``: the smallest id). Descriptions are
    compared as a whole, not by a hash."""
    d = descriptions(objects)
    # A partial aggregate meets equal descriptions before the shuffle.
    reps = d.groupBy("terms").agg(F.min("obj_id").alias("rep"))
    rep = d.join(reps, "terms").select("obj_id", "rep")
    kept = reps.select(F.col("rep").alias("obj_id"), F.explode("terms").alias("term_id"))
    return kept, rep


def mass(objects: DataFrame) -> DataFrame:
    """obj_id, term_id, cnt, n: the mass of a term is cnt/n."""
    return objects.join(sizes(objects), "obj_id").select("obj_id", "term_id", F.lit(1).cast("long").alias("cnt"), "n")


def reduce_objects(objects: DataFrame, tree: Ontology, h: int = 1) -> DataFrame:
    """obj_id, term_id, cnt, n on the tree cut at height ``h``."""
    cut = objects.join(F.broadcast(tree.cut(h)) if _small(tree) else tree.cut(h), "term_id")
    counted = cut.groupBy("obj_id", F.col("kept_id").alias("term_id")).agg(F.count(F.lit(1)).alias("cnt"))
    return counted.join(sizes(objects), "obj_id")


def _small(tree: Ontology) -> bool:
    from ..ontology import BROADCAST_ROWS

    return tree.nodes.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS


def placed(objects: DataFrame, tree: Ontology) -> DataFrame:
    """obj_id, node_id, level, w, below: a row for each term and node on its path; ``below``: distance of the term."""
    steps = objects.join(tree.paths(), "term_id").withColumn("last", F.element_at("path", -1)["depth"])
    s = steps.select("obj_id", "last", F.explode("path").alias("s"))
    return s.select("obj_id", F.col("s.node_id").alias("node_id"), F.col("s.level").alias("level"), F.col("s.w").alias("w"), (F.col("last") - F.col("s.depth")).alias("below"))


def subtree_counts(objects: DataFrame, tree: Ontology) -> DataFrame:
    """obj_id, node_id, level, w, c, n: terms of the object below each node that it touches, the root left out."""
    c = placed(objects, tree).filter("level > 0").groupBy("obj_id", "node_id", "level", "w").agg(F.count(F.lit(1)).alias("c"))
    return c.join(known_sizes(objects, tree), "obj_id")


def known_sizes(objects: DataFrame, tree: Ontology) -> DataFrame:
    """obj_id, n, s: number of terms that the tree has, and their summed depth."""
    depth = tree.nodes.select(F.col("node_id").alias("term_id"), "depth")
    joined = objects.join(F.broadcast(depth) if _small(tree) else depth, "term_id")
    return joined.groupBy("obj_id").agg(F.count(F.lit(1)).alias("n"), F.sum("depth").alias("s"))


def subtree_minima(objects: DataFrame, tree: Ontology) -> DataFrame:
    """node_id, obj_id, level, dist: distance from each node down to the object's nearest term, the root included."""
    return placed(objects, tree).groupBy("node_id", "obj_id", "level").agg(F.min("below").alias("dist"))


def avg_build(objects: DataFrame, tree: Ontology, mode: str = "closure") -> DataFrame:
    """obj_id, node_id, level, n, w: number of the object's terms below a node and their summed distance to it.

    ``closure``: one aggregate over the root paths. ``levels``: bottom-up, a join and an aggregate for each level.
    """
    if mode == "closure":
        return placed(objects, tree).groupBy("obj_id", "node_id", "level").agg(F.count(F.lit(1)).alias("n"), F.sum("below").alias("w"))
    if mode != "levels":
        raise ValueError(mode)
    up = tree.nodes.select("node_id", "parent_id", "level", F.col("w").alias("edge"))
    up = F.broadcast(up) if _small(tree) else up
    own = objects.withColumnRenamed("term_id", "node_id").join(up, "node_id").select("obj_id", "node_id", "level", F.lit(1).cast("long").alias("n"), F.lit(0).cast("long").alias("w"))
    out, above = None, None
    for level in range(tree.height, -1, -1):
        here = own.filter(F.col("level") == level)
        here = here.unionByName(above) if above is not None else here
        here = here.groupBy("obj_id", "node_id", "level").agg(F.sum("n").alias("n"), F.sum("w").alias("w"))
        out = here if out is None else out.unionByName(here)
        moved = here.join(up.select("node_id", "parent_id", "edge"), "node_id").filter("parent_id IS NOT NULL")
        above = moved.select("obj_id", F.col("parent_id").alias("node_id"), (F.col("level") - 1).alias("level"), "n", (F.col("w") + F.col("edge") * F.col("n")).alias("w"))
    return out


def avg_rollup(leaves: DataFrame, levels: list[str], obj: str = "obj_id") -> DataFrame:
    """Subtree counts of a levelled tree by ROLLUP over its level columns: obj_id, the levels, depth, n."""
    g = leaves.rollup(obj, *levels).agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("g"))
    depth = sum((F.when(F.expr(f"(g & {1 << (len(levels) - 1 - i)}) = 0"), 1).otherwise(0) for i in range(len(levels))), F.lit(0))
    return g.filter(F.col(obj).isNotNull()).select(obj, *levels, depth.alias("depth"), "n")


def spans(build: DataFrame) -> DataFrame:
    """obj_id, n, w (at the root), children, list_id: the single subtree, ``root`` for objects at the root alone, or the
    partition by size ``n=..`` of objects of several subtrees."""
    root = build.filter("level = 0")
    top = build.filter("level = 1").groupBy("obj_id").agg(F.count(F.lit(1)).alias("children"), F.min("node_id").alias("child"), F.sum("n").alias("below"))
    s = root.select("obj_id", "n", "w").join(top, "obj_id", "left")
    groups = F.coalesce("children", F.lit(0)) + (F.coalesce("below", F.lit(0)) < F.col("n")).cast("long")
    name = F.when(groups > 1, F.concat(F.lit("n="), F.col("n").cast("string"))).otherwise(F.coalesce("child", F.lit(ROOT)))
    return s.select("obj_id", "n", "w", groups.cast("long").alias("children"), name.alias("list_id"))
