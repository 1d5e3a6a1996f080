"""The k closest pairs under the minimum distance: short lists at the nodes, no pair of objects is looked at twice."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import list_length, ratio
from ..ontology import Ontology
from .objects import subtree_minima
from .search import checkpoint, ranked


def nearest(minima: DataFrame, m: int, by: tuple[str, ...] = ("node_id",)) -> DataFrame:
    """The first ``m`` objects of each node by (dist, obj_id); the cut runs before the shuffle as well."""
    w = Window.partitionBy(*by).orderBy("dist", "obj_id")
    return minima.withColumn("nth", F.row_number().over(w)).filter(F.col("nth") <= m)


def node_pairs(lists: DataFrame, k: int, right: DataFrame | None = None) -> DataFrame:
    """a, b, d: at each node the k best sums of two list entries.

    A pair at the positions (p, q) of sorted lists has at least all pairs at lower positions before it, ties included, so
    it is among the k best only if those number at most k. That leaves about k log k rows a node, not the square.
    """
    x = lists.select("node_id", F.col("obj_id").alias("x"), F.col("dist").alias("dx"), F.col("nth").alias("p"))
    other = lists if right is None else right
    y = other.select("node_id", F.col("obj_id").alias("y"), F.col("dist").alias("dy"), F.col("nth").alias("q"))
    both = x.join(y, "node_id")
    if right is None:
        both = both.filter((F.col("p") < F.col("q")) & (F.col("p") * F.col("q") - F.col("p") * (F.col("p") + 1) / 2 <= k))
        a, b = F.least("x", "y"), F.greatest("x", "y")
    else:
        both = both.filter(F.col("p") * F.col("q") <= k)
        a, b = F.col("x"), F.col("y")
    sums = both.select("node_id", a.alias("a"), b.alias("b"), (F.col("dx") + F.col("dy")).alias("d"))
    w = Window.partitionBy("node_id").orderBy("d", "a", "b")
    return sums.withColumn("r", F.row_number().over(w)).filter(F.col("r") <= k).select("node_id", "a", "b", "d")


def mindist_topk(objects: DataFrame, tree: Ontology, k: int = 10, right: DataFrame | None = None, list_len: str = "safe", engine: str = "closure") -> DataFrame:
    """rank, a, b, dist. ``closure``: all levels at once; ``levels``: bottom-up, with lists cut at every node.
    ``list_len='sqrt'`` is the published length, which can miss pairs."""
    if k <= 0:
        return objects.sparkSession.createDataFrame([], "rank int, a long, b long, dist double")
    m = list_length(k, list_len)
    if engine == "levels":
        if right is not None:
            raise ValueError("the level engine takes one set")
        pairs = _by_levels(objects, tree, k, m)
    else:
        lists = nearest(subtree_minima(objects, tree), m)
        other = None if right is None else nearest(subtree_minima(right, tree), m)
        pairs = node_pairs(lists, k, other)
    den = F.lit(tree.scale).cast("long")
    return ranked(pairs.groupBy("a", "b").agg(ratio(F.min("d"), den).alias("dist")), k)


def _by_levels(objects: DataFrame, tree: Ontology, k: int, m: int) -> DataFrame:
    up = tree.nodes.select("node_id", "parent_id", "level", "w")
    own = objects.join(up.withColumnRenamed("node_id", "term_id"), "term_id").select(F.col("term_id").alias("node_id"), "obj_id", "level", F.lit(0).cast("long").alias("dist"))
    near, pairs = None, None
    w = Window.partitionBy("node_id").orderBy("d", "a", "b")
    for level in range(tree.height, -1, -1):
        here = own.filter(F.col("level") == level).select("node_id", "obj_id", "dist")
        if near is not None:
            here = here.unionByName(near).groupBy("node_id", "obj_id").agg(F.min("dist").alias("dist"))
        lists = nearest(here, m)
        found = node_pairs(lists, k)
        if pairs is not None:
            found = found.unionByName(pairs)
        found = found.groupBy("node_id", "a", "b").agg(F.min("d").alias("d")).withColumn("r", F.row_number().over(w)).filter(F.col("r") <= k).drop("r")
        if level == 0:
            return found
        edge = up.filter(F.col("level") == level)
        state = checkpoint(lists.join(edge, "node_id").select(F.col("parent_id").alias("node_id"), "obj_id", (F.col("dist") + F.col("w")).alias("dist")))
        near = state.groupBy("node_id", "obj_id").agg(F.min("dist").alias("dist"))
        pairs = checkpoint(found.join(edge, "node_id").select(F.col("parent_id").alias("node_id"), "a", "b", "d"))
    return found


def list_sizes(objects: DataFrame, tree: Ontology, k: int, list_len: str = "safe") -> DataFrame:
    """level, nodes, most, kept: the space that the lists take."""
    lists = nearest(subtree_minima(objects, tree), list_length(k, list_len))
    g = lists.groupBy("level", "node_id").agg(F.count(F.lit(1)).alias("n"))
    return g.groupBy("level").agg(F.count(F.lit(1)).alias("nodes"), F.max("n").alias("most"), F.sum("n").alias("kept"))
