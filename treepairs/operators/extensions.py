"""Range joins, nearest neighbours, keyword search, several trees, clustering."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import ratio
from ..ontology import Ontology
from . import dense
from .distance import DISTANCES
from .min_join import nearest
from .objects import subtree_minima
from .search import answers, checkpoint, ranked


def range_join(objects: DataFrame, tree: Ontology, radius: float, measure: str = "emd", right: DataFrame | None = None) -> DataFrame:
    """a, b, dist of all pairs at most ``radius`` apart.

    MIN is joined on nodes, where an object within the radius is near: a node takes part with objects that are within the
    radius of it. EMD and AVG run in the block kernel under their bounds.
    """
    if measure == "min":
        limit = int(radius * tree.scale + 1e-9)
        near = subtree_minima(objects, tree).filter(F.col("dist") <= limit)
        x = near.select("node_id", F.col("obj_id").alias("a"), F.col("dist").alias("da"))
        other = near if right is None else subtree_minima(right, tree).filter(F.col("dist") <= limit)
        y = other.select("node_id", F.col("obj_id").alias("b"), F.col("dist").alias("db"))
        both = x.join(y, "node_id").filter(F.col("da") + F.col("db") <= limit)
        both = both.filter("a < b") if right is None else both
        return both.groupBy("a", "b").agg(ratio(F.min(F.col("da") + F.col("db")), F.lit(tree.scale)).alias("dist"))
    return answers(dense.search(objects, tree, measure, None, right, radius=radius, checkpoint=checkpoint))


def knn(objects: DataFrame, tree: Ontology, queries: DataFrame, k: int = 5, measure: str = "emd") -> DataFrame:
    """query, rank, b, dist: for each query object its k nearest of the objects, itself left out where it is one.

    A cell of the kernel gives the k+1 best of each of its queries, one more for the query itself.
    """
    found = answers(dense.search(queries, tree, measure, k + 1, objects, per_left=True, checkpoint=checkpoint)).filter("a <> b") if measure != "min" else _min_to(queries, objects, tree, k)
    w = Window.partitionBy("a").orderBy("dist", "b")
    return found.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select(F.col("a").alias("query"), "rank", "b", "dist")


def _min_to(queries: DataFrame, objects: DataFrame, tree: Ontology, k: int) -> DataFrame:
    """a, b, dist of the queries and the first k+1 objects of each node that they touch, itself left out.

    The distance to one of the k nearest is met at a node where it is among the first k+1: k others at least would be before
    it in the order otherwise. So a node's rows number (queries below it) x (k+1), whatever the objects.
    """
    x = subtree_minima(queries, tree).select("node_id", F.col("obj_id").alias("a"), F.col("dist").alias("da"))
    y = nearest(subtree_minima(objects, tree), k + 1).select("node_id", F.col("obj_id").alias("b"), F.col("dist").alias("db"))
    return x.join(y, "node_id").filter("a <> b").groupBy("a", "b").agg(ratio(F.min(F.col("da") + F.col("db")), F.lit(tree.scale)).alias("dist"))


def keyword_search(objects: DataFrame, tree: Ontology, term: str, k: int = 10) -> DataFrame:
    """rank, obj_id, dist: objects with the keyword first, then those with the nearest terms."""
    path = tree.nodes.filter(F.col("node_id") == term).select("depth", F.explode("path").alias("s")).select(F.col("s.node_id").alias("node_id"), (F.col("depth") - F.col("s.depth")).alias("up"))
    d = subtree_minima(objects, tree).join(F.broadcast(path), "node_id").groupBy("obj_id").agg(F.min(F.col("dist") + F.col("up")).alias("num"))
    best = d.select("obj_id", ratio(F.col("num"), F.lit(tree.scale)).alias("dist")).orderBy("dist", "obj_id").limit(k)
    return best.select(F.row_number().over(Window.orderBy("dist", "obj_id")).alias("rank"), "obj_id", "dist")


def multi_topk(sets: list[tuple[DataFrame, Ontology]], k: int = 10, agg: str = "sum", measure: str = "emd", weights: list[float] | None = None, depth: int | None = None) -> DataFrame:
    """The k best pairs over several trees by threshold aggregation: rank, a, b, dist.

    Each tree gives its best ``depth`` pairs in order (sorted access); missing distances of the pairs met are looked up
    (random access). The search ends when the kth aggregate is at most that of the last distances seen; until then the
    depth is doubled. Objects that lack a description in one of the trees are left out.
    """
    weights = weights or [1.0] * len(sets)
    combine = {"sum": lambda xs: reduce(lambda p, q: p + q, xs), "max": lambda xs: F.greatest(*xs), "wavg": lambda xs: reduce(lambda p, q: p + q, [F.lit(w) * x for w, x in zip(weights, xs, strict=True)]) / F.lit(sum(weights))}[agg]
    plain = {"sum": sum, "max": max, "wavg": lambda v: sum(w * x for w, x in zip(weights, v, strict=True)) / sum(weights)}[agg]
    common = reduce(lambda x, y: x.join(y, "obj_id", "left_semi"), [o.select("obj_id").distinct() for o, _ in sets])
    common = checkpoint(common)
    sets = [(o.join(common, "obj_id", "left_semi"), t) for o, t in sets]
    n = common.count()
    everything = n * (n - 1) // 2
    size = depth or max(64, 8 * k)
    while True:
        lists = [checkpoint(answers(dense.search(o, t, measure, size, checkpoint=checkpoint)).orderBy("dist", "a", "b").limit(size)) for o, t in sets]
        met = checkpoint(reduce(DataFrame.unionByName, [x.select("a", "b") for x in lists]).distinct())
        full = met
        for i, (o, t) in enumerate(sets):
            full = full.join(DISTANCES[measure](met, o, t).select("a", "b", F.col("dist").alias(f"d{i}")), ["a", "b"])
        best = checkpoint(full.withColumn("dist", combine([F.col(f"d{i}") for i in range(len(sets))])).orderBy("dist", "a", "b").limit(k))
        bottom = [x.agg(F.max("dist")).first()[0] for x in lists]
        kth = [r[0] for r in best.select("dist").orderBy("dist").collect()]
        if size >= everything or (len(kth) == k and all(b is not None for b in bottom) and kth[-1] < plain(bottom)):
            return ranked(best, k)
        size = min(everything, 4 * size)


def single_link(objects: DataFrame, tree: Ontology, cut: float) -> DataFrame:
    """obj_id, cluster (its smallest object): single linkage under MIN, joined at distances up to ``cut``.

    Objects near one node are linked in a star to the smallest of the nearest, never to each other; labels then spread
    along the stars until nothing changes.
    """
    limit = int(cut * tree.scale + 1e-9)
    near = subtree_minima(objects, tree).filter(F.col("dist") <= limit)
    w = Window.partitionBy("node_id").orderBy("dist", "obj_id")
    hub = near.withColumn("nth", F.row_number().over(w)).filter("nth = 1").select("node_id", F.col("obj_id").alias("hub"), F.col("dist").alias("hd"))
    # Whoever is linked to anyone at this node is linked to its nearest object.
    links = near.join(hub, "node_id").filter((F.col("dist") + F.col("hd") <= limit) & (F.col("obj_id") != F.col("hub"))).select(F.col("obj_id").alias("x"), F.col("hub").alias("y")).distinct()
    links = checkpoint(links.unionByName(links.select(F.col("y").alias("x"), F.col("x").alias("y"))).distinct())
    label = checkpoint(objects.select("obj_id").distinct().withColumn("cluster", F.col("obj_id")))
    while True:
        heard = links.join(label, F.col("x") == F.col("obj_id")).groupBy("y").agg(F.min("cluster").alias("m"))
        step = label.join(heard, F.col("obj_id") == F.col("y"), "left").select("obj_id", F.least("cluster", "m").alias("cluster"), F.col("cluster").alias("was"))
        jump = step.select(F.col("obj_id").alias("cluster"), F.col("cluster").alias("up"))
        step = checkpoint(step.join(jump, "cluster").select("obj_id", F.least("cluster", "up").alias("cluster"), "was"))
        if step.filter("cluster <> was").isEmpty():
            return step.select("obj_id", "cluster")
        label = step.select("obj_id", "cluster")
