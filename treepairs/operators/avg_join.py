"""The k closest pairs under the average distance: Build, then best bounds first."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..ontology import Ontology
from . import dense
from .objects import avg_build, spans
from .progressive import avg_best_first
from .search import Metrics, answers, beyond_sequential, block_counts, checkpoint, item_rows, ranked, run_sequential

COUNTERS = ["pops", "examined", "complete"]


def avgdist_topk(objects: DataFrame, tree: Ontology, k: int = 10, right: DataFrame | None = None, refine: str = "stepwise", order: str = "bfs", engine: str = "auto", metrics: Metrics | None = None, block_rows: int = dense.BLOCK_ROWS) -> DataFrame:
    """rank, a, b, dist. ``refine``: pairs are ordered by the case bounds at the root (``complete``) or by the exact
    across costs at the root as well (``stepwise``) before their distance is computed. ``order`` is that of the sequential
    engine (``bfs`` or ``dfs``); the block kernel has no order of descent and takes ``bfs`` only."""
    if order not in ("bfs", "dfs") or (order == "dfs" and engine != "progressive"):
        raise ValueError(f"order {order} needs the progressive engine")
    if k <= 0:
        return objects.sparkSession.createDataFrame([], "rank int, a long, b long, dist double")
    if engine == "progressive":
        return progressive(objects, tree, k, refine, order, right=right).filter("rank > 0").select("rank", "a", "b", "dist")
    found = dense.search(objects, tree, "avg", k, right, refine=refine, block_rows=block_rows, checkpoint=checkpoint)
    if metrics is not None:
        found = checkpoint(found)
        s = found.agg(F.sum("bounds"), F.sum("exact")).first()
        metrics.add("bounds", s[0] or 0)
        metrics.add("exact", s[1] or 0)
    return ranked(answers(found), k)


def progressive(objects: DataFrame, tree: Ontology, k: int, refine: str = "stepwise", order: str = "bfs", group=None, right: DataFrame | None = None) -> DataFrame:
    """The best-first search; beyond the objects of a sequential search the block kernel, as in ``emd_join.progressive``."""
    if group is None and beyond_sequential(objects, right):
        found = dense.search(objects, tree, "avg", k, right, refine=refine, checkpoint=checkpoint)
        return block_counts(found, k, {"pops": "none", "examined": "bounds", "complete": "exact"})
    scale, height, two = tree.scale, tree.height, right is not None
    rows = item_rows(objects, tree, 0, group)
    if two:
        rows = rows.unionByName(item_rows(right, tree, 1, group))
    return run_sequential(rows, lambda items: avg_best_first(items, k, scale, height, refine, order, two), COUNTERS)


def ordered_lists(objects: DataFrame, tree: Ontology) -> DataFrame:
    """list_id, obj_id, n, w, key, position: the single-span lists by mean depth, the partitions by summed depth."""
    s = spans(avg_build(objects, tree))
    key = F.when(F.col("children") > 1, F.col("w").cast("double")).otherwise(F.col("w") / F.col("n"))
    w = Window.partitionBy("list_id").orderBy("key", "obj_id")
    return s.withColumn("key", key).withColumn("position", F.row_number().over(w)).select("list_id", "obj_id", "n", "w", "children", "key", "position")


def list_pairs(objects: DataFrame, tree: Ontology, theta: float | None = None) -> DataFrame:
    """la, lb, case, head: the bound of the first pair of every two lists, those above ``theta`` left out.

    As many rows as the square of the number of lists (subtrees of the root and distinct sizes), whatever the objects.
    """
    lists = ordered_lists(objects, tree)
    h = lists.groupBy("list_id").agg(F.min("key").alias("key"), F.min_by("n", "position").alias("n"), F.min_by("w", "position").alias("w"), F.max("children").alias("children"), F.count(F.lit(1)).alias("size"), F.collect_list(F.when(F.col("position") <= 2, F.col("key"))).alias("two"))
    a, b = h.select(*[F.col(c).alias(f"a_{c}") for c in h.columns]), h.select(*[F.col(c).alias(f"b_{c}") for c in h.columns])
    p = a.crossJoin(b).filter("a_list_id <= b_list_id AND (a_list_id <> b_list_id OR a_size > 1)")
    sa, sb, c = F.col("a_children") <= 1, F.col("b_children") <= 1, F.col
    case = F.when(sa & sb & (c("a_list_id") == c("b_list_id")), "1a").when(sa & sb, "1b").when(sa | sb, "3").otherwise("2")
    second = F.element_at(F.sort_array("a_two"), 2)
    w2 = F.when(c("a_list_id") == c("b_list_id"), second).otherwise(c("b_w"))
    head = F.when(case == "1a", 0.0).when(case == "1b", c("a_key") + c("b_key")).when(case == "3", F.when(sa, c("a_key") / c("b_n")).otherwise(c("b_key") / c("a_n"))).otherwise((c("a_w") + w2) / (c("a_n") * c("b_n")))
    out = p.select(c("a_list_id").alias("la"), c("b_list_id").alias("lb"), case.alias("case"), (head / F.lit(float(tree.scale))).alias("head"))
    return out if theta is None else out.filter(F.col("head") <= F.lit(theta))
