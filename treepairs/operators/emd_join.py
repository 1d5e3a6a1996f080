"""The k closest pairs under the earth mover's distance."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..ontology import Ontology
from . import dense
from .objects import dedupe_objects
from .progressive import emd_reduced_first, emd_threshold
from .search import Metrics, answers, beyond_sequential, block_counts, checkpoint, expand_representatives, item_rows, ranked, run_sequential

COUNTERS = ["calls", "new", "bounds", "full_l1", "emd", "most_calls"]
VARIANTS = ("edge", "l1_reduced", "l1_full", "emd_reduced", "brute")


def emd_topk(objects: DataFrame, tree: Ontology, k: int = 10, right: DataFrame | None = None, variant: str = "edge", h: int | None = None, engine: str = "auto", dedupe: bool = False, curated: bool = False, metrics: Metrics | None = None, block_rows: int = dense.BLOCK_ROWS) -> DataFrame:
    """rank, a, b, dist.

    ``variant``: the bound that orders and filters pairs. ``edge``: EMD of the cut tree by its closed form; ``l1_reduced``:
    half L1 over the reduced terms; ``l1_full``: over all terms; ``emd_reduced``: as ``edge`` at height 1; ``brute``: none.
    ``dedupe``: search among distinct descriptions of one set and expand afterwards, the same answers (two sets are searched
    as they are); ``curated``: leave repeated descriptions out of each set, as for the published data.
    """
    if variant not in VARIANTS:
        raise ValueError(variant)
    if k <= 0:
        return objects.sparkSession.createDataFrame([], "rank int, a long, b long, dist double")
    if curated and right is not None:
        objects, right = dedupe_objects(objects)[0], dedupe_objects(right)[0]
    if engine == "progressive":
        return progressive(objects, tree, k, right, variant, h or 1).filter("rank > 0").select("rank", "a", "b", "dist")
    if (dedupe or curated) and right is None:
        kept, rep = dedupe_objects(objects)
        if dedupe and not curated:  # equal descriptions are at 0, distinct ones are not
            zero = expand_representatives(kept.sparkSession.createDataFrame([], "a long, b long, dist double"), rep, k)
            if zero.limit(k).count() == k:
                return ranked(zero, k)
        best = emd_topk(kept, tree, k, None, variant, h, engine, metrics=metrics, block_rows=block_rows)
        return best if curated else ranked(expand_representatives(best, rep, k), k)
    found = _blocks(objects, tree, k, right, variant, h, block_rows)
    if metrics is not None:
        found = checkpoint(found)
        s = found.agg(F.sum("bounds"), F.sum("exact")).first()
        metrics.add("bounds", s[0] or 0)
        metrics.add("exact", s[1] or 0)
    return ranked(answers(found), k)


def _blocks(objects: DataFrame, tree: Ontology, k: int, right: DataFrame | None, variant: str, h: int | None, block_rows: int) -> DataFrame:
    height = {"edge": h or min(tree.height, 2), "l1_reduced": h or 1, "l1_full": tree.height, "emd_reduced": h or 1, "brute": 0}[variant]
    kind = {"edge": "edge", "emd_reduced": "edge", "l1_reduced": "l1", "l1_full": "l1", "brute": "none"}[variant]
    return dense.search(objects, tree, "emd", k, right, bound_height=height, variant=kind, block_rows=block_rows, checkpoint=checkpoint)


def progressive(objects: DataFrame, tree: Ontology, k: int, right: DataFrame | None = None, variant: str = "l1_reduced", h: int = 1, halved: bool = True, group=None) -> DataFrame:
    """The threshold search with a heap for each dimension; a row for each answer with the counters.

    One group of more objects than a sequential search takes goes to the block kernel: the same answers, its counts of
    bounds and distances, and no counts (null) of what it does not do.
    """
    if group is None and halved and beyond_sequential(objects, right):
        found = _blocks(objects, tree, k, right, variant, h, dense.BLOCK_ROWS)
        return block_counts(found, k, {c: {"new": "bounds", "bounds": "bounds", "emd": "exact"}.get(c, "none") for c in COUNTERS})
    rows = item_rows(objects, tree, 0, group)
    if right is not None:
        rows = rows.unionByName(item_rows(right, tree, 1, group))
    scale, two = tree.scale, right is not None
    least = tree.least_edge / tree.scale
    factor = least if variant == "l1_full" else min(1.0, tree.least_top_edge / tree.scale if h == 1 else least)
    if variant in ("emd_reduced", "brute"):
        height = h if variant == "emd_reduced" else 0
        return run_sequential(rows, lambda items: emd_reduced_first(items, k, scale, height, two), COUNTERS)
    return run_sequential(rows, lambda items: emd_threshold(items, k, scale, variant, h, factor, least, two, halved), COUNTERS)
