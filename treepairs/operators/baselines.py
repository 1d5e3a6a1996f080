"""What the searches are compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..ontology import Ontology
from . import dense, every_pair
from .classes import Classes, expanded
from .distance import DISTANCES, all_pairs
from .emd_join import emd_topk
from .search import answers, checkpoint, ranked


def brute_force(objects: DataFrame, tree: Ontology, measure: str, k: int = 10, engine: str = "blocks") -> DataFrame:
    """All pairs, then the k best. ``blocks``: every distance in the block kernel, without bounds; ``join``: by joins on
    nodes inside cells, equal descriptions as one; ``flow``: EMD as a transport problem, the published way."""
    if engine == "blocks":
        found = dense.search(objects, tree, measure, k, variant="none", bound_height=0, checkpoint=checkpoint)
        return ranked(answers(found), k)
    if engine == "flow":
        return ranked(DISTANCES["emd"](all_pairs(objects), objects, tree, solver="flow"), k)
    if measure == "min":
        return ranked(every_pair.nearest(objects, tree, measure, k), k)
    classes = Classes.of(dense.packed(objects, tree, measure), checkpoint)
    return ranked(expanded(checkpoint(every_pair.nearest(classes.kept(objects), tree, measure, k)), classes, k), k)


def emd_reduced_topk(objects: DataFrame, tree: Ontology, k: int = 10, h: int = 1, metrics=None) -> DataFrame:
    """EMD on the cut tree for all pairs, exact EMD only where that is at most the kth."""
    return emd_topk(objects, tree, k, variant="emd_reduced", h=h, metrics=metrics)
