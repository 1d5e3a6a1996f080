"""Choices that are made from statistics, at the level of DataFrames."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..ontology import Ontology
from ..operators.objects import subtree_counts

#: Cells of array work that one task may hold (objects of a block times nodes of the bound).
CELL_BUDGET = 64 << 20
#: Sets up to this size may be searched by the sequential engines.
SEQUENTIAL = 1_000


@dataclass(frozen=True)
class Statistics:
    objects: int
    annotations: int
    terms: int
    height: int
    nodes_by_level: dict[int, int]
    objects_of_hottest: dict[int, int]


@dataclass(frozen=True)
class Plan:
    engine: str
    bound_height: int
    block_rows: int
    broadcast_tree: bool


def statistics(objects: DataFrame, tree: Ontology) -> Statistics:
    """One pass over the annotations and one over the tree."""
    s = objects.agg(F.approx_count_distinct("obj_id").alias("n"), F.count(F.lit(1)).alias("d")).first()
    levels = {r.level: r.n for r in tree.nodes.groupBy("level").agg(F.count(F.lit(1)).alias("n")).collect()}
    hot = subtree_counts(objects, tree).groupBy("level", "node_id").agg(F.count(F.lit(1)).alias("n")).groupBy("level").agg(F.max("n").alias("m")).collect()
    return Statistics(s.n, s.d, sum(levels.values()), tree.height, levels, {r.level: r.m for r in hot})


def choose(s: Statistics, measure: str) -> Plan:
    """Bound on as many levels as fit the array budget, deeper ones exactly on what is left; MIN needs no kernel."""
    from ..ontology import BROADCAST_ROWS

    if measure == "min":
        return Plan("closure", 0, 0, s.terms <= BROADCAST_ROWS)
    block, height, nodes = 1024, 0, 0
    for level in range(1, s.height + 1):
        nodes += s.nodes_by_level.get(level, 0)
        if nodes * block > CELL_BUDGET // 256:
            break
        height = level
    return Plan("blocks" if s.objects > 2 else "progressive", max(1, height), block, s.terms <= BROADCAST_ROWS)


def pair_work(s: Statistics) -> dict[int, int]:
    """Rows that an equi-join on nodes would make at the hottest node of each level: why the top levels go to arrays."""
    return {level: m * (m - 1) // 2 for level, m in s.objects_of_hottest.items()}
