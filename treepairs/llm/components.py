"""Connected components by alternating large-star and small-star steps over DataFrames."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch

#: Links that one task may join; beyond it the joining goes on in steps over all tasks.
FEW = 1 << 14


class Forest:
    """Union of positions by smallest label, many links at once."""

    def __init__(self, n: int) -> None:
        self.label = np.arange(n)

    def add(self, a: np.ndarray, b: np.ndarray) -> None:
        label = self.label
        while len(a):
            la, lb = label[a], label[b]
            open_ = la != lb
            if not open_.any():
                break
            a, b, la, lb = a[open_], b[open_], la[open_], lb[open_]
            low = np.minimum(la, lb)
            np.minimum.at(label, la, low)
            np.minimum.at(label, lb, low)
            while not np.array_equal(nxt := label[label], label):
                label[:] = nxt


def _stars(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    links = [np.column_stack([x.to_numpy(zero_copy_only=False) for x in batch.columns]) for batch in batches]
    nodes, at = np.unique(np.concatenate([np.empty((0, 2), np.int64), *links]), return_inverse=True)
    forest, at = Forest(len(nodes)), at.reshape(-1, 2)
    forest.add(at[:, 0], at[:, 1])
    yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(nodes[forest.label])], names=["node", "component"])


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def components(edges: DataFrame, a: str = "a", b: str = "b", scratch: Scratch | None = None) -> DataFrame:
    """node, component (the smallest node reachable) for every node that has a link; the links are stars at the end.

    The steps go on until nothing changes. The smallest neighbours are written before they are joined, so that the join
    reads both sides from exchanges and the rows of a hub can be parted among tasks.
    """
    scratch = scratch or Scratch(edges.sparkSession)
    e = scratch.table(edges.select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")).filter("a <> b").distinct())
    before = _state(e)
    if before[0] <= FEW:
        return e.coalesce(1).mapInArrow(_stars, "node long, component long")
    while True:
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = scratch.table(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m")))
        large = both.join(low, "a").filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        small = large.join(large.groupBy("a").agg(F.min("b").alias("m")), "a")
        nxt = scratch.table(small.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(small.select("a", F.col("m").alias("b"))).filter("a <> b").distinct())
        scratch.drop(low, e)
        e, after = nxt, _state(nxt)
        if after == before:
            break
        before = after
    roots = e.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return e.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(roots)
