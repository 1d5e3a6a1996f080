"""Objects as arrays of term numbers: what is kept and shuffled is one integer for each term.

The nodes of a tree of bounded size are numbered in the order of a descent and sent to all tasks with their paths. In that
order the terms of an object, sorted once, are sorted at every level, so its nodes and counts are runs of one array.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..ontology import Ontology

#: Nodes of a tree up to which it is numbered; larger ones keep the rows of :func:`..dense.packed`.
CODED_NODES = 400_000
ROWS = "obj_id long, side int, home int, share double, self double, key binary, terms array<int>"
TOPS = "block int, side int, obj_id long, v string, w long, f double"


@dataclass(frozen=True)
class Numbers:
    """The numbered tree: the node of each node's path at each level (-1 beyond its own), and level, edge and depth."""

    path: np.ndarray
    level: np.ndarray
    w: np.ndarray
    depth: np.ndarray
    scale: int

    def __len__(self) -> int:
        return len(self.level)


class Coded:
    """The numbers of a tree as a broadcast, and term_id, code as a table."""

    def __init__(self, spark, numbers: Numbers, names: list[str]) -> None:
        self.numbers, self.height = spark.sparkContext.broadcast(numbers), numbers.path.shape[1] - 1
        self.codes = spark.createDataFrame(pa.table({"term_id": pa.array(names, pa.string()), "code": pa.array(np.arange(len(names)), pa.int32())}))

    @staticmethod
    def of(tree: Ontology, spark) -> Coded | None:
        """None where the tree has more than CODED_NODES nodes."""
        t = tree.nodes.select("node_id", F.col("path.node_id").alias("path"), "level", "w", "depth").limit(CODED_NODES + 1).toArrow()
        if t.num_rows > CODED_NODES:
            return None
        paths = t.column("path").to_pylist()
        order = sorted(range(len(paths)), key=paths.__getitem__)
        code = {paths[i][-1]: n for n, i in enumerate(order)}
        path = np.full((len(order), tree.height + 1), -1, np.int32)
        for n, i in enumerate(order):
            path[n, : len(paths[i])] = [code[v] for v in paths[i]]
        level, w, depth = (t.column(c).to_numpy().astype(np.int64)[order] for c in ("level", "w", "depth"))
        return Coded(spark, Numbers(path, level, w, depth, tree.scale), [paths[i][-1] for i in order])

    def described(self, objects: DataFrame) -> DataFrame:
        """obj_id and the numbers of its terms in order; terms that the tree lacks are left out."""
        rows = objects.join(F.broadcast(self.codes), "term_id")
        return rows.groupBy("obj_id").agg(F.sort_array(F.collect_list("code")).alias("terms"))

    def rows(self, described: DataFrame, measure: str, side: int = 0) -> DataFrame:
        """ROWS: the description with its main subtree and the share of it, the distance to an equal object, and a SHA-256."""
        numbers = self.numbers

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if not b.num_rows:
                    continue
                x = Coded.arrays(pa.Table.from_batches([b]), numbers.value)
                own = np.zeros(len(x["id"]))
                if measure == "avg":
                    q = np.bincount(x["row"], x["w"] * x["c"] * x["c"], len(own)).astype(np.int64)
                    own = (2 * x["n"] * x["s"] - 2 * q) / (x["n"] * x["n"] * numbers.value.scale)
                terms, at = x["terms"], x["starts"]
                keys = [hashlib.sha256(terms[lo:hi].tobytes()).digest() for lo, hi in zip(at[:-1], at[1:], strict=True)]
                data = [pa.array(x["id"]), pa.array(np.full(len(own), side, np.int32)), pa.array(x["home"].astype(np.int32)), pa.array(x["most"] / x["n"]), pa.array(own), pa.array(keys, pa.binary()), pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.array(terms))]
                yield pa.RecordBatch.from_arrays(data, names=["obj_id", "side", "home", "share", "self", "key", "terms"])

        return described.mapInArrow(run, ROWS)

    def tops(self, rows: DataFrame) -> DataFrame:
        """TOPS: the share of each object in each level-1 node that it touches."""
        numbers = self.numbers

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                x = Coded.arrays(pa.Table.from_batches([b]), numbers.value)
                at = np.flatnonzero(x["level"] == 1)
                row = x["row"][at]
                block, side = (b.column(c).to_numpy(zero_copy_only=False)[row] for c in ("block", "side"))
                data = [pa.array(block, pa.int32()), pa.array(side, pa.int32()), pa.array(x["id"][row]), pa.array(x["node"][at].astype(str), pa.string()), pa.array(x["w"][at]), pa.array(x["c"][at] / x["n"][row])]
                yield pa.RecordBatch.from_arrays(data, names=["block", "side", "obj_id", "v", "w", "f"])

        return rows.select("block", "side", "obj_id", "terms").mapInArrow(run, TOPS)

    @staticmethod
    def arrays(t: pa.Table, tree: Numbers) -> dict[str, np.ndarray]:
        """The nodes of the objects as parallel arrays, those of one object next to each other; n, s, the main subtree (home),
        its terms (most), and whether all terms lie in one (single)."""
        lists = t.column("terms").combine_chunks()
        starts = np.asarray(lists.offsets).astype(np.int64) if len(t) else np.zeros(1, np.int64)
        starts = starts - starts[0]
        terms = lists.flatten().to_numpy(zero_copy_only=False).astype(np.int32)
        objects = len(t)
        of = np.repeat(np.arange(objects), np.diff(starts))
        depth = tree.depth[terms]
        row, node, c, d = [], [], [], []
        for level in range(1, tree.path.shape[1]):
            at = tree.path[terms, level]
            here = np.flatnonzero(at >= 0)
            if not len(here):
                continue
            v, o = at[here], of[here]
            first = np.flatnonzero(np.r_[True, (v[1:] != v[:-1]) | (o[1:] != o[:-1])])
            row.append(o[first])
            node.append(v[first])
            c.append(np.diff(np.r_[first, len(v)]))
            d.append(np.add.reduceat(depth[here], first) - c[-1] * tree.depth[v[first]])
        join = lambda parts: np.concatenate(parts).astype(np.int64) if parts else np.empty(0, np.int64)
        row, node, c, d = join(row), join(node), join(c), join(d)
        order = np.argsort(row, kind="stable")
        row, node, c, d = row[order], node[order], c[order], d[order]
        out = {"id": t.column("obj_id").combine_chunks().to_numpy(zero_copy_only=False), "terms": terms, "starts": starts, "row": row, "node": node, "c": c, "d": d, "level": tree.level[node], "w": tree.w[node]}
        out["n"] = np.diff(starts)
        out["s"] = np.bincount(of, depth, objects).astype(np.int64)
        top = np.flatnonzero(out["level"] == 1)
        tops, below = np.bincount(row[top], minlength=objects), np.bincount(row[top], c[top], objects)
        out["single"] = tops + (below < out["n"]) <= 1
        home, most = np.full(objects, -1, np.int64), np.zeros(objects, np.int64)
        by = top[np.lexsort((node[top], c[top], row[top]))]  # the last of an object is its main subtree
        home[row[by]], most[row[by]] = node[by], c[by]
        out["home"], out["most"] = home, most
        return out
