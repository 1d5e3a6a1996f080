"""The transport problem behind the earth mover's distance: the reference solver and the flows themselves."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..ontology import Ontology


def transport(cost: list[list[int]], supply: list[int], demand: list[int]) -> tuple[int, list[tuple[int, int, int]]]:
    """(least cost, flows) of an integer transport problem, by successive shortest paths with potentials."""
    n, m = len(supply), len(demand)
    flow = [[0] * m for _ in range(n)]
    left, need = list(supply), list(demand)
    up, down = [0] * n, [0] * m
    while any(left):
        dist, via, done = {}, {}, set()
        heap = [(0, 0, i) for i in range(n) if left[i]]
        dist.update({(0, i): 0 for _, _, i in heap})
        heapq.heapify(heap)
        goal = None
        while heap:
            d, side, v = heapq.heappop(heap)
            if (side, v) in done:
                continue
            done.add((side, v))
            if side and need[v] and goal is None:
                goal = v
            steps = ((1, j, cost[v][j] + up[v] - down[j]) for j in range(m)) if side == 0 else ((0, i, -cost[i][v] + down[v] - up[i]) for i in range(n) if flow[i][v])
            for s, x, extra in steps:
                if d + extra < dist.get((s, x), 1 << 62):
                    dist[s, x] = d + extra
                    via[s, x] = (side, v)
                    heapq.heappush(heap, (d + extra, s, x))
        for (s, x), d in dist.items():
            if s:
                down[x] += d
            else:
                up[x] += d
        path, at = [], (1, goal)
        while at in via:
            path.append((via[at], at))
            at = via[at]
        amount = min([left[at[1]], need[goal], *[flow[b[1]][a[1]] for a, b in path if a[0]]])
        for a, b in path:
            if a[0]:
                flow[b[1]][a[1]] -= amount
            else:
                flow[a[1]][b[1]] += amount
        left[at[1]] -= amount
        need[goal] -= amount
    moved = [(i, j, flow[i][j]) for i in range(n) for j in range(m) if flow[i][j]]
    return sum(cost[i][j] * f for i, j, f in moved), moved


def path_distance(p: list[tuple[str, int]], q: list[tuple[str, int]]) -> int:
    """Scaled distance of two nodes given as (node, depth) paths."""
    shared = 0
    for (x, d), (y, _) in zip(p, q, strict=False):
        if x != y:
            break
        shared = d
    return p[-1][1] + q[-1][1] - 2 * shared


def solve(pa_: list, pb_: list) -> tuple[int, list[tuple[int, int, int]]]:
    cost = [[path_distance(p, q) for q in pb_] for p in pa_]
    return transport(cost, [len(pb_)] * len(pa_), [len(pa_)] * len(pb_))


def _with_paths(pairs: DataFrame, objects: DataFrame, tree: Ontology, right: DataFrame | None) -> DataFrame:
    def lists(o: DataFrame, name: str, key: str) -> DataFrame:
        slim = F.struct("term_id", F.transform("path", lambda s: F.struct(s["node_id"], s["depth"])).alias("steps"))
        return o.join(tree.paths(), "term_id").groupBy(F.col("obj_id").alias(key)).agg(F.sort_array(F.collect_list(slim)).alias(name))

    return pairs.join(lists(objects, "ta", "a"), "a").join(lists(objects if right is None else right, "tb", "b"), "b")


def _steps(terms: list) -> list:
    return [[tuple(s.values()) if isinstance(s, dict) else tuple(s) for s in (t["steps"] if isinstance(t, dict) else t.steps)] for t in terms]


def emd_by_flow(pairs: DataFrame, objects: DataFrame, tree: Ontology, right: DataFrame | None = None) -> DataFrame:
    scale = tree.scale

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = batch.to_pylist()
            num, den = [], []
            for r in rows:
                x, y = _steps(r["ta"]), _steps(r["tb"])
                num.append(solve(x, y)[0])
                den.append(len(x) * len(y) * scale)
            yield pa.RecordBatch.from_arrays([pa.array([r["a"] for r in rows], pa.int64()), pa.array([r["b"] for r in rows], pa.int64()), pa.array(num, pa.int64()), pa.array(den, pa.int64()), pa.array([n / d for n, d in zip(num, den, strict=True)], pa.float64())], names=["a", "b", "num", "den", "dist"])

    return _with_paths(pairs, objects, tree, right).select("a", "b", "ta", "tb").mapInArrow(run, "a long, b long, num long, den long, dist double")


@udtf(returnType="p string, q string, flow long, cost long")
class BestFlow:
    """The matching of two objects: how much of the mass of each term moves to which term, in units of 1/(na*nb)."""

    def eval(self, ta, tb):
        x, y = _steps(ta), _steps(tb)
        for i, j, f in solve(x, y)[1]:
            yield x[i][-1][0], y[j][-1][0], f, f * path_distance(x[i], y[j])


def emd_flow(pairs: DataFrame, objects: DataFrame, tree: Ontology, right: DataFrame | None = None) -> DataFrame:
    """a, b, p, q, flow, cost (scaled)."""
    spark = pairs.sparkSession
    spark.udtf.register("best_flow", BestFlow)
    both = _with_paths(pairs, objects, tree, right)
    return spark.sql("SELECT a, b, f.p, f.q, f.flow, f.cost FROM {both}, LATERAL best_flow(ta, tb) f", both=both)
