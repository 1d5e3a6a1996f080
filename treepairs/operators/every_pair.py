"""Distances and bounds of every pair of a set: blocks against blocks, whole cells of numbers inside a task.

Unlike the searches nothing is left out: a cell holds sums over shared nodes for all its pairs, level by level, and gives
either a row for each pair or the counts of the cell.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..checkpoints import checkpoint
from ..ontology import Ontology
from .coded import Coded
from .objects import known_sizes, placed

#: Objects in a block; a cell holds the square of it.
BLOCK_ROWS = 1024
#: Numbers of the side that is sent to all tasks, rows made at once, tasks for each core, and counts of cut trees made at once.
SENT_COUNTS, PAIR_ROWS, PAIR_TASKS, CUT_CELLS = 8_000_000, 1 << 18, 4, 1 << 22
_FAR = np.int64(1) << 60
_LISTS = ("level", "w", "c", "d", "m", "own")


def packed(objects: DataFrame, tree: Ontology) -> DataFrame:
    """obj_id, n and the object's nodes, the root included: count, summed and least distance below, terms at the node
    itself, and the only group below it (null if there are several)."""
    g = placed(objects, tree).groupBy("obj_id", "node_id", "level", "w").agg(F.count(F.lit(1)).alias("c"), F.sum("below").alias("d"), F.min("below").alias("m"), F.count_if(F.col("below") == 0).alias("own"))
    up = tree.nodes.filter("parent_id IS NOT NULL").select("node_id", "parent_id")
    below = g.join(up, "node_id").groupBy("obj_id", F.col("parent_id").alias("node_id")).agg(F.count(F.lit(1)).alias("k"), F.min("node_id").alias("child"))
    g = g.join(below, ["obj_id", "node_id"], "left").withColumn("only", F.when(F.coalesce("k", F.lit(0)) + (F.col("own") > 0).cast("long") <= 1, F.coalesce("child", F.lit("self"))))
    lists = g.groupBy("obj_id").agg(F.collect_list(F.struct("node_id", "only", *_LISTS)).alias("x"))
    return known_sizes(objects, tree).join(lists, "obj_id").select("obj_id", "n", *[F.col(f"x.{name}").alias(name) for name in ("node_id", "only", *_LISTS)])


class Side:
    """The objects of one side of a cell, their nodes sorted by code."""

    def __init__(self, t: pa.Table, codes: dict[str, int]) -> None:
        flat = lambda name: t.column(name).combine_chunks().flatten()
        self.id, self.n = t.column("obj_id").to_numpy(), t.column("n").to_numpy().astype(np.int64)
        number = lambda v: codes.setdefault(v, len(codes)) if v is not None else -1
        code = np.fromiter(map(number, flat("node_id").to_pylist()), np.int64)
        order = np.argsort(code, kind="stable")
        self.code = code[order]
        self.row = np.repeat(np.arange(len(self.id)), np.diff(np.asarray(t.column("node_id").combine_chunks().offsets)))[order]
        self.only = np.fromiter(map(number, flat("only").to_pylist()), np.int64)[order]
        for name in _LISTS:
            setattr(self, name, flat(name).to_numpy(zero_copy_only=False).astype(np.int64)[order])

    def depth(self, level: int) -> np.ndarray:
        """Summed depth of each object's terms on the tree cut at the level."""
        out = np.zeros(len(self.id), np.int64)
        np.add.at(out, self.row, np.where(self.level <= level, self.w * self.c, 0))
        return out


class Cell:
    """All pairs of two sides; ``open`` marks the pairs that count (those above the diagonal of one block, or from it)."""

    def __init__(self, t: pa.Table, scale: int, height: int, diagonal: bool = False) -> None:
        codes: dict[str, int] = {}
        side = t.column("side").to_numpy()
        self.x = Side(t.filter(pa.array(side == 0)), codes)
        one = not (side == 1).any()
        self.y = self.x if one else Side(t.filter(pa.array(side == 1)), codes)
        self.scale, self.height = scale, height
        self.shape = (len(self.x.id), len(self.y.id))
        self.open = np.triu(np.ones(self.shape, bool), int(not diagonal)) if one else np.ones(self.shape, bool)
        self.sizes = np.multiply.outer(self.x.n, self.y.n)
        a, b = np.broadcast_to(self.x.id[:, None], self.shape)[self.open], np.broadcast_to(self.y.id, self.shape)[self.open]
        self.a, self.b = np.minimum(a, b), np.maximum(a, b)

    def shared(self):
        """(at, i, j) for each node on both sides: the place of the pairs and the positions in the two sides."""
        common = np.intersect1d(self.x.code, self.y.code)
        edges = [(np.searchsorted(s.code, common), np.searchsorted(s.code, common, "right")) for s in (self.x, self.y)]
        for k in range(len(common)):
            i, j = (slice(lo[k], hi[k]) for lo, hi in edges)
            rx, ry = self.x.row[i], self.y.row[j]
            whole = len(rx) == self.shape[0] and len(ry) == self.shape[1]
            yield (np.s_[:] if whole and (np.diff(rx) > 0).all() and (np.diff(ry) > 0).all() else np.ix_(rx, ry)), i, j

    def _least(self, i: slice, j: slice, name: str) -> np.ndarray:
        x, y = self.x, self.y
        return np.minimum(np.multiply.outer(getattr(x, name)[i], y.n[y.row[j]]), np.multiply.outer(x.n[x.row[i]], getattr(y, name)[j]))

    def emd(self, levels: tuple[int, ...]) -> list[np.ndarray]:
        """Numerators of the earth mover's distance on the tree cut at each of the levels, over scale * sizes."""
        by = np.zeros((self.height + 1, *self.shape), np.int64)
        for at, i, j in self.shared():
            if 0 < (level := self.x.level[i.start]) <= max(levels):
                by[level][at] += self.x.w[i.start] * self._least(i, j, "c")
        cut = lambda h: np.multiply.outer(self.x.depth(h), self.y.n) + np.multiply.outer(self.x.n, self.y.depth(h)) - 2 * by[: h + 1].sum(axis=0)
        return [cut(h) for h in levels]

    def min(self) -> np.ndarray:
        out = np.full(self.shape, _FAR)
        for at, i, j in self.shared():
            out[at] = np.minimum(out[at], np.add.outer(self.x.m[i], self.y.m[j]))
        return out

    def avg(self, level: int | None = None) -> np.ndarray:
        """Numerators of the average distance; with a level, of its bound with case bounds at the shared nodes there."""
        x, y, height = self.x, self.y, self.height if level is None else level
        out = np.multiply.outer(x.depth(self.height), y.n) + np.multiply.outer(x.n, y.depth(self.height))
        for at, i, j in self.shared():
            here = x.level[i.start]
            if here > height:
                continue
            out[at] -= 2 * x.w[i.start] * np.multiply.outer(x.c[i], y.c[j])
            if level is not None and here == level:
                across = np.multiply.outer(x.d[i], y.c[j]) + np.multiply.outer(x.c[i], y.d[j])
                p, q = (x.only[i] >= 0)[:, None], (y.only[j] >= 0)[None, :]
                same = x.only[i][:, None] == y.only[j][None, :]
                dx, dy = x.d[i][:, None], y.d[j][None, :]
                case = np.select([p & q & same, p & q, p & ~q, ~p & q], [0 * across, across, dx + 0 * dy, dy + 0 * dx], dx + dy)
                out[at] += case - across
        return out

    def avg_cut(self, level: int) -> np.ndarray:
        """Numerators of the average distance on the tree cut at the level."""
        x, y = self.x, self.y
        out = np.multiply.outer(x.depth(level), y.n) + np.multiply.outer(x.n, y.depth(level))
        for at, i, j in self.shared():
            if x.level[i.start] <= level:
                out[at] -= 2 * x.w[i.start] * np.multiply.outer(x.c[i], y.c[j])
        return out

    def half_l1(self, own: bool, factor: float) -> np.ndarray:
        """factor * (1 - shared mass) over all terms (``own``) or the terms of the tree cut at level 1."""
        mass = np.zeros(self.shape, np.int64)
        for at, i, j in self.shared():
            level = self.x.level[i.start]
            if own or level <= 1:
                mass[at] += self._least(i, j, "c" if not own and level == 1 else "own")
        return (self.sizes - mass) / self.sizes * factor


def _cells(rows: DataFrame, objects: DataFrame, run: Callable[[pa.Table], pa.Table], schema: str, block_rows: int) -> DataFrame:
    blocks = max(1, -(-objects.select("obj_id").distinct().count() // block_rows))
    rows = rows.withColumn("block", F.pmod(F.xxhash64("obj_id"), F.lit(blocks)).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    dealt = rows.withColumn("other", other).withColumn("side", (F.col("block") > F.col("other")).cast("int"))
    dealt = dealt.withColumn("x", F.least("block", "other")).withColumn("y", F.greatest("block", "other")).drop("block", "other")
    return dealt.groupBy("x", "y").applyInArrow(run, schema)


def _each_cell(objects: DataFrame, tree: Ontology, measure: Callable[[Cell], pa.Table], schema: str, block_rows: int, diagonal: bool = False) -> DataFrame:
    scale, height = tree.scale, tree.height

    def run(t: pa.Table) -> pa.Table:
        return measure(Cell(t, scale, height, diagonal))

    return _cells(packed(objects, tree), objects, run, schema, block_rows)


def _rows(cell: Cell, **columns: np.ndarray) -> pa.Table:
    return pa.table({"a": cell.a, "b": cell.b} | {name: np.asarray(v[cell.open], np.float64) for name, v in columns.items()})


def emd_ladder(objects: DataFrame, tree: Ontology, levels: tuple[int, ...], block_rows: int = BLOCK_ROWS) -> DataFrame:
    """a, b, and h.. for each level: the distances on the cut trees."""

    def run(c: Cell) -> pa.Table:
        return _rows(c, **{f"h{h}": num / (c.sizes * c.scale) for h, num in zip(levels, c.emd(levels), strict=True)})

    return _each_cell(objects, tree, run, "a long, b long, " + ", ".join(f"h{h} double" for h in levels), block_rows)


def distances(objects: DataFrame, tree: Ontology, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """a, b, emd, avg, min."""

    def run(c: Cell) -> pa.Table:
        den = c.sizes * c.scale
        return _rows(c, emd=c.emd((c.height,))[0] / den, avg=c.avg() / den, min=c.min() / c.scale)

    return _each_cell(objects, tree, run, "a long, b long, emd double, avg double, min double", block_rows)


def _ratio(c: Cell, measure: str) -> np.ndarray:
    if measure == "min":
        return c.min() / c.scale
    return (c.emd((c.height,))[0] if measure == "emd" else c.avg()) / (c.sizes * c.scale)


def matrix(objects: DataFrame, tree: Ontology, measure: str, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """a, b, dist, the diagonal included."""
    return _each_cell(objects, tree, lambda c: _rows(c, dist=_ratio(c, measure)), "a long, b long, dist double", block_rows, diagonal=True)


def nearest(objects: DataFrame, tree: Ontology, measure: str, k: int, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """a, b, dist: the k best of each cell, by the distances of all its pairs."""

    def run(c: Cell) -> pa.Table:
        dist = _ratio(c, measure)[c.open]
        at = np.flatnonzero(dist <= np.partition(dist, k - 1)[k - 1]) if len(dist) > k else np.arange(len(dist))
        at = at[np.lexsort((c.b[at], c.a[at], dist[at]))[:k]]
        return pa.table({"a": c.a[at], "b": c.b[at], "dist": dist[at]})

    return _each_cell(objects, tree, run, "a long, b long, dist double", block_rows)


def avg_reduced(objects: DataFrame, tree: Ontology, level: int, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """a, b, bound, as ``bounds.avg_reduced``. Where the counts of all objects on the cut tree can be sent to all tasks, nothing is
    shuffled by pair; beyond, cells."""
    spark = objects.sparkSession
    coded = Coded.of(tree, spark)
    if coded is not None:
        columns = np.flatnonzero((coded.numbers.value.level > 0) & (coded.numbers.value.level <= level))
        held = checkpoint(_cut_counts(coded, objects, columns))
        if held.count() * (len(columns) + 4) <= SENT_COUNTS:
            return _against_sent(held, coded.numbers.value.w[columns], tree.scale)
    return _each_cell(objects, tree, lambda c: _rows(c, bound=c.avg_cut(level) / (c.sizes * c.scale)), "a long, b long, bound double", block_rows)


def _cut_counts(coded: Coded, objects: DataFrame, columns: np.ndarray) -> DataFrame:
    """obj_id, n, and c: the object's terms below each of the nodes ``columns``. Dealt by object and sorted in a task, so that rows
    that pass together have about the same partners."""
    numbers = coded.numbers

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = np.full(len(numbers.value), -1)
        at[columns] = np.arange(len(columns))
        step = max(1, CUT_CELLS // max(1, len(columns)))
        for whole in batches:
            for b in (whole.slice(lo, step) for lo in range(0, whole.num_rows, step)):
                lists = b.column("terms")
                n = np.diff(np.asarray(lists.offsets))
                of, terms = np.repeat(np.arange(len(n)), n), lists.flatten().to_numpy(zero_copy_only=False)
                c = np.zeros(len(n) * len(columns), np.int64)
                for step_down in range(1, numbers.value.path.shape[1]):
                    node = numbers.value.path[terms, step_down]
                    here = np.flatnonzero((node >= 0) & (at[node] >= 0))
                    c += np.bincount(of[here] * len(columns) + at[node[here]], minlength=len(c))
                c = pa.ListArray.from_arrays(pa.array(np.arange(len(n) + 1) * len(columns), pa.int32()), pa.array(c))
                yield pa.RecordBatch.from_arrays([b.column("obj_id"), pa.array(n.astype(np.int64)), c], names=["obj_id", "n", "c"])

    tasks = PAIR_TASKS * objects.sparkSession.sparkContext.defaultParallelism
    return coded.described(objects).repartition(tasks, "obj_id").sortWithinPartitions("obj_id").mapInArrow(run, "obj_id long, n long, c array<long>")


def _against_sent(held: DataFrame, w: np.ndarray, scale: int) -> DataFrame:
    """a, b, bound of every pair of the held rows: all are sent, and pass against those of greater ids."""

    def arrays(t: pa.Table | pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        c = t.column("c")
        c = (c.combine_chunks() if isinstance(t, pa.Table) else c).flatten()
        return t.column("obj_id").to_numpy(), t.column("n").to_numpy(), c.to_numpy(zero_copy_only=False).reshape(t.num_rows, len(w))

    sent = held.sparkSession.sparkContext.broadcast(arrays(held.sort("obj_id").toArrow()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, m, d = sent.value
        # Sums of integers below 2^53 are exact in double precision, where products of matrices are fast.
        most = 4 * int(m.max(initial=0)) * int((d @ w).max(initial=0))
        kind = np.float64 if max(most, int(m.max(initial=0)) ** 2 * scale) < 1 << 53 else np.int64
        y = np.column_stack([m, d @ w, d]).T.astype(kind)
        m = (m * scale).astype(kind)
        for b in batches:
            a, n, c = arrays(b)
            order = np.argsort(a)
            a, n, c = a[order], n[order], c[order]
            x = np.column_stack([c @ w, n, -2 * w * c]).astype(kind)
            n = n.astype(kind)
            first = np.searchsorted(ids, a, "right")
            lo = 0
            while lo < len(a):
                hi = min(len(a), lo + max(1, PAIR_ROWS // max(1, len(ids) - int(first[lo]))))
                for left in range(int(first[lo]), len(ids), PAIR_ROWS):
                    own = slice(left, left + PAIR_ROWS)
                    bound = (x[lo:hi] @ y[:, own]) / np.multiply.outer(n[lo:hi], m[own])
                    starts = np.clip(first[lo:hi] - left, 0, bound.shape[1])
                    part = [pa.array(np.repeat(a[lo:hi], bound.shape[1] - starts)), pa.array(np.concatenate([ids[own][s:] for s in starts])), pa.array(np.concatenate([r[s:] for r, s in zip(bound, starts, strict=True)]))]
                    yield pa.RecordBatch.from_arrays(part, names=["a", "b", "bound"])
                lo = hi

    return held.mapInArrow(run, "a long, b long, bound double")


def naive(objects: DataFrame, tree: Ontology, measure: str, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """a, b, dist of MIN or AVG by all term pairs, as ``distance.naive``: no counts of subtrees take part."""
    scale, height = tree.scale, tree.height

    def side(t: pa.Table, codes: dict[str, int]) -> tuple[np.ndarray, ...]:
        terms = t.column("paths").combine_chunks()
        paths = terms.flatten()
        starts = np.asarray(terms.offsets)[:-1] - np.asarray(terms.offsets)[0]
        node, depth = np.full((len(paths), height + 1), -1), np.zeros((len(paths), height + 1), np.int64)
        for i, path in enumerate(paths.to_pylist()):
            for level, step in enumerate(path):
                node[i, level], depth[i, level] = codes.setdefault(step["node_id"], len(codes)), step["depth"]
        return t.column("obj_id").to_numpy(), starts, node, depth

    def run(t: pa.Table) -> pa.Table:
        codes: dict[str, int] = {}
        at = t.column("side").to_numpy()
        one = not (at == 1).any()
        xid, xs, xn, xd = side(t.filter(pa.array(at == 0)), codes)
        yid, ys, yn, yd = (xid, xs, xn, xd) if one else side(t.filter(pa.array(at == 1)), codes)
        parts = []
        edges = np.r_[xs, len(xn)]
        for lo in range(0, len(xid), 128):
            rows = slice(edges[lo], edges[min(lo + 128, len(xid))])
            shared = np.zeros((rows.stop - rows.start, len(yn)), np.int64)
            for level in range(1, height + 1):
                met = (xn[rows, level, None] == yn[None, :, level]) & (xn[rows, level, None] >= 0)
                np.copyto(shared, np.broadcast_to(xd[rows, level, None], shared.shape), where=met)
            far = xd[rows].max(axis=1)[:, None] + yd.max(axis=1)[None, :] - 2 * shared
            fold = np.minimum if measure == "min" else np.add
            parts.append(fold.reduceat(fold.reduceat(far, xs[lo : lo + 128] - rows.start, axis=0), ys, axis=1))
        total = np.concatenate(parts) if parts and len(yid) else np.zeros((len(xid), len(yid)), np.int64)
        sizes = np.multiply.outer(np.diff(edges), np.diff(np.r_[ys, len(yn)]))
        dist = total / (scale if measure == "min" else sizes * scale)
        i, j = np.nonzero(np.triu(np.ones(dist.shape, bool), 1) if one else np.ones(dist.shape, bool))
        return pa.table({"a": np.minimum(xid[i], yid[j]), "b": np.maximum(xid[i], yid[j]), "dist": dist[i, j]})

    steps = F.transform("path", lambda p: F.struct(p["node_id"].alias("node_id"), p["depth"].alias("depth")))
    rows = objects.join(tree.paths(), "term_id").groupBy("obj_id").agg(F.collect_list(steps).alias("paths"))
    return _cells(rows, objects, run, "a long, b long, dist double", block_rows)


def avg_descend(objects: DataFrame, tree: Ontology, level: int, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """a, b, bound, as ``bounds.avg_descend``."""
    return _each_cell(objects, tree, lambda c: _rows(c, bound=c.avg(level) / (c.sizes * c.scale)), "a long, b long, bound double", block_rows)


def tightness(objects: DataFrame, tree: Ontology, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """bound, pairs, violations, mean_ratio (over positive distances) of the bounds of the earth mover's distance."""
    reduced, full = min(1.0, tree.least_top_edge / tree.scale), tree.least_edge / tree.scale

    def run(c: Cell) -> pa.Table:
        den = c.sizes * c.scale
        one, two, exact = (num / den for num in c.emd((1, min(2, c.height), c.height)))
        kinds = {"edge_1": one, "edge_2": two, "l1_reduced": c.half_l1(False, reduced), "l1_full": c.half_l1(True, full)}
        exact = exact[c.open]
        positive = exact > 0
        out = []
        for name, bound in kinds.items():
            bound = bound[c.open]
            out.append((name, len(exact), int((bound > exact + 1e-9).sum()), float((bound[positive] / exact[positive]).sum()), int(positive.sum())))
        return pa.table({k: [r[i] for r in out] for i, k in enumerate(("bound", "pairs", "violations", "total", "positive"))})

    cells = _each_cell(objects, tree, run, "bound string, pairs long, violations long, total double, positive long", block_rows)
    total = cells.groupBy("bound").agg(F.sum("pairs").alias("pairs"), F.sum("violations").alias("violations"), F.sum("total").alias("t"), F.sum("positive").alias("p"))
    return total.select("bound", "pairs", "violations", F.when(F.col("p") > 0, F.col("t") / F.col("p")).alias("mean_ratio"))


def sandwich(objects: DataFrame, tree: Ontology, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """pairs, violations of MIN <= EMD <= AVG, compared without a division."""

    def run(c: Cell) -> pa.Table:
        emd = c.emd((c.height,))[0]
        wrong = (c.min() * c.sizes > emd) | (emd > c.avg())
        return pa.table({"pairs": [len(c.a)], "violations": [int(wrong[c.open].sum())]})

    cells = _each_cell(objects, tree, run, "pairs long, violations long", block_rows)
    return cells.agg(F.coalesce(F.sum("pairs"), F.lit(0)).alias("pairs"), F.coalesce(F.sum("violations"), F.lit(0)).alias("violations"))
