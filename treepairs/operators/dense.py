"""The block kernel: pairs of blocks of objects, compared with arrays inside a task.

Objects are packed to one row each and dealt into blocks that lie close together in the cut tree. A cell is a pair of
blocks; cells whose boxes are further apart than the threshold are never made. Inside a cell a bound is computed for all
pairs at once, exact distances follow in the order of the bound, and only the answers leave the task.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.columns import ratio
from ..ontology import Ontology
from .classes import Classes, expanded
from .coded import Coded, Numbers
from .objects import placed

#: Objects in a block; a cell holds at most the square of it.
BLOCK_ROWS = 1024
#: Slack for bounds that are computed in floating point.
EPS = 1e-5
ANSWERS = "a long, b long, num long, den long, dist double, bounds long, exact long"


@dataclass(frozen=True)
class Spec:
    measure: str
    k: int | None
    radius: float | None
    scale: int
    height: int
    #: emd: levels of the bound; avg: 0 for the case bounds, 1 for one descent more.
    bound_height: int
    two_sided: bool
    theta: float = float("inf")
    #: factor and kind of the bound: ``edge`` (weighted), ``l1`` (half L1 over reduced terms), ``none``.
    variant: str = "edge"
    factor: float = 1.0
    #: Keep the k best of each left object instead of the cell's.
    per_left: bool = False


def packed(objects: DataFrame, tree: Ontology, measure: str, side: int = 0) -> DataFrame:
    """obj_id, side, n, s, single, home, share, self and the object's nodes as parallel arrays. One row of the root holds n
    and s; ``self`` is the distance of an object to an equal one."""
    rows = placed(objects, tree).groupBy("obj_id", "node_id", "level", "w").agg(F.count(F.lit(1)).alias("k"), F.sum("below").alias("t"), F.min("below").alias("m"))
    if measure == "min":
        rows = rows.select("obj_id", "node_id", "level", F.lit(0).cast("long").alias("w"), F.col("m").alias("c"), F.lit(0).cast("long").alias("d"), "k", "t")
    else:
        rows = rows.select("obj_id", "node_id", "level", "w", F.col("k").alias("c"), F.col("t").alias("d"), "k", "t")
    top = F.when(F.col("level") == 1, F.struct(F.col("k").alias("c"), F.col("node_id").alias("v")))
    item = F.struct("level", "node_id", "w", "c", "d")
    item = item if measure == "min" else F.when(F.col("level") > 0, item)
    at_root = lambda name: F.max(F.when(F.col("level") == 0, F.col(name))).alias(name)
    g = rows.groupBy("obj_id").agg(F.sort_array(F.collect_list(item)).alias("x"), F.count_if(F.col("level") == 1).alias("tops"), F.sum(F.when(F.col("level") == 1, F.col("k"))).alias("below"), F.max(top).alias("most"), at_root("k"), at_root("t"), F.sum(F.when(F.col("level") > 0, F.col("w") * F.col("k") * F.col("k")).otherwise(0)).alias("q"))
    g = g.withColumnsRenamed({"k": "n", "t": "s"})
    groups = F.coalesce("tops", F.lit(0)) + (F.coalesce("below", F.lit(0)) < F.col("n")).cast("long")
    empty = lambda name, kind: F.coalesce(F.col(f"x.{name}"), F.array().cast(f"array<{kind}>")).alias(name)
    own = ratio(2 * F.col("n") * F.col("s") - 2 * F.col("q"), F.col("n") * F.col("n") * F.lit(tree.scale)) if measure == "avg" else F.lit(0.0)
    return g.select(
        "obj_id", F.lit(side).alias("side"), "n", "s", (groups <= 1).alias("single"), F.coalesce(F.col("most.v"), F.lit("")).alias("home"),
        (F.coalesce("most.c", F.lit(0)) / F.col("n")).alias("share"), own.alias("self"), empty("level", "int"), empty("node_id", "string"), empty("w", "bigint"), empty("c", "bigint"), empty("d", "bigint"),
    )


class Block:
    """The objects of one side of a cell as arrays."""

    def __init__(self, t: pa.Table, codes: dict[str, int] | Numbers) -> None:
        if isinstance(codes, Numbers):
            x = Coded.arrays(t, codes)
            self.id, self.n, self.s, self.single, self.home, self.row = (x[c] for c in ("id", "n", "s", "single", "home", "row"))
            self.node, self.level, self.w, self.c, self.d = (x[c] for c in ("node", "level", "w", "c", "d"))
            self.at = np.searchsorted(self.row, np.arange(len(self.id) + 1))
            return
        col = lambda n: t.column(n).combine_chunks()
        self.id, self.n, self.s = (col(c).to_numpy(zero_copy_only=False) for c in ("obj_id", "n", "s"))
        self.single = col("single").to_numpy(zero_copy_only=False)
        self.home = np.array([codes.setdefault(h, len(codes)) for h in col("home").to_pylist()])
        nodes = col("node_id")
        self.at = np.asarray(nodes.offsets)
        self.at = self.at - self.at[0]
        d = nodes.flatten().dictionary_encode()
        table = np.array([codes.setdefault(v, len(codes)) for v in d.dictionary.to_pylist()] or [0])
        self.node = table[d.indices.to_numpy(zero_copy_only=False)] if len(d) else np.empty(0, int)
        self.level, self.w, self.c, self.d = (col(c).flatten().to_numpy(zero_copy_only=False).astype(np.int64) for c in ("level", "w", "c", "d"))
        self.row = np.repeat(np.arange(len(self.id)), np.diff(self.at))

    def matrix(self, keep: np.ndarray, columns: np.ndarray) -> np.ndarray:
        out = np.zeros((len(self.id), len(columns)))
        where = np.flatnonzero(keep & np.isin(self.node, columns))
        out[self.row[where], np.searchsorted(columns, self.node[where])] = self.c[where]
        return out


def _bounds(x: Block, y: Block, spec: Spec) -> np.ndarray:
    """A lower bound for every pair of the cell."""
    out = np.zeros((len(x.id), len(y.id)), np.float32)
    if spec.measure == "emd" and spec.variant != "none":
        keep_x, keep_y = x.level <= spec.bound_height, y.level <= spec.bound_height
        nodes, first = np.unique(np.concatenate([x.node[keep_x], y.node[keep_y]]), return_index=True)
        level = np.concatenate([x.level[keep_x], y.level[keep_y]])[first]
        weight = np.concatenate([x.w[keep_x], y.w[keep_y]])[first] / spec.scale
        a, b = x.matrix(keep_x, nodes) / x.n[:, None], y.matrix(keep_y, nodes) / y.n[:, None]
        if spec.variant == "l1":  # masses of the reduced terms: those at the bound height, and the root with the rest
            top = level == spec.bound_height
            weight = np.full(int(top.sum()) + 1, spec.factor / 2)
            a = np.column_stack([a[:, top], 1 - a[:, top].sum(axis=1)])
            b = np.column_stack([b[:, top], 1 - b[:, top].sum(axis=1)])
        a, b = (a * weight).astype(np.float32), (b * weight).astype(np.float32)
        for v in range(a.shape[1]):
            out += np.abs(a[:, v, None] - b[None, :, v])
    elif spec.measure == "avg" and spec.variant != "none":
        n, m = x.n[:, None], y.n[None, :]
        wx, wy = x.s[:, None], y.s[None, :]
        sx, sy = x.single[:, None], y.single[None, :]
        same = x.home[:, None] == y.home[None, :]
        total = np.select([sx & sy & same, sx & sy, sx & ~sy, ~sx & sy], [0 * n * m, m * wx + n * wy, wx + 0 * m, wy + 0 * n], wx + wy)
        if spec.bound_height:  # across costs at the root, exact: all distances via the root less those in shared subtrees
            keep_x, keep_y = x.level == 1, y.level == 1
            nodes = np.unique(np.concatenate([x.node[keep_x], y.node[keep_y]]))
            a, b = x.matrix(keep_x, nodes), y.matrix(keep_y, nodes)
            da, db = _depths(x, nodes), _depths(y, nodes)
            total = np.maximum(total, m * wx + n * wy - da @ b.T - a @ db.T)
        out = (total / (n * m * spec.scale)).astype(np.float32)
    return out


def _depths(x: Block, tops: np.ndarray) -> np.ndarray:
    """Summed distance to the root of the terms below each level-1 node."""
    out = np.zeros((len(x.id), len(tops)))
    at = np.flatnonzero(x.level == 1)
    out[x.row[at], np.searchsorted(tops, x.node[at])] = x.d[at] + x.w[at] * x.c[at]
    return out


def exact_numbers(x: Block, y: Block, i: np.ndarray, j: np.ndarray, spec: Spec, codes: int) -> tuple[np.ndarray, np.ndarray]:
    """num, den of the pairs (i, j): the rows of the partners are met with one dense row of each left object."""
    order = np.argsort(i, kind="stable")
    num = np.zeros(len(i), np.int64)
    edges = np.flatnonzero(np.r_[True, np.diff(i[order]) != 0, True]) if len(i) else []
    far = np.int64(1) << 60
    row = np.full(codes, far if spec.measure == "min" else 0, np.int64)
    for lo, hi in zip(edges[:-1], edges[1:], strict=True):
        at = order[lo:hi]
        left = int(i[at[0]])
        own = slice(x.at[left], x.at[left + 1])
        row[x.node[own]] = x.c[own]
        partners = j[at]
        lengths = y.at[partners + 1] - y.at[partners]
        starts = np.cumsum(lengths) - lengths
        where = np.arange(int(lengths.sum())) - np.repeat(starts - y.at[partners], lengths)
        mine, theirs = row[y.node[where]], y.c[where]
        if spec.measure == "min":
            num[at] = np.minimum.reduceat(mine + theirs, starts)
        else:
            if spec.measure == "emd":
                part = y.w[where] * np.minimum(mine * np.repeat(y.n[partners], lengths), theirs * x.n[left])
            else:
                part = y.w[where] * mine * theirs
            sums = np.r_[0, np.cumsum(part)]
            shared = sums[starts + lengths] - sums[starts]
            num[at] = y.n[partners] * x.s[left] + x.n[left] * y.s[partners] - 2 * shared
        row[x.node[own]] = far if spec.measure == "min" else 0
    den = np.full(len(i), spec.scale, np.int64) if spec.measure == "min" else x.n[i] * y.n[j] * spec.scale
    return num, den


def _best_of_each(x: Block, y: Block, bound: np.ndarray, spec: Spec, codes: int) -> tuple[tuple[np.ndarray, ...], int]:
    """For each left object its k best partners by (distance, id), and the number of exact distances."""
    limit = np.full(len(x.id), np.inf)
    left = np.arange(bound.size)
    flat, size, exact = bound.ravel(), max(4096, 2 * (spec.k or 1) * len(x.id)), 0
    best = tuple(np.empty(0, np.int64) for _ in range(5)) + (np.empty(0),)
    while len(left):
        if len(left) > size:
            near = np.argpartition(flat[left], size)
            take, left = left[near[:size]], left[near[size:]]
        else:
            take, left = left, left[:0]
        i, j = take // len(y.id), take % len(y.id)
        num, den = exact_numbers(x, y, i, j, spec, codes)
        exact += len(i)
        found = (i, x.id[i], y.id[j], num, den, num / den)
        best = tuple(np.concatenate(p) for p in zip(best, found, strict=True))
        order = np.lexsort((best[2], best[5], best[0]))
        best = tuple(f[order] for f in best)
        first = np.searchsorted(best[0], best[0])
        keep = np.arange(len(order)) - first < spec.k
        best = tuple(f[keep] for f in best)
        starts, counts = np.unique(best[0], return_index=True, return_counts=True)[1:]
        full = counts == spec.k
        limit[best[0][starts[full]]] = best[5][starts[full] + spec.k - 1]
        left = left[flat[left] <= limit[left // len(y.id)] + EPS]
    return best[1:], exact


def cell(t: pa.Table, spec: Spec, numbers: Numbers | None = None) -> pa.Table:
    """The answers of a cell, and a row of its counts with null ids."""
    side = t.column("side").to_numpy()
    codes: dict[str, int] | Numbers = {} if numbers is None else numbers
    one_block = not (side == 1).any() and not spec.two_sided
    x = Block(t.filter(pa.array(side == 0)), codes)
    y = x if one_block else Block(t.filter(pa.array(side == 1)), codes)
    out: list[tuple[np.ndarray, ...]] = []
    exact = total = 0
    theta = spec.radius if spec.radius is not None else spec.theta
    if len(x.id) and len(y.id):
        bound = _bounds(x, y, spec)
        if one_block:
            bound[np.tril_indices(len(x.id))] = np.inf
        total = int(np.isfinite(bound).sum())
        if spec.per_left:
            found, exact = _best_of_each(x, y, bound, spec, len(codes))
            out.append(found)
        left = np.empty(0, int) if spec.per_left else np.flatnonzero(np.isfinite(bound.ravel()) & (bound.ravel() <= theta + EPS))
        size = max(4096, 4 * (spec.k or 0))
        if spec.radius is not None:
            size = max(size, 1 << 18)
        best = None
        while len(left):
            values = bound.ravel()[left]
            if len(left) > size:
                near = np.argpartition(values, size)
                take, left = left[near[:size]], left[near[size:]]
            else:
                take, left = left, left[:0]
            i, j = take // len(y.id), take % len(y.id)
            num, den = exact_numbers(x, y, i, j, spec, len(codes))
            exact += len(i)
            a, b = x.id[i], y.id[j]
            if not spec.two_sided:
                a, b = np.minimum(a, b), np.maximum(a, b)
            found = (a, b, num, den, num / den)
            ok = found[4] <= theta
            found = tuple(f[ok] for f in found)
            if spec.k is None:
                out.append(found)
                continue
            best = found if best is None else tuple(np.concatenate(p) for p in zip(best, found, strict=True))
            order = np.lexsort((best[1], best[0], best[4]))[: spec.k]
            best = tuple(f[order] for f in best)
            if len(best[0]) == spec.k:
                theta = min(theta, float(best[4][-1]))
                left = left[bound.ravel()[left] <= theta + EPS]
            size = min(2 * size, 1 << 17)
        if best is not None:
            out.append(best)
    cols = [np.concatenate([o[i] for o in out]) if out else np.empty(0, np.int64) for i in range(5)]
    return answer_table(cols, total, exact)


def answer_table(cols: list[np.ndarray] | tuple[np.ndarray, ...], total: int, exact: int) -> pa.Table:
    """Answers a, b, num, den, dist, and a row of the counts with null ids."""
    n = len(cols[0])
    data = [pa.array(np.r_[c, 0], mask=np.r_[np.zeros(n, bool), True]) for c in cols[:4]] + [pa.array(np.r_[cols[4].astype(float), 0.0], mask=np.r_[np.zeros(n, bool), True])]
    counts = [pa.array(np.r_[np.zeros(n, np.int64), v]) for v in (total, exact)]
    return pa.Table.from_arrays(data + counts, names=["a", "b", "num", "den", "dist", "bounds", "exact"])


def _blocks(rows: DataFrame, block_rows: int, measure: str = "emd") -> tuple[DataFrame, int]:
    """Adds ``block``: ranges of about ``block_rows`` objects in the order of home subtree and its share; for AVG in that of
    the distance to an equal object, since two objects are at least the mean of theirs apart."""
    n = rows.count()
    g = max(1, -(-n // block_rows))
    if g == 1:
        return rows.withColumn("block", F.lit(0)), 1
    dealt = rows.repartitionByRange(g, *(("self", "obj_id") if measure == "avg" else ("home", "share", "obj_id")))
    return dealt.withColumn("block", F.spark_partition_id()), g


def _answered(dealt: DataFrame, spec: Spec, coded: Coded | None) -> DataFrame:
    if coded is None:
        return dealt.groupBy("key").applyInArrow(lambda t: cell(t, spec), ANSWERS)
    numbers = coded.numbers
    return dealt.select("key", "obj_id", "side", "terms").groupBy("key").applyInArrow(lambda t: cell(t, spec, numbers.value), ANSWERS)


def _run(rows: DataFrame, cells: Column, spec: Spec, coded: Coded | None = None) -> DataFrame:
    dealt = rows.withColumn("cell", F.explode(cells)).withColumn("side", F.col("cell.side")).withColumn("key", F.col("cell.key")).drop("cell", "block", "share", "self")
    return _answered(dealt, spec, coded)


def _boxes(rows: DataFrame, coded: Coded | None = None) -> DataFrame:
    """block, and for each level-1 node the least and greatest share over the block's objects."""
    item = F.explode(F.arrays_zip("level", "node_id", "w", "c")).alias("i")
    tops = coded.tops(rows) if coded else rows.select("block", "side", "obj_id", "n", item).filter("i.level = 1").select("block", "side", F.col("i.node_id").alias("v"), F.col("i.w").alias("w"), (F.col("i.c") / F.col("n")).alias("f"))
    total = rows.groupBy("block", "side").agg(F.count(F.lit(1)).alias("objects"))
    box = tops.groupBy("block", "side", "v", "w").agg(F.min("f").alias("lo"), F.max("f").alias("hi"), F.count(F.lit(1)).alias("k")).join(total, ["block", "side"])
    box = box.select("block", "side", "v", "w", F.when(F.col("k") < F.col("objects"), 0.0).otherwise(F.col("lo")).alias("lo"), "hi")
    entry = F.struct("v", F.struct("lo", "hi", "w").alias("r"))
    return total.select("block", "side").join(box.groupBy("block", "side").agg(F.map_from_entries(F.collect_list(entry)).alias("box")), ["block", "side"], "left")


def _cells(rows: DataFrame, spec: Spec, theta: float, diagonal: bool, coded: Coded | None = None) -> DataFrame:
    """x, y: pairs of blocks whose boxes are at most ``theta`` apart. Rows grow with the number of blocks only."""
    if spec.measure == "avg" and spec.variant != "none" and np.isfinite(theta):
        least = rows.groupBy("side", "block").agg(F.min("self").alias("least"))
        x = least.filter("side = 0").select(F.col("block").alias("x"), F.col("least").alias("lx"))
        y = least.filter(f"side = {1 if spec.two_sided else 0}").select(F.col("block").alias("y"), F.col("least").alias("ly"))
        pairs = x.crossJoin(y).filter((F.col("lx") + F.col("ly")) / 2 <= F.lit(theta + EPS))
        return (pairs if spec.two_sided else pairs.filter("x <= y" if diagonal else "x < y")).select("x", "y")
    boxes = _boxes(rows, coded)
    x = boxes.filter("side = 0").select(F.col("block").alias("x"), F.col("box").alias("bx"))
    y = boxes.filter(f"side = {1 if spec.two_sided else 0}").select(F.col("block").alias("y"), F.col("box").alias("by"))
    pairs = x.crossJoin(y)
    if not spec.two_sided:
        pairs = pairs.filter("x <= y" if diagonal else "x < y")
    if spec.measure != "emd" or not np.isfinite(theta):
        return pairs.select("x", "y")
    none = F.create_map().cast("map<string,struct<lo:double,hi:double,w:bigint>>")
    lo = lambda r: F.coalesce(r["lo"], F.lit(0.0))
    hi = lambda r: F.coalesce(r["hi"], F.lit(0.0))
    gap = F.map_zip_with(F.coalesce("bx", none), F.coalesce("by", none), lambda _, p, q: F.coalesce(p["w"], q["w"]) * F.greatest(F.lit(0.0), lo(p) - hi(q), lo(q) - hi(p)))
    bound = F.aggregate(F.map_values(gap), F.lit(0.0), lambda s, v: s + v) / F.lit(float(spec.scale))
    return pairs.filter(bound <= F.lit(theta + EPS)).select("x", "y")


def search(objects: DataFrame, tree: Ontology, measure: str, k: int | None = None, right: DataFrame | None = None, radius: float | None = None, bound_height: int | None = None, variant: str = "edge", refine: str = "stepwise", block_rows: int = BLOCK_ROWS, per_left: bool = False, checkpoint=None) -> DataFrame:
    """Rows of ANSWERS: at least the k best pairs or all pairs within the radius, and the counts.

    A set of one block is one cell. Of larger sets equal descriptions are searched once; a small side of two is sent to all
    tasks; the k best pairs of one set by the earth mover's distance are searched in passes (:mod:`.passed`); the rest is dealt
    into cells.
    """
    if bound_height is None:
        bound_height = min(tree.height, 2) if measure == "emd" else int(refine == "stepwise")
    factor = min(1.0, tree.least_top_edge / tree.scale)
    spec = Spec(measure, k, radius, tree.scale, tree.height, bound_height, right is not None, variant=variant, factor=factor, per_left=per_left)
    coded = Coded.of(tree, objects.sparkSession) if checkpoint and variant != "none" and measure != "min" else None
    sets = [o for o in (objects, right) if o is not None]
    if coded:  # each set is made once and kept as one row of numbers an object
        held = [coded.described(o) for o in sets]
        if per_left:  # the side that passes is dealt evenly
            held[1] = held[1].repartition(2 * objects.sparkSession.sparkContext.defaultParallelism, "obj_id")
        held = [checkpoint(h) for h in held]
        made = [coded.rows(o, measure, i) for i, o in enumerate(held)]
        many = any(o.count() > block_rows for o in held)
    else:
        made = [packed(o, tree, measure, i) for i, o in enumerate(sets)]
        many = any(_objects(o, block_rows + 1) > block_rows for o in sets)
    if not checkpoint or not many or variant == "none" or measure == "min":
        return _searched(made[0], made[1] if right is not None else None, spec, block_rows, checkpoint, coded)
    if per_left:
        if _sendable(made[0], coded):
            return streamed(made[0], made[1], spec, True, coded)
        return _searched(made[0], made[1], spec, block_rows, checkpoint, coded)

    def kept(classes: Classes, at: int, where: Column | None = None) -> DataFrame:
        """The rows of one object for each class."""
        return classes.kept(made[at], where) if coded else packed(classes.kept(sets[at], where), tree, measure, at)

    left = Classes.of(made[0], checkpoint)
    if right is not None:
        other = Classes.of(made[1], checkpoint)
        x, y = kept(left, 0), kept(other, 1)
        found = None
        if radius is None and _sendable(y, coded):
            found = streamed(y, x, spec, False, coded)
        elif radius is None and _sendable(x, coded):
            found = streamed(x, y, spec, True, coded)
        found = _searched(x, y, spec, block_rows, checkpoint, coded) if found is None else found
        return _joined(checkpoint(found), left, k, radius, other)
    theta = float("inf") if radius is None else radius
    if k is not None:
        inside, theta = left.inside(k)
        if inside == k and theta == 0:
            return _joined(None, left, k, None)
    where = None
    if measure == "avg":
        if k is not None:  # the objects that are closest to equal ones give a first kth distance
            first = left.table.orderBy("self", "rep").limit(block_rows).select(F.col("rep").alias("obj_id"))
            few = made[0].join(F.broadcast(first), "obj_id", "left_semi") if coded else packed(objects.join(F.broadcast(first), "obj_id", "left_semi"), tree, measure)
            theta = min(theta, kth(_searched(few, None, spec, block_rows, checkpoint, coded), k))
        least = left.table.agg(F.min("self")).first()[0]
        if least is not None and np.isfinite(theta):
            where = F.col("self") <= F.lit(2 * theta - least + EPS)
    found = _searched(kept(left, 0, where), None, replace(spec, theta=theta), block_rows, checkpoint, coded)
    return _joined(checkpoint(found), left, k, radius)


def _objects(objects: DataFrame, most: int) -> int:
    return objects.select("obj_id").distinct().limit(most).count()


def _sendable(rows: DataFrame, coded: Coded | None = None) -> bool:
    from .streamed import SENT_NODES

    # All levels below the root, at most.
    nodes = F.size("terms") * coded.height + 1 if coded else F.size("node_id") + 1
    return (rows.agg(F.sum(nodes)).first()[0] or 0) <= SENT_NODES


def streamed(*args) -> DataFrame:
    from . import streamed as module

    return module.streamed(*args)


def _joined(found: DataFrame | None, left: Classes, k: int | None, radius: float | None, right: Classes | None = None) -> DataFrame:
    """Rows of ANSWERS over all objects from those over classes."""
    none = F.lit(None).cast("long")
    pairs = None if found is None else found.filter("a IS NOT NULL").select("a", "b", "dist")
    out = expanded(pairs, left, k, radius, right).select("a", "b", none.alias("num"), none.alias("den"), "dist", F.lit(0).cast("long").alias("bounds"), F.lit(0).cast("long").alias("exact"))
    return out if found is None else out.unionByName(found.filter("a IS NULL"))


def _searched(objects: DataFrame, right: DataFrame | None, spec: Spec, block_rows: int, checkpoint, coded: Coded | None = None) -> DataFrame:
    """The cells of packed rows, or of the rows of a numbered tree."""
    k, radius = spec.k, spec.radius
    if coded and checkpoint and right is None and k is not None and spec.measure == "emd" and spec.variant == "edge":
        from .passed import searched

        if (found := searched(objects, spec, coded, block_rows, checkpoint)) is not None:
            return found
    rows, g = _blocks(objects, block_rows, spec.measure)
    if right is not None:
        other, h = _blocks(right, block_rows, spec.measure)
        rows = rows.unionByName(other)
        g = max(g, h)
    key = lambda x, y: F.concat_ws("-", x, y)
    if g == 1:
        return _run(rows, F.array(F.struct(F.col("side"), F.lit("0-0").alias("key"))), spec, coded)
    rows = checkpoint(rows) if checkpoint else rows
    done = None
    if right is None:
        done = _run(rows, F.array(F.struct(F.lit(0).alias("side"), key(F.col("block").cast("string"), F.col("block").cast("string")).alias("key"))), spec, coded)
        done = checkpoint(done) if checkpoint else done
        theta = radius if radius is not None else min(spec.theta, kth(done, k))
    else:
        theta = radius if radius is not None else spec.theta
    spec = replace(spec, theta=theta)
    cells = _cells(rows, spec, theta, False, coded)
    side_y = 1 if right is not None else 0
    plan = cells.select(F.explode(F.array(F.struct(F.col("x").alias("block"), F.lit(0).alias("from"), F.lit(0).alias("side"), key(F.col("x").cast("string"), F.col("y").cast("string")).alias("key")), F.struct(F.col("y").alias("block"), F.lit(side_y).alias("from"), F.lit(1).alias("side"), key(F.col("x").cast("string"), F.col("y").cast("string")).alias("key")))).alias("p")).select("p.*")
    lists = plan.groupBy("block", "from").agg(F.collect_list(F.struct("side", "key")).alias("cells"))
    cross = rows.withColumnRenamed("side", "from").join(lists, ["block", "from"])
    rest = _dealt(cross, spec, coded)
    return rest if done is None else done.unionByName(rest)


def _dealt(cross: DataFrame, spec: Spec, coded: Coded | None = None) -> DataFrame:
    dealt = cross.withColumn("cell", F.explode("cells")).withColumn("side", F.col("cell.side")).withColumn("key", F.col("cell.key")).drop("cell", "cells", "block", "share", "self", "from")
    return _answered(dealt, spec, coded)


def kth(answers: DataFrame, k: int) -> float:
    """The kth distance so far, or infinity: k rows at most reach the driver."""
    rows = answers.filter("a IS NOT NULL").orderBy("dist", "a", "b").limit(k).select("dist").collect()
    return float(rows[-1][0]) if len(rows) == k else float("inf")


