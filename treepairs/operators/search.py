"""What the searches share: counts, ranks, checkpoints, and the bridge to the sequential engines."""

from __future__ import annotations

import time
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..checkpoints import checkpoint
from ..ontology import ROOT, Ontology
from .objects import known_sizes, placed


class Metrics:
    """Counts and seconds of a search by stage."""

    def __init__(self) -> None:
        self.rows: list[tuple[str, int, int, float]] = []
        self._at = time.perf_counter()

    def add(self, stage: str, pairs: int, round_: int = 0) -> None:
        now = time.perf_counter()
        self.rows.append((stage, round_, int(pairs), now - self._at))
        self._at = now

    def pairs(self, stage: str) -> int:
        return sum(r[2] for r in self.rows if r[0] == stage)

    def frame(self, spark) -> DataFrame:
        from ..schemas import METRICS

        return spark.createDataFrame(self.rows, METRICS)


def ranked(pairs: DataFrame, k: int) -> DataFrame:
    """rank, a, b, dist of the k best in the order (dist, a, b). The window sees k rows only."""
    best = pairs.select("a", "b", "dist").orderBy("dist", "a", "b").limit(k)
    return best.select(F.row_number().over(Window.orderBy("dist", "a", "b")).alias("rank"), "a", "b", "dist")


def answers(found: DataFrame) -> DataFrame:
    return found.filter("a IS NOT NULL").select("a", "b", "dist")


def expand_representatives(best: DataFrame, rep: DataFrame, k: int) -> DataFrame:
    """Pairs of all objects from those of representatives, and the pairs at distance 0 inside a description.

    Only the first k+1 members of a description can be in an answer of k pairs, so no group is expanded beyond that.
    """
    nth = F.row_number().over(Window.partitionBy("rep").orderBy("obj_id"))
    few = rep.withColumn("nth", nth).filter(F.col("nth") <= k + 1)
    x, y = few.select(F.col("rep").alias("ra"), F.col("obj_id").alias("x")), few.select(F.col("rep").alias("rb"), F.col("obj_id").alias("y"))
    cross = best.select(F.col("a").alias("ra"), F.col("b").alias("rb"), "dist").join(x, "ra").join(y, "rb")
    equal = x.join(y, F.col("ra") == F.col("rb")).filter("x < y").select("ra", "rb", F.lit(0.0).alias("dist"), "x", "y")
    both = cross.select("dist", "x", "y").unionByName(equal.select("dist", "x", "y"))
    return both.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "dist")


def item_rows(objects: DataFrame, tree: Ontology, side: int = 0, group: Column | None = None) -> DataFrame:
    """A row for each object with its nodes as arrays, the input of the sequential engines."""
    nodes = placed(objects, tree).filter("level > 0").groupBy("obj_id", "node_id", "level", "w").agg(F.count(F.lit(1)).alias("c"), F.sum("below").alias("d"))
    nodes = nodes.join(tree.nodes.select("node_id", "parent_id"), "node_id")
    lists = nodes.groupBy("obj_id").agg(F.collect_list(F.struct("node_id", "parent_id", "level", "w", "c", "d")).alias("x"))
    return known_sizes(objects, tree).join(lists, "obj_id", "left").select((F.lit(0) if group is None else group).alias("grp"), "obj_id", F.lit(side).alias("side"), "n", "s", "x")


def beyond_sequential(*sets: DataFrame | None) -> bool:
    """Whether one group of these objects is too large for a sequential search."""
    from . import progressive

    ids = [o.select("obj_id").distinct().limit(progressive.MOST_OBJECTS + 1).count() for o in sets if o is not None]
    return sum(ids) > progressive.MOST_OBJECTS


def block_counts(found: DataFrame, k: int, counters: dict[str, str]) -> DataFrame:
    """What :func:`run_sequential` gives, from the block kernel: the answers with the kernel's counts under the given names.

    ``counters``: name to ``bounds``, ``exact`` or ``none`` (null: a count that the kernel does not have).
    """
    found = checkpoint(found)
    total = found.agg(F.coalesce(F.sum("bounds"), F.lit(0)).alias("bounds"), F.coalesce(F.sum("exact"), F.lit(0)).alias("exact"))
    counts = total.select(F.lit(0).alias("grp"), *[(F.lit(None) if c == "none" else F.col(c)).cast("long").alias(name) for name, c in counters.items()])
    best = ranked(answers(found), k)
    return counts.join(best, F.lit(True), "left").select("grp", F.coalesce("rank", F.lit(0)).alias("rank"), "a", "b", "dist", *counters)


def run_sequential(rows: DataFrame, engine: Callable, counters: list[str]) -> DataFrame:
    """grp, rank, a, b, dist and the counters (on every row; a group without pairs gives a row with rank 0)."""
    from .progressive import MOST_OBJECTS, Item

    kinds = [("grp", pa.int32()), ("rank", pa.int32()), ("a", pa.int64()), ("b", pa.int64()), ("dist", pa.float64()), *[(c, pa.int64()) for c in counters]]

    def run(t: pa.Table) -> pa.Table:
        if t.num_rows > MOST_OBJECTS:
            raise ValueError(f"a sequential search takes at most {MOST_OBJECTS} objects a group; use the block engine")
        items = []
        for r in t.to_pylist():
            x = r["x"] or []
            items.append(Item(r["obj_id"], r["n"], r["s"], {v["node_id"]: (v["level"], v["w"], v["c"], v["d"]) for v in x}, r["side"], {v["node_id"]: v["parent_id"] if v["level"] > 1 else ROOT for v in x}))
        items.sort(key=lambda i: (i.side, i.id))
        best, counts = engine(items)
        best = best or [(None, None, None)]
        grp = t.column("grp")[0].as_py()
        cols = [[grp] * len(best), [i + 1 if b[1] is not None else 0 for i, b in enumerate(best)], [b[1] for b in best], [b[2] for b in best], [b[0] for b in best], *[[counts.get(c, 0)] * len(best) for c in counters]]
        return pa.Table.from_arrays([pa.array(c, k) for c, (_, k) in zip(cols, kinds, strict=True)], names=[n for n, _ in kinds])

    schema = "grp int, rank int, a long, b long, dist double" + "".join(f", {c} long" for c in counters)
    return rows.groupBy("grp").applyInArrow(run, schema)


__all__ = ["Metrics", "answers", "beyond_sequential", "block_counts", "checkpoint", "expand_representatives", "item_rows", "ranked", "run_sequential"]
