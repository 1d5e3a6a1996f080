"""Pairs of one-dimensional values in the order of their gaps."""

from __future__ import annotations

import heapq
from collections import Counter
from collections.abc import Iterator

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf


def adjacent_gaps(values: DataFrame) -> DataFrame:
    """dim, a, b, gap of neighbours in the order (value, id); ``values``: dim, id, value."""
    w = Window.partitionBy("dim").orderBy("value", "id")
    v = values.withColumn("nv", F.lead("value").over(w)).withColumn("ni", F.lead("id").over(w)).filter("ni IS NOT NULL")
    return v.select("dim", F.least("id", "ni").alias("a"), F.greatest("id", "ni").alias("b"), (F.col("nv") - F.col("value")).alias("gap"))


def gaps_within(values: DataFrame, tau: float) -> DataFrame:
    """All pairs of a dimension with a gap of at most ``tau``: an equi-join on buckets of that width."""
    if tau <= 0:
        x, y = values.select("dim", "value", F.col("id").alias("a")), values.select("dim", "value", F.col("id").alias("b"))
        return x.join(y, ["dim", "value"]).filter("a < b").select("dim", "a", "b", F.lit(0.0).alias("gap"))
    slot = F.floor(F.col("value") / F.lit(tau))
    x = values.select("dim", F.col("id").alias("a"), F.col("value").alias("va"), F.explode(F.array(slot - 1, slot, slot + 1)).alias("slot"))
    y = values.select("dim", F.col("id").alias("b"), F.col("value").alias("vb"), slot.alias("slot"))
    near = x.join(y, ["dim", "slot"]).filter("a < b").withColumn("gap", F.abs(F.col("va") - F.col("vb")))
    return near.filter(F.col("gap") <= F.lit(tau)).select("dim", "a", "b", "gap")


def ordered_pairs(values: DataFrame, limit: int, init: str = "sort") -> DataFrame:
    """The first ``limit`` pairs of each dimension: dim, nth, a, b, gap in the order (gap, a, b).

    The limit-th adjacent gap bounds nothing by itself, but among the first ``limit`` pairs none has a gap above the
    limit-th smallest of the adjacent ones, where there are so many; fewer values have few pairs and all are made.
    ``hash``: equal values are met in buckets first.
    """
    if init == "hash":
        equal = gaps_within(values, 0.0)
        one = values.groupBy("dim", "value").agg(F.min("id").alias("id"))
        far = _first(one, limit)
        x, y = values.select("dim", F.col("id").alias("x"), F.col("value").alias("vx")), values.select("dim", F.col("id").alias("y"), F.col("value").alias("vy"))
        reps = far.join(one.select("dim", F.col("id").alias("a"), F.col("value").alias("vx")), ["dim", "a"]).join(one.select("dim", F.col("id").alias("b"), F.col("value").alias("vy")), ["dim", "b"])
        cross = reps.select("dim", "vx", "vy", "gap").join(x, ["dim", "vx"]).join(y, ["dim", "vy"])
        found = equal.unionByName(cross.select("dim", F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "gap"))
    elif init == "sort":
        found = _first(values, limit)
    else:
        raise ValueError(init)
    w = Window.partitionBy("dim").orderBy("gap", "a", "b")
    return found.withColumn("nth", F.row_number().over(w)).filter(F.col("nth") <= limit).select("dim", "nth", "a", "b", "gap")


def _first(values: DataFrame, limit: int) -> DataFrame:
    """Pairs of each dimension that are among its first ``limit``, and some more."""
    rank = Window.partitionBy("dim").orderBy("gap")
    adjacent = adjacent_gaps(values)
    count = values.groupBy("dim").agg(F.count(F.lit(1)).alias("n"), (F.max("value") - F.min("value")).alias("width"))
    edge = adjacent.withColumn("r", F.row_number().over(rank)).filter(F.col("r") == limit).select("dim", F.col("gap").alias("edge"))
    tau = count.join(edge, "dim", "left").select("dim", F.coalesce("edge", "width").alias("tau"))
    v = values.join(tau, "dim")
    width = F.greatest(F.col("tau"), F.lit(1e-12))
    slot = F.floor(F.col("value") / width)
    x = v.select("dim", F.col("id").alias("a"), F.col("value").alias("va"), "tau", F.explode(F.array(slot - 1, slot, slot + 1)).alias("slot"))
    y = v.select("dim", F.col("id").alias("b"), F.col("value").alias("vb"), slot.alias("slot"))
    near = x.join(y, ["dim", "slot"]).filter("a < b").withColumn("gap", F.abs(F.col("va") - F.col("vb")))
    return near.filter(F.col("gap") <= F.col("tau")).select("dim", "a", "b", "gap").distinct()


@udtf(returnType="nth int, a long, b long, gap double")
class OrderedGaps:
    """A lazy stream of the first pairs of a partition: TABLE(values) PARTITION BY dim ORDER BY value, and a limit."""

    def __init__(self):
        self.rows, self.limit = [], 0

    def eval(self, row, limit):
        self.rows.append((row["value"], row["id"]))
        self.limit = limit

    def terminate(self):
        yield from first_gaps(self.rows, self.limit)


def first_gaps(values: list[tuple[float, int]], limit: int) -> Iterator[tuple[int, int, int, float]]:
    """nth, a, b, gap of the first pairs in the order (gap, a, b).

    The stream is in the order of the gap alone, so it is read to the end of the last gap that counts. Of equal values only
    the first ``limit`` + 1 ids can be in an answer: the rest is left out before pairs are made.
    """
    from .progressive import GapStream

    seen: Counter[float] = Counter()
    few = []
    for value, i in sorted(values):
        seen[value] += 1
        if seen[value] <= limit + 1:
            few.append((value, i))
    last: list[float] = []

    def near() -> Iterator[tuple[float, int, int]]:
        for gap, a, b in GapStream(few):
            if len(last) >= limit and gap > last[-1]:
                return
            if len(last) < limit:
                last.append(gap)
            yield float(gap), min(a, b), max(a, b)

    for nth, (gap, a, b) in enumerate(heapq.nsmallest(limit, near()), 1):
        yield nth, a, b, gap


def ordered_gaps(values: DataFrame, limit: int) -> DataFrame:
    return OrderedGaps(values.asTable().partitionBy("dim").orderBy("value"), F.lit(int(limit)))
