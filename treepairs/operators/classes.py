"""Objects with equal descriptions as one class: searched once, and its members put back into the answers."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Slack for distances compared in floating point.
EPS = 1e-9


@dataclass(frozen=True)
class Classes:
    #: obj_id, key: the class of each object; key, rep (its smallest object), m (members), self (distance of two members).
    members: DataFrame
    table: DataFrame

    @staticmethod
    def of(packed: DataFrame, checkpoint) -> Classes:
        """Equal are objects with the same number of terms below each node, by a SHA-256 of the counts (``key``, where the rows
        have it)."""
        if "key" in packed.columns:
            return Classes._of(packed.select("obj_id", "key", "self"), checkpoint)
        item = F.transform(F.arrays_zip("node_id", "c"), lambda i: F.concat(F.length(i["node_id"]).cast("string"), F.lit(":"), i["node_id"], F.lit(","), i["c"].cast("string"), F.lit(";")))
        key = F.unhex(F.sha2(F.concat(F.col("n").cast("string"), F.lit(";"), F.array_join(item, "")), 256))
        return Classes._of(packed.select("obj_id", key.alias("key"), "self"), checkpoint)

    @staticmethod
    def _of(keyed: DataFrame, checkpoint) -> Classes:
        members = checkpoint(keyed)
        table = members.groupBy("key").agg(F.min("obj_id").alias("rep"), F.count(F.lit(1)).alias("m"), F.min("self").alias("self"))
        return Classes(members.select("obj_id", "key"), checkpoint(table))

    def kept(self, objects: DataFrame, where: Column | None = None) -> DataFrame:
        """The descriptions of one object for each class."""
        reps = self.table if where is None else self.table.filter(where)
        return objects.join(reps.select(F.col("rep").alias("obj_id")), "obj_id", "left_semi")

    def inside(self, k: int) -> tuple[int, float]:
        """How many of the k best pairs there are inside classes at most, and the kth distance of those pairs."""
        pairs = 0
        for r in self.table.filter("m > 1").orderBy("self", "rep").limit(k).select("self", "m").collect():
            pairs += r["m"] * (r["m"] - 1) // 2
            if pairs >= k:
                return k, float(r["self"])
        return pairs, float("inf")

    def first(self, reps: DataFrame, most: int | None) -> DataFrame:
        """rep, obj_id: the members of the given classes, the first ``most`` of each."""
        named = self.table.join(F.broadcast(reps) if most else reps, "rep", "left_semi").select("key", "rep")
        rows = self.members.join(F.broadcast(named) if most else named, "key").select("rep", "obj_id")
        if most is None:
            return rows
        nth = F.row_number().over(Window.partitionBy("rep").orderBy("obj_id"))
        return rows.withColumn("nth", nth).filter(F.col("nth") <= most).select("rep", "obj_id")


def _spread(found: DataFrame, x: DataFrame, y: DataFrame) -> DataFrame:
    left = x.select(F.col("rep").alias("a"), F.col("obj_id").alias("x"))
    right = y.select(F.col("rep").alias("b"), F.col("obj_id").alias("y"))
    return found.join(left, "a").join(right, "b").select("x", "y", "dist")


def expanded(found: DataFrame | None, left: Classes, k: int | None, radius: float | None = None, right: Classes | None = None) -> DataFrame:
    """a, b, dist over all objects from the pairs of class representatives.

    The first pair of two classes is that of their representatives, so the k best pairs lie in the k best pairs of classes
    (a class with itself included), and of each class in its first k+1 members. Within a radius all members take part.
    """
    most = None if k is None else k + 1
    parts = []
    if found is not None:
        best = found if k is None else found.orderBy("dist", "a", "b").limit(k)
        x = left.first(best.select(F.col("a").alias("rep")).union(best.select(F.col("b").alias("rep"))) if right is None else best.select(F.col("a").alias("rep")), most)
        y = x if right is None else right.first(best.select(F.col("b").alias("rep")), most)
        parts.append(_spread(best, x, y))
    if right is None:
        own = left.table.filter("m > 1").select("rep", F.col("self").alias("dist"))
        own = own.filter(F.col("dist") <= F.lit(radius)) if k is None else own.orderBy("dist", "rep").limit(k)
        x = left.first(own.select("rep"), most)
        own = own.select(F.col("rep").alias("a"), F.col("rep").alias("b"), "dist")
        parts.append(_spread(own, x, x).filter("x < y"))
    both = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
    if right is not None:
        return both.select(F.col("x").alias("a"), F.col("y").alias("b"), "dist")
    return both.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "dist")
