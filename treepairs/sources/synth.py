"""The generator of trees and objects: everything is a digest of (seed, number), so a partition can be made anywhere.

The published limits of the perturbation and the mean branching are not known; the defaults are parameters.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.weights import Rule
from ..ontology import Ontology


def unit(seed: int, *keys: Column) -> Column:
    """A number in [0, 1) from a digest."""
    return F.pmod(F.xxhash64(F.lit(seed), *keys), F.lit(1 << 30)) / F.lit(float(1 << 30))


def perturbed(mean: float, spread: float, u: Column) -> Column:
    return F.greatest(F.lit(1), F.round(F.lit(mean) * (1 + F.lit(spread) * (2 * u - 1)))).cast("int")


def parents(terms: int, branching: float = 5.0, spread: float = 0.5, seed: int = 42, top: int | None = None) -> list[int]:
    """Parent of each node in breadth-first order, -1 for the root; ``top`` fixes the number of the root's children.

    A tree is control data of the size of the vocabulary; the driver draws the numbers of children from the same digest
    that :class:`SynthTree` uses.
    """
    import hashlib

    out, queue = [-1], 0
    while len(out) < terms:
        h = int.from_bytes(hashlib.blake2b(f"{seed}:{queue}".encode(), digest_size=8).digest(), "big") / 2**64
        n = top if queue == 0 and top else max(1, round(branching * (1 + spread * (2 * h - 1))))
        out.extend([queue] * min(n, terms - len(out)))
        queue += 1
    return out


def ontology(spark: SparkSession, terms: int, branching: float = 5.0, spread: float = 0.5, seed: int = 42, top: int | None = None, rule: Rule | None = None) -> Ontology:
    rows = [(str(i), None if p < 0 else str(p)) for i, p in enumerate(parents(terms, branching, spread, seed, top))]
    return Ontology.from_edges(spark.createDataFrame(rows, "child string, parent string"), rule=rule)


def objects(spark: SparkSession, n: int, terms: int, size: float = 6.0, spread: float = 0.5, seed: int = 42) -> DataFrame:
    """obj_id, term_id: for each object a perturbed number of terms drawn without replacement.

    Draws are digests of (seed, object, draw); twice as many as needed are made, repeats fall away and the first are kept,
    so nothing of the size of the vocabulary is sorted. Small vocabularies cap the size.
    """
    base = spark.range(n).select(F.col("id").alias("obj_id")).withColumn("size", F.least(perturbed(size, spread, unit(seed, F.col("obj_id"))), F.lit(terms)))
    draws = F.sequence(F.lit(1), F.greatest(2 * F.col("size") + 8, F.lit(0)))
    pick = F.transform(draws, lambda d: F.pmod(F.xxhash64(F.lit(seed + 1), F.col("obj_id"), d), F.lit(terms)))
    chosen = F.slice(F.array_distinct(pick), 1, F.col("size"))
    return base.select("obj_id", F.explode(chosen.cast("array<string>")).alias("term_id"))


def register_source(spark: SparkSession) -> None:
    """``spark.read.format('synthtree').option('terms', ..)``: (child, parent) rows of a generated tree by partitions."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class Part(InputPartition):
        def __init__(self, lo: int, hi: int) -> None:
            self.lo, self.hi = lo, hi

    class Reader(DataSourceReader):
        def __init__(self, options: dict) -> None:
            self.terms = int(options.get("terms", 100))
            self.args = (float(options.get("branching", 5)), float(options.get("spread", 0.5)), int(options.get("seed", 42)), int(options["top"]) if "top" in options else None)
            self.parts = int(options.get("partitions", 4))

        def partitions(self) -> list[InputPartition]:
            step = -(-self.terms // self.parts)
            return [Part(lo, min(lo + step, self.terms)) for lo in range(0, self.terms, step)]

        def read(self, partition: Part) -> Iterator[tuple]:
            up = parents(self.terms, *self.args)
            for i in range(partition.lo, partition.hi):
                yield str(i), None if up[i] < 0 else str(up[i])

    class SynthTree(DataSource):
        @classmethod
        def name(cls) -> str:
            return "synthtree"

        def schema(self) -> str:
            return "child string, parent string"

        def reader(self, schema) -> DataSourceReader:
            return Reader(self.options)

    spark.dataSource.register(SynthTree)
