"""Sets whose terms are words below their prefixes: a word names its own path, so no tree is made, joined or sent.

An object is one row, obj_id and its distinct words in order. One set: objects of the same words are at distance 0, and
where they hold the k best pairs nothing else is compared. Two sets: only nodes that the smaller side touches can be shared,
so the other side is counted at these alone; of its other words no more than the depth matters.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.weights import exponential
from . import dense, streamed
from .classes import Classes
from .coded import Numbers
from .search import answers, checkpoint, ranked

#: Letters of the prefixes that are nodes; the whole word is the level below.
PREFIXES = (1, 2, 3)
HEIGHT = len(PREFIXES) + 1
NUMBERED = "obj_id long, terms array<int>"


def words(rows: DataFrame, obj: Column, text: Column) -> DataFrame:
    """obj_id, terms: the distinct lower-case words of each object in order; those without an id or a word are left out.

    Only where ids repeat are the words of rows shuffled, to be put together.
    """
    low = F.lower(F.coalesce(text, F.lit("")))
    found = F.regexp_extract_all(low, F.lit(r"\p{L}+"), F.lit(0))
    ids = rows.select(obj.cast("long").alias("obj_id")).dropna()
    # A filter on the words would be computed with them once more below their projection; this one stops at the first letter.
    made = rows.filter(obj.isNotNull() & low.rlike(r"\p{L}")).select(obj.cast("long").alias("obj_id"), F.array_sort(F.array_distinct(found)).alias("terms"))
    if ids.groupBy("obj_id").count().filter("count > 1").isEmpty():
        return made
    return made.groupBy("obj_id").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("terms")))).alias("terms"))


class Shared:
    """The tree of the nodes that some words touch, with one more number at each inner node for other words below it."""

    def __init__(self, spark, terms: set[str]) -> None:
        weights, scale = exponential()(HEIGHT)
        depths = np.cumsum([0] + [weights[i] for i in range(1, HEIGHT + 1)])
        inner = {()} | {path[:i] for path in map(path_of, terms) for i in range(1, HEIGHT)}
        # "" stands for other words: it sorts before what lies below the node, as the node itself does.
        paths = sorted(inner | {p + ("",) for p in inner} | set(map(path_of, terms)))
        code = {p: n for n, p in enumerate(paths)}
        path = np.full((len(paths), HEIGHT + 1), -1, np.int32)
        level, depth = np.zeros(len(paths), np.int64), np.zeros(len(paths), np.int64)
        for n, p in enumerate(paths):
            own = p[:-1] if p and p[-1] == "" else p
            path[n, : len(own) + 1] = [code[own[:i]] for i in range(len(own) + 1)]
            level[n], depth[n] = len(own), depths[len(own) if own is p else HEIGHT]
        w = np.array([0] + [weights[i] for i in range(1, HEIGHT + 1)], np.int64)[level]
        self.numbers = spark.sparkContext.broadcast(Numbers(path, level, w, depth, scale))
        self.height, self.scale, self.codes = HEIGHT, scale, spark.sparkContext.broadcast(code)

    def rows(self, words: DataFrame) -> DataFrame:
        """NUMBERED: the number of each word, or that of other words at the last node of its path that is known."""
        codes = self.codes

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            known = codes.value

            def number(word: str) -> int:
                path = path_of(word)
                if path in known:
                    return known[path]
                return next(known[path[:i] + ("",)] for i in range(HEIGHT - 1, -1, -1) if path[:i] + ("",) in known)

            for b in batches:
                lists = b.column("terms")
                starts = np.asarray(lists.offsets).astype(np.int32)
                coded = lists.flatten().dictionary_encode()
                table = np.fromiter(map(number, coded.dictionary.to_pylist()), np.int32)
                terms = table[coded.indices.to_numpy(zero_copy_only=False)]
                of = np.repeat(np.arange(b.num_rows), np.diff(starts))
                terms = terms[np.lexsort((terms, of))]
                yield pa.RecordBatch.from_arrays([b.column("obj_id"), pa.ListArray.from_arrays(pa.array(starts - starts[0]), pa.array(terms))], names=["obj_id", "terms"])

        return words.select("obj_id", "terms").mapInArrow(run, NUMBERED)


def path_of(word: str) -> tuple[str, ...]:
    return (*(word[:i] for i in PREFIXES), word)


def classes_of(words: DataFrame) -> Classes:
    """Objects of the same words, by a SHA-256 of them: no word holds the sign between two."""
    key = F.unhex(F.sha2(F.array_join("terms", "/"), 256))
    return Classes._of(words.select("obj_id", key.alias("key"), F.lit(0.0).alias("self")), checkpoint)


def _small(words: DataFrame) -> bool:
    return (words.agg(F.sum(F.size("terms") * HEIGHT + 1)).first()[0] or 0) <= streamed.SENT_NODES


def emd_topk(left: DataFrame, k: int, general: Callable[[], DataFrame], right: DataFrame | None = None) -> DataFrame:
    """rank, a, b, dist of the k closest pairs under the earth mover's distance, of one set of :func:`words` or of two.

    ``general`` is the search for what is left: fewer than k pairs of equal objects in one set, or two large sets.
    """
    if right is None:
        classes = classes_of(left)
        if classes.inside(k)[0] < k:
            return general()
        return ranked(answers(dense._joined(None, classes, k, None)), k)
    sent_left = not _small(right)
    if sent_left and not _small(left):
        return general()
    small, large = (left, right) if sent_left else (right, left)
    small = checkpoint(small)
    terms = {r[0] for r in small.select(F.explode("terms")).distinct().collect()}
    tree = Shared(left.sparkSession, terms)
    spec = dense.Spec("emd", k, None, tree.scale, HEIGHT, 0, True)
    return ranked(answers(streamed.streamed(tree.rows(small), tree.rows(large), spec, sent_left, tree)), k)
