"""Benchmark decontamination: fingerprints of item-sized windows, found by multi-index blocks, verified exactly.

Words are runs of letters and digits in lower case, shingles five words (an item of fewer words is one shingle). Windows as
long as an item get a SimHash fingerprint: all windows that hold a shingle of an item of that size, since others share nothing
with one. A text that is shorter than an item is its one window as a whole. Eight blocks of eight bits, each looked up with up
to two flipped bits, give every item within 23 differing bits of a window. Candidates are then verified by the weighted
Jaccard similarity of the shingles with their counts. Similar windows of short items can differ in more bits than that: an
item of which a window holds 0.88 of the shingles is verified whatever the fingerprint, so no window of 0.8 or more is lost.

The items are gathered in groups of at most ``group_bytes`` of text, the bound of each broadcast; further groups are
further passes over the documents, so no document or item is left out.

Defined cases: null and empty texts and items without words match nothing; rows that repeat an id or have a null one give a
row each; very long texts are searched whole; other columns are ignored by :func:`contaminated`; items
that repeat a text are all reported; empty tables on either side give an empty result.
"""

from __future__ import annotations

import re
from collections import Counter, defaultdict
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import tidy

SHINGLE, SIMILARITY, BLOCKS, FLIPS = 5, 0.8, 8, 2
RADIUS = BLOCKS * (FLIPS + 1) - 1
#: Text of the benchmark that is broadcast at once.
GROUP_BYTES = 8 << 20
_WORD = re.compile(r"[^\W_]+")


def words_of(text: str | None) -> list[str]:
    return _WORD.findall(text.lower()) if text else []


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _rolled(ids: np.ndarray, length: int) -> np.ndarray:
    """A 64-bit value for every run of ``length`` ids."""
    n = len(ids) - length + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    h = np.zeros(n, np.uint64)
    x = _mixed(ids.astype(np.uint64) + np.uint64(1))
    for i in range(length):
        h = h * np.uint64(0x9E3779B97F4A7C15) + x[i : i + n]
    return _mixed(h)


def _signs(h: np.ndarray) -> np.ndarray:
    return np.unpackbits(h.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).astype(np.int32) * 2 - 1


def _pack(sums: np.ndarray) -> np.ndarray:
    return np.packbits(sums > 0, axis=1).view(">u8").ravel().astype(np.uint64)


class Items:
    """The multi-index over the items of one group."""

    def __init__(self, rows: list[tuple[int, str]]) -> None:
        self.vocabulary: dict[str, int] = {}
        self.ids, self.sizes, self.lengths, self.weights, prints = [], [], [], [], []
        self.by_shingle: dict[int, dict[int, set[int]]] = defaultdict(lambda: defaultdict(set))
        for item_id, text in rows:
            words = words_of(text)
            if not words:
                continue
            codes = np.array([self.vocabulary.setdefault(w, len(self.vocabulary)) for w in words])
            length = min(SHINGLE, len(words))
            h = _rolled(codes, length)
            k = len(self.ids)
            self.ids.append(item_id)
            self.sizes.append(len(words))
            self.lengths.append(length)
            self.weights.append(Counter(h.tolist()))
            prints.append(_pack(_signs(h).sum(axis=0, keepdims=True))[0])
            for x in h.tolist():
                self.by_shingle[length][x].add(k)
        self.by_shingle = {n: dict(t) for n, t in self.by_shingle.items()}
        self.sorted = {n: np.array(sorted(t), np.uint64) for n, t in self.by_shingle.items()}
        self.prints = np.array(prints, np.uint64)
        flips = np.array([0, *(1 << i for i in range(8)), *((1 << i) | (1 << j) for i in range(8) for j in range(i))], np.uint8)
        self.blocks = []
        for b in range(BLOCKS):
            table: dict[int, set[int]] = defaultdict(set)
            for k, p in enumerate(prints):
                for v in (np.uint8((int(p) >> (8 * b)) & 255) ^ flips).tolist():
                    table[v].add(k)
            self.blocks.append(dict(table))

    def near(self, fp: int) -> set[int]:
        """Items within RADIUS of a fingerprint: one block of theirs differs in at most FLIPS bits."""
        found = set().union(*(t.get((fp >> (8 * b)) & 255, ()) for b, t in enumerate(self.blocks)))
        return {k for k in found if (int(self.prints[k]) ^ fp).bit_count() <= RADIUS}

    def matches(self, words: list[str]) -> dict[int, tuple[float, int]]:
        """item position: (similarity, first word of the best window), of 0.8 or more."""
        get = self.vocabulary.get
        codes = np.fromiter((get(w, -1) for w in words), np.int64, len(words))
        out: dict[int, tuple[float, int]] = {}
        for length, values in self.sorted.items():
            known = codes >= 0
            runs = np.flatnonzero(np.convolve(known, np.ones(length, int), "valid") == length) if len(codes) >= length else np.empty(0, int)
            if not len(runs):
                continue
            h = _rolled(codes, length)
            x = h[runs]
            i = np.searchsorted(values, x)
            hits = runs[(i < len(values)) & (values[np.minimum(i, len(values) - 1)] == x)]
            if not len(hits):
                continue
            starts: dict[int, set[int]] = defaultdict(set)  # windows by item size
            sure: dict[tuple[int, int], set[int]] = defaultdict(set)  # items of a window that need no fingerprint
            cut: dict[int, float] = {}  # items longer than the text
            touched = {k for x in set(h[hits].tolist()) for k in self.by_shingle[length][x]}
            for k in touched:
                size, count = self.sizes[k], self.sizes[k] - length + 1
                if size > len(words):
                    # Similarity is at most the quotient of the counts. An item of one shingle has no shorter text with it.
                    if len(h) >= SIMILARITY * count - 1e-9:
                        both = sum((Counter(h.tolist()) & self.weights[k]).values())
                        cut[k] = both / (len(h) + count - both)
                    continue
                # Every window of the item's size that holds a shingle of the item gets a fingerprint.
                own = np.array([p for p in hits.tolist() if int(h[p]) in self.weights[k]])
                for p in own.tolist():
                    starts[size].update(range(max(0, p - count + 1), min(p, len(words) - size) + 1))
                # A window of 0.8 or more holds 8/9 of the item's shingles, so it starts at most 1/9 before the first: these
                # windows are compared with the item wherever their fingerprints lie, so the radius loses nothing.
                enough = np.searchsorted(own, own + count) - np.arange(len(own)) >= 0.88 * count
                for p in own[enough].tolist():
                    for q in range(max(0, p - count // 8), min(p, len(words) - size) + 1):
                        sure[q, size].add(k)
            out.update((k, (similarity, 0)) for k, similarity in cut.items() if similarity >= SIMILARITY)
            for size, wanted in starts.items():
                count = size - length + 1
                at = np.array(sorted(s for s in wanted if s + size <= len(words)), int)
                for first in range(0, len(at), 2048):
                    part = at[first : first + 2048]
                    low, high = int(part[0]), int(part[-1]) + count
                    if high - low > 16 * 2048:  # far apart: a window at a time
                        groups = [np.array([p]) for p in part.tolist()]
                    else:
                        groups = [part]
                    for g in groups:
                        low, high = int(g[0]), int(g[-1]) + count
                        sums = np.zeros((high - low + 1, 64), np.int32)
                        np.cumsum(_signs(h[low:high]), axis=0, out=sums[1:])
                        prints = _pack(sums[g - low + count] - sums[g - low])
                        for p, fp in zip(g.tolist(), prints.tolist(), strict=True):
                            for k in self.near(fp) | sure.get((p, size), set()):
                                if self.sizes[k] == size and self.lengths[k] == length:
                                    window = Counter(h[p : p + count].tolist())
                                    both = sum((window & self.weights[k]).values())
                                    similarity = both / (2 * count - both)
                                    if similarity >= SIMILARITY and similarity > out.get(k, (0.0, 0))[0]:
                                        out[k] = (similarity, p)
        return out


def _found(shared, whole_rows: bool, text_at: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items: Items = shared.value
        for batch in batches:
            texts = batch.column(text_at).to_pylist()
            if whole_rows:
                yield batch.filter(pa.array([not items.matches(words_of(t)) for t in texts], pa.bool_()))
                continue
            rows = [(d, items.ids[k], s, p) for d, t in zip(batch.column(0).to_pylist(), texts, strict=True) for k, (s, p) in sorted(items.matches(words_of(t)).items())]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int64(), pa.int64(), pa.float64(), pa.int64()))], names=["doc_id", "item_id", "similarity", "first_word"])

    return run


def item_groups(benchmark: DataFrame, group_bytes: int, id_col: str = "item_id", text_col: str = "text") -> Iterator[list[tuple[int, str]]]:
    """The items in groups of bounded size, one group at a time on the driver."""
    rows = benchmark.select(F.col(id_col).cast("long"), F.col(text_col)).filter(F.col(text_col).isNotNull())
    group, size = [], 0
    for item_id, text in rows.toLocalIterator():
        if group and size + len(text) > group_bytes:
            yield group
            group, size = [], 0
        group.append((item_id, text))
        size += len(text)
    if group:
        yield group


def contaminated(docs: DataFrame, benchmark: DataFrame, group_bytes: int = GROUP_BYTES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, item_id, similarity, first_word: a row for each document and item with a window of 0.8 or more."""
    kinds = "doc_id long, item_id long, similarity double, first_word long"
    pairs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    share = docs.sparkSession.sparkContext.broadcast
    found = [pairs.mapInArrow(tidy(_found(share(Items(g)), False, 1)), kinds) for g in item_groups(benchmark, group_bytes)]
    return reduce(DataFrame.unionByName, found) if found else docs.sparkSession.createDataFrame([], kinds)


def keep_clean(docs: DataFrame, benchmark: DataFrame, group_bytes: int = GROUP_BYTES, text_col: str = "text") -> DataFrame:
    """The rows without a match, with all their columns; no shuffle."""
    share = docs.sparkSession.sparkContext.broadcast
    for group in item_groups(benchmark, group_bytes):
        docs = docs.mapInArrow(tidy(_found(share(Items(group)), True, docs.columns.index(text_col))), docs.schema)
    return docs
