"""Near-duplicates by word-shingle similarity: a Gray-ordered SimHash index first, an exact prefix join for what it leaves.

Texts with the same set of shingles are one class from the start. Then

1. Each class has a fingerprint of 128 bits. Its index is that of ``simhash``: the top nodes are masked patterns (two of
   eight blocks of 16 bits), below them fingerprints lie in Gray order and groups of runs are pruned by accumulated
   differences. Fingerprints are dealt by ranges of (top node, Gray rank), so a node that holds a third of all rows is parted
   among tasks. Every fingerprint names two neighbours within the radius at most in a node, the first and the nearest, so the
   number of candidates is linear.
2. A fingerprint cannot be complete at a similarity of 0.8, so an exact prefix join finds the rest: in one order of all
   shingles, two sets of that similarity share one of the first ones of both. Only pairs of different groups are looked at.
   A shingle that many texts have is compared block by block, in cells of their own.
3. Candidates of both kinds are cut by the parity of the shingles in 256 classes, which no pair of the similarity fails, and
   by those in 4,096 classes, and decided by the shingle sets. In two rounds every text tests its closest open candidate and what is linked then is merged;
   all pairs that are still between different groups are tested after that. No link between different groups is lost.

Defined cases: ASCII case and runs of separators do not count; a text of fewer words is one shingle; texts without words
(null, empty) are copies of one another; of rows that repeat an id and a text one stays, and rows that repeat an id with
different texts are documents of their own, in the order of a digest of the text; rows with a null id stay; an empty table
gives an empty result; other columns pass through, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, checkpointed, content_digest, one_row_per_text, repeats, shuffle_width, tidy, unused
from .components import components
from .shingles import mixed, shingle_sets
from .simhash import gray_rank, pairs_below

_PRINTS, _BITS, _SUMS = ["f0", "f1"], ["x0", "x1", "x2", "x3"], ["d0", "d1"]
_SIGNED = ", ".join(["doc_id long", "n long", *(f"{c} long" for c in (*_PRINTS, *_BITS, *_SUMS)), "frequent array<long>", "times array<long>"])
_BLOCKS = 8
#: Rows of one top node that are compared at once.
_NODE_ROWS = 4096
#: Shingles that come last in the order of the prefixes: the most frequent ones, of those that some slice holds more than twice.
_LAST = 1 << 18
#: A shingle in the prefixes of more texts than this is compared in cells, of blocks of so many texts.
_HOT = 4096
#: Postings in one task, rows of fingerprints in one task, and pairs that are held at once.
_POSTINGS, _ROWS, _AT_ONCE = 1 << 20, 1 << 20, 1 << 20
#: Rows of an Arrow batch that are worked on at once.
_SLICE = 2048
#: A round sends the sets of all texts once more, to save at most one set for a pair: it pays beyond so many pairs for a text.
_PAIRS_OF_TEXT = 4
#: Classes of the parities that are compared before sets are.
_WIDE = 4096
#: Ids that are broadcast to find their texts (8 MB).
_FEW_IDS = 1 << 20


def _slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, _SLICE):
            yield batch.slice(at, _SLICE)


def _signatures(shingle: int):
    """A row for each text: number of shingles, fingerprint, parities, sums that tell sets apart; the first row of a slice
    carries the slice's frequent shingles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _slices(batches):
            ids = batch.column(0)
            every = [np.empty(0, np.uint64)]
            rows = []
            for _, s in shingle_sets(batch.column(1).cast(pa.binary()).to_pylist(), shingle):
                parity = s.parities()
                rows.append([s.sizes, *(s.majority(k).view(np.int64) for k in range(2)), *(parity[:, k] for k in range(4)), s.sums(3).view(np.int64), s.sums(4).view(np.int64)])
                every.append(s.values)
            if not rows:
                continue
            values, times = np.unique(np.concatenate(every), return_counts=True)
            values, times = values[times > 2].view(np.int64), times[times > 2]
            lists = [pa.array([x, *[None] * (len(ids) - 1)], pa.list_(pa.int64())) for x in (values, times)]
            cols = [pa.array(np.ascontiguousarray(np.concatenate(c))) for c in zip(*rows, strict=True)]
            yield pa.RecordBatch.from_arrays([ids, *cols, *lists], names=["doc_id", "n", *_PRINTS, *_BITS, *_SUMS, "frequent", "times"])

    return run


def _block(i: int) -> Column:
    return F.shiftrightunsigned(_PRINTS[i // 4], 16 * (i % 4)).bitwiseAND(F.lit(0xFFFF))


def _neighbours(radius: int, total: int):
    """For each row of each top node its first and its nearest neighbour before it, in Gray order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cols = [[np.empty(0, np.int64)] for _ in range(4)]
        for batch in batches:
            for c, x in zip(cols, batch.columns, strict=True):
                c.append(x.to_numpy(zero_copy_only=False))
        key, f0, f1, node = (np.concatenate(c) for c in cols)
        f0, f1 = f0.view(np.uint64), f1.view(np.uint64)
        order = np.lexsort((gray_rank(f0), key))
        key, f0, f1, node = (c[order] for c in (key, f0, f1, node))
        n = len(key)
        # a node of many rows is compared in portions of Gray order
        first = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        place = np.arange(n) - np.repeat(first, np.diff(np.r_[first, n]))
        part = np.cumsum(np.r_[True, (key[1:] != key[:-1]) | (place[1:] % _NODE_ROWS == 0)]) if n else key
        low, best = np.full(n, n), np.full(n, 1 << 40)
        for i, j in pairs_below(part, f0, radius):
            differ = (np.bitwise_count(f0[i] ^ f0[j]) + np.bitwise_count(f1[i] ^ f1[j])).astype(np.int64)
            ok = differ <= total
            i, j, differ = i[ok], j[ok], differ[ok]
            np.minimum.at(low, j, i)
            np.minimum.at(best, j, differ << 32 | i)
        near = np.flatnonzero(low < n)
        a, b = np.r_[node[near], node[near]], np.r_[node[low[near]], node[best[near] & 0xFFFFFFFF]]
        pairs = np.unique(np.column_stack([np.minimum(a, b), np.maximum(a, b)])[a != b], axis=0).reshape(-1, 2)
        yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(pairs[:, k])) for k in range(2)], names=["a", "b"])

    return run


def simhash_candidates(classes: DataFrame, radius: int = 18, total: int = 30) -> DataFrame:
    """a, b: pairs of classes whose fingerprints are near, at most two for a class and top node."""
    prints = classes.groupBy(*_PRINTS).agg(F.min("doc_id").alias("node"))
    same = classes.join(prints, _PRINTS).filter("doc_id <> node").select(F.col("node").alias("a"), F.col("doc_id").alias("b"))
    tops = [F.xxhash64(F.lit(k), _block(i), _block(j)) for k, (i, j) in enumerate(combinations(range(_BLOCKS), 2))]
    keyed = prints.select(F.explode(F.array(*tops)).alias("key"), *_PRINTS, "node")
    gray = F.col("f0")
    for s in (1, 2, 4, 8, 16, 32):
        gray = gray.bitwiseXOR(F.shiftrightunsigned(gray, s))
    # The top bit decides first: a signed order of the ranks' upper halves is enough to part a node in Gray order.
    ranked = keyed.withColumn("rank", F.shiftrightunsigned(gray, 1))
    ranges = max(shuffle_width(classes.sparkSession), len(tops) * classes.count() // _ROWS)
    linked = ranked.repartitionByRange(ranges, "key", "rank").drop("rank").mapInArrow(tidy(_neighbours(radius, total)), "a long, b long")
    return linked.unionByName(same).distinct()


def least_shared(n: np.ndarray, threshold: float) -> np.ndarray:
    """Shingles that sets of ``n`` share at least with any set of the similarity."""
    return np.ceil(threshold * n - 1e-9).astype(np.int64)


def _prefixes(shingle: int, threshold: float, last: np.ndarray):
    """The first shingles of each text in the order of all shingles: those of ``last`` come last, the most frequent at the end."""
    by_value = np.argsort(last)
    values = last[by_value]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _slices(batches):
            prefixes: list[bytes] = []
            for _, s in shingle_sets(batch.column(1).cast(pa.binary()).to_pylist(), shingle):
                rank = np.zeros(len(s.values), np.int64)
                if len(values):
                    at = np.minimum(np.searchsorted(values, s.values), len(values) - 1)
                    rank = np.where(values[at] == s.values, len(values) - by_value[at], 0)
                ordered = s.values[np.lexsort((s.values, rank, s.owner))]
                size = s.sizes
                upto = s.bounds[:-1] + np.where(size > 0, size - least_shared(size, threshold) + 1, 0)
                prefixes += [ordered[i:j].tobytes() for i, j in zip(s.bounds[:-1].tolist(), upto.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(prefixes, pa.binary())], names=["doc_id", "prefix"])

    return run


_ENTRY = np.dtype([("key", "<i8"), ("doc", "<i8"), ("group", "<i8"), ("odd0", "<i8"), ("odd1", "<i8"), ("before", "<i8"), ("before2", "<i8"), ("n", "<i4"), ("place", "<i4"), ("side", "<i1")])


def _repeated(times: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each place its number of copies: the place and the number of each copy."""
    at = np.repeat(np.arange(len(times)), times)
    return at, np.arange(len(at)) - np.repeat(np.cumsum(times) - times, times)


def _cells(e: np.ndarray, nth: np.ndarray, main: np.ndarray, main_blocks: np.ndarray, other_blocks: np.ndarray) -> np.ndarray:
    """Entries of hot shingles under the keys of their cells. Those of the shingle's largest group are never compared with one
    another: each lies in one block. The others go to all these blocks, and to the cells of their own block with the rest."""
    digest = mixed(e["doc"].view(np.uint64), 5)
    inside = e["group"] == main[nth]
    low, out = [], []

    def put(at: np.ndarray, side: np.ndarray | int, cell: np.ndarray) -> None:
        part = e[at]
        part["side"] = side
        part["key"] = mixed(mixed(part["key"].view(np.uint64), 11) + cell.astype(np.uint64), 13).view(np.int64)
        out.append(part)

    low = np.flatnonzero(inside)
    put(low, 0, digest[low] % main_blocks[nth[low]].astype(np.uint64))
    rest = np.flatnonzero(~inside)
    at, block = _repeated(main_blocks[nth[rest]])
    put(rest[at], 1, block)
    at, block = _repeated(other_blocks[nth[rest]])
    own = (digest[rest[at]] % other_blocks[nth[rest[at]]].astype(np.uint64)).astype(np.int64)
    cell = (1 << 48) + (np.minimum(own, block) << 24) + np.maximum(own, block)
    put(rest[at], np.where(own == block, 2, own < block), cell)
    return np.concatenate(out)


def _entries(columns: list[pa.Array]) -> np.ndarray:
    """The entries of doc_id, n, prefix, group, odd0, odd1, each with the two shingles before it in its prefix (0: none)."""
    prefixes = [np.frombuffer(p, np.int64) for p in columns[2].to_pylist()]
    row, place = _repeated(np.array([len(p) for p in prefixes], np.int64))
    e = np.zeros(len(row), _ENTRY)
    e["key"], e["place"], e["side"] = np.concatenate([np.empty(0, np.int64), *prefixes]), place, 2
    for name, i in (("doc", 0), ("n", 1), ("group", 3), ("odd0", 4), ("odd1", 5)):
        e[name] = columns[i].to_numpy(zero_copy_only=False)[row]
    for name, back in (("before", 1), ("before2", 2)):
        e[name][back:] = np.where(place[back:] >= back, e["key"][:-back], 0)
    return e


def _found_in(values: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Whether each of ``x`` is among the ascending values, and its place."""
    if not len(values):
        return np.zeros(len(x), bool), np.zeros(len(x), np.int64)
    at = np.minimum(np.searchsorted(values, x), len(values) - 1)
    return values[at] == x, at


def _hot_counts(values: np.ndarray):
    """key, group, n: entries of the shingles that may be hot, by group, summed within a batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _slices(batches):
            e = _entries(batch.columns)
            e = e[_found_in(values, e["key"])[0]]
            both, n = np.unique(np.column_stack([e["key"], e["group"]]), axis=0, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(both[:, 0])), pa.array(np.ascontiguousarray(both[:, 1])), pa.array(n)], names=["key", "group", "n"])

    return run


def _postings(buckets: int, hot: tuple[np.ndarray, ...]):
    """doc_id, n, prefix, group, odd0, odd1 to packed entries by bucket."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _slices(batches):
            e = _entries(batch.columns)
            is_hot, nth = _found_in(hot[0], e["key"])
            if is_hot.any():
                e = np.concatenate([e[~is_hot], _cells(e[is_hot], nth[is_hot], *hot[1:])])
            bucket = (mixed(e["key"].view(np.uint64), 17) % np.uint64(buckets)).astype(np.int64)
            order = np.argsort(bucket, kind="stable")
            bucket, e = bucket[order], e[order]
            first = np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]][: len(e)])
            packed = [e[i:j].tobytes() for i, j in zip(first.tolist(), [*first[1:].tolist(), len(e)], strict=False)]
            yield pa.RecordBatch.from_arrays([pa.array(bucket[first]), pa.array(packed, pa.binary())], names=["bucket", "entries"])

    return run


def _sharing(threshold: float):
    """Pairs of different groups that share a shingle of both prefixes and whose sizes, places and parities allow the
    similarity (the parities of 256 classes are folded to 128 here).

    A pair is left out where one of the two shingles before is shared as well: it has been found there, since smaller places
    pass every test that larger ones pass and the smaller set (then the smaller id) takes the first side at every shingle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = np.concatenate([np.empty(0, _ENTRY), *(np.frombuffer(b, _ENTRY) for batch in batches for b in batch.column(1).to_pylist())])
        e = e[np.lexsort((e["doc"], e["n"], e["key"]))]
        again = e["key"][1:] == e["key"][:-1]
        e = e[(np.r_[again, False] | np.r_[False, again])[: len(e)]]
        key, doc, group, odd0, odd1, *before, n, place, side = (e[c].astype(np.int64) for c in e.dtype.names)
        found, held = [], 0

        def batch_of(pairs: list[np.ndarray]) -> pa.RecordBatch:
            ab = np.unique(np.concatenate(pairs), axis=0)
            return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(ab[:, k])) for k in range(2)], names=["a", "b"])

        # The first shingle that a pair shares leaves enough behind it only if it lies in the inner prefix of the smaller set.
        live, shift = np.flatnonzero(place <= n - np.ceil(2 * threshold / (1 + threshold) * n - 1e-9)), 1
        while len(live := live[live + shift < len(key)]):
            other = live + shift
            ok = (key[live] == key[other]) & (n[live] >= least_shared(n[other], threshold))  # sizes rise, so no later row fits either
            live, other = live[ok], other[ok]
            least = np.ceil(threshold / (1 + threshold) * (n[live] + n[other]) - 1e-9)
            ok = (group[live] != group[other]) & (np.minimum(n[live] - place[live], n[other] - place[other]) >= least)
            ok &= (side[live] == 2) | (side[live] != side[other])
            i, j = live[ok], other[ok]
            known = np.zeros(len(i), bool)
            for x in before:
                for y in before:
                    known |= (x[i] == y[j]) & (x[i] != 0)
            i, j = i[~known], j[~known]
            differ = sum(np.bitwise_count((x[i] ^ x[j]).view(np.uint64)).astype(np.int64) for x in (odd0, odd1))
            ok = differ <= (1 - threshold) / (1 + threshold) * (n[i] + n[j]) + 1e-6
            i, j = doc[i[ok]], doc[j[ok]]
            if len(i):
                found.append(np.column_stack([np.minimum(i, j), np.maximum(i, j)]))
                held += len(i)
            if held > _AT_ONCE:
                yield batch_of(found)
                found, held = [], 0
            shift += 1
        if held:
            yield batch_of(found)

    return run


def _grouped(df: DataFrame, groups: DataFrame, id_col: str, name: str) -> DataFrame:
    """With the group of an id, which is the id itself where it has none."""
    named = groups.select(F.col("node").alias(id_col), F.col("component").alias(name))
    return df.join(named, id_col, "left").withColumn(name, F.coalesce(name, id_col))


def prefix_candidates(texts: DataFrame, classes: DataFrame, frequent: DataFrame, groups: DataFrame, scratch: Scratch, shingle: int, threshold: float) -> DataFrame:
    """a, b: every pair of classes of different groups that may have the similarity."""
    spark = texts.sparkSession
    last = np.array([r.value for r in frequent.orderBy(F.desc("n"), "value").limit(_LAST).select("value").collect()], np.int64)
    prefixes = texts.mapInArrow(tidy(_prefixes(shingle, threshold, last.view(np.uint64))), "doc_id long, prefix binary")
    odd = [F.col("x0").bitwiseXOR(F.col("x2")).alias("odd0"), F.col("x1").bitwiseXOR(F.col("x3")).alias("odd1")]
    sized = _grouped(classes.filter("n > 0").select("doc_id", "n", *odd), groups, "doc_id", "group")
    rows = scratch.table(prefixes.join(sized, "doc_id").select("doc_id", "n", "prefix", "group", "odd0", "odd1"))
    parts = rows.mapInArrow(tidy(_hot_counts(np.sort(last))), "key long, group long, n long").groupBy("key", "group").agg(F.sum("n").alias("n"))
    whole = parts.groupBy("key").agg(F.sum("n").alias("all"), F.max_by("group", F.struct("n", "group")).alias("main"), F.max("n").alias("most")).filter(F.col("all") > _HOT)
    hot = np.array([(r.key, r.main, -(-r.most // _HOT), -(-(r["all"] - r.most) // _HOT)) for r in whole.collect()], np.int64).reshape(-1, 4)
    hot = hot[np.argsort(hot[:, 0])]
    total = rows.agg(F.sum(F.length("prefix") / 8)).first()[0] or 0
    tasks = max(shuffle_width(spark), int(total) // _POSTINGS)
    packed = rows.mapInArrow(tidy(_postings(8 * tasks, tuple(np.ascontiguousarray(hot[:, i]) for i in range(4)))), "bucket long, entries binary")
    return packed.repartition(tasks, "bucket").mapInArrow(tidy(_sharing(threshold)), "a long, b long").distinct()


def may_be_similar(pairs: DataFrame, classes: DataFrame, threshold: float) -> DataFrame:
    """a, b, differ: the pairs whose sizes and parities allow the similarity; ``differ`` counts the classes of odd difference."""
    side = lambda name: classes.select(F.col("doc_id").alias(name), F.col("n").alias(f"{name}n"), *(F.col(x).alias(f"{name}{x}") for x in _BITS))
    differ = sum((F.bit_count(F.col(f"a{x}").bitwiseXOR(F.col(f"b{x}"))) for x in _BITS), F.lit(0))
    both = F.col("an") + F.col("bn")
    ok = (differ <= F.lit((1 - threshold) / (1 + threshold)) * both + F.lit(1e-6)) & (F.least("an", "bn") >= F.lit(threshold) * F.greatest("an", "bn") - F.lit(1e-6))
    return pairs.join(side("a"), "a").join(side("b"), "b").filter(ok).select("a", "b", differ.alias("differ"))


def _sets(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _slices(batches):
            at = 0
            for _, s in shingle_sets(batch.column(1).cast(pa.binary()).to_pylist(), shingle):
                lists = pa.ListArray.from_arrays(pa.array(s.bounds.astype(np.int32)), pa.array(s.values.view(np.int64)))
                wide = pa.array(list(s.parities(_WIDE)), pa.list_(pa.int64()))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, len(s)), pa.array(s.sizes, pa.int64()), wide, lists], names=["doc_id", "n", "wide", "shingles"])
                at += len(s)

    return run


def _rows_of(df: DataFrame, pairs: DataFrame) -> DataFrame:
    """The rows whose ids occur in pairs."""
    ids = checkpointed(pairs.select(F.col("a").alias("doc_id")).unionByName(pairs.select(F.col("b").alias("doc_id"))).distinct())
    if ids.count() <= _FEW_IDS:  # else the rows are shuffled
        ids = F.broadcast(ids)
    return df.join(ids, "doc_id", "left_semi")


def shingle_lists(texts: DataFrame, pairs: DataFrame, shingle: int) -> DataFrame:
    """doc_id, n, wide, shingles of the texts that occur in pairs: size, parities in many classes, and the set."""
    return _rows_of(texts, pairs).mapInArrow(tidy(_sets(shingle)), "doc_id long, n long, wide array<long>, shingles array<long>")


def similar(pairs: DataFrame, lists: DataFrame, threshold: float, scratch: Scratch) -> DataFrame:
    """The pairs whose sets have the similarity: those whose parities allow it first, so that few sets are sent."""
    side = lambda df, name, *cols: df.select(F.col("doc_id").alias(name), *(F.col(c).alias(f"{name}_{c}") for c in cols))
    differ = F.aggregate(F.zip_with("a_wide", "b_wide", lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)
    close = pairs.join(side(lists, "a", "n", "wide"), "a").join(side(lists, "b", "n", "wide"), "b")
    close = scratch.table(close.filter(differ <= F.lit((1 - threshold) / (1 + threshold)) * (F.col("a_n") + F.col("b_n")) + F.lit(1e-6)).select("a", "b"))
    sets = _rows_of(lists.select("doc_id", "shingles"), close)
    shared = F.size(F.array_intersect("a_shingles", "b_shingles"))
    both = close.join(side(sets, "a", "shingles"), "a").join(side(sets, "b", "shingles"), "b")
    return both.filter(shared >= F.lit(threshold) * (F.size("a_shingles") + F.size("b_shingles") - shared)).select("a", "b")


def _as_links(groups: DataFrame) -> DataFrame:
    return groups.filter("node <> component").select(F.col("node").alias("a"), F.col("component").alias("b"))


def _merged(scratch: Scratch, groups: DataFrame, links: DataFrame) -> DataFrame:
    return scratch.table(components(_as_links(groups).unionByName(links.select("a", "b")), scratch=scratch))


def _between(pairs: DataFrame, groups: DataFrame) -> DataFrame:
    """The pairs that lie between different groups."""
    named = _grouped(_grouped(pairs, groups, "a", "ga"), groups, "b", "gb")
    return named.filter("ga <> gb").select("a", "b", "differ")


def _closest(pairs: DataFrame) -> DataFrame:
    """The closest pair of each id, as either side."""
    sides = [pairs.groupBy(F.col(x).alias("x")).agg(F.min(F.struct("differ", "a", "b")).alias("p")) for x in ("a", "b")]
    return sides[0].unionByName(sides[1]).select("p.a", "p.b", "p.differ").distinct()


def joined_groups(scratch: Scratch, groups: DataFrame, pairs: DataFrame, lists: DataFrame, threshold: float, rounds: int = 2) -> DataFrame:
    """The groups after all similar pairs among the candidates have been joined; few pairs for a text need no rounds."""
    most = _PAIRS_OF_TEXT * lists.count() if rounds else 0
    for _ in range(rounds):
        if pairs.count() <= most:
            break
        tried = scratch.table(_closest(pairs))
        groups = _merged(scratch, groups, similar(tried, lists, threshold, scratch))
        pairs = scratch.table(_between(pairs.join(tried, ["a", "b"], "left_anti"), groups))
    return _merged(scratch, groups, similar(pairs, lists, threshold, scratch))


def copy_groups(docs: DataFrame, shingle: int = 5, threshold: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, group: ids of documents with a near copy of a smaller id, and the smallest id of their group."""
    scratch = Scratch(docs.sparkSession)
    texts = docs.filter(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    signed = scratch.table(texts.mapInArrow(tidy(_signatures(shingle)), _SIGNED))
    frequent = signed.filter("frequent IS NOT NULL").select(F.explode(F.arrays_zip("frequent", "times")).alias("f")).groupBy(F.col("f.frequent").alias("value")).agg(F.sum("f.times").alias("n"))
    kinds = ["n", *_SUMS]
    classes = scratch.table(signed.groupBy(*kinds).agg(F.min("doc_id").alias("doc_id"), *(F.first(c).alias(c) for c in (*_PRINTS, *_BITS))))
    groups = docs.sparkSession.createDataFrame([], "node long, component long")
    near = scratch.table(may_be_similar(simhash_candidates(classes), classes, threshold))
    lists = scratch.table(shingle_lists(texts, near, shingle))
    groups = joined_groups(scratch, groups, near, lists, threshold, rounds=0)
    left = scratch.table(may_be_similar(prefix_candidates(texts, classes, frequent, groups, scratch, shingle, threshold), classes, threshold))
    if not left.isEmpty():
        scratch.drop(lists)
        lists = scratch.table(shingle_lists(texts, left, shingle))
        groups = joined_groups(scratch, groups, left, lists, threshold)
    members = signed.select("doc_id", *kinds).join(classes.select(*kinds, F.col("doc_id").alias("node")), kinds)
    found = checkpointed(_grouped(members.select("doc_id", "node"), groups, "node", "group").filter("doc_id <> group").select("doc_id", "group").distinct())
    scratch.close()
    return found


def keep_one_of_group(docs: DataFrame, shingle: int = 5, threshold: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows that stay: one of each group of near-duplicates, the one with the smallest id, and every row with a null id."""
    digest, number = unused(docs.columns, "digest"), unused(docs.columns, "number")
    known = docs.filter(F.col(id_col).isNotNull()).withColumn(digest, content_digest(text_col))
    repeated, several = repeats(known, id_col, digest)
    if not several:
        gone = copy_groups(docs, shingle, threshold, id_col, text_col).select(F.col("doc_id").alias(id_col))
        stay = known.join(gone, id_col, "left_anti")
    else:  # numbers in the order of (id, digest) take the place of the ids
        numbers = checkpointed(known.select(id_col, digest).distinct().orderBy(id_col, digest).withColumn(number, F.monotonically_increasing_id()))
        numbered = known.join(numbers, [id_col, digest])
        gone = copy_groups(numbered, shingle, threshold, number, text_col).select(F.col("doc_id").alias(number))
        stay = numbered.join(gone, number, "left_anti")
    if repeated:
        stay = one_row_per_text(stay, id_col, text_col, digest)
    return stay.select([F.col(f"`{c}`") for c in docs.columns]).unionByName(docs.filter(F.col(id_col).isNull()))
