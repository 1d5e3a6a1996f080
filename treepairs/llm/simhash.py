"""SimHash near-duplicates through a Gray-ordered hierarchical index.

Every whole text gets a 64-bit fingerprint: a bit is set if it is set in over half of the XXH64 values of its shingles.
Only distinct fingerprints are linked. The top nodes of the index are masked patterns: the value of ``choose`` of
``blocks`` bit blocks. Two fingerprints within ``blocks - choose`` differing bits agree in at least ``choose`` blocks, so
they meet below a top node; the node is also the shuffle key, hence no task sees all fingerprints. Below it, fingerprints
are sorted by Gray rank; runs of 16 and of 256 form nodes with the bits that all their members share. The differences in
shared bits add up from the upper to the lower node, and a pair of nodes is left out as soon as they exceed the radius.

A task emits a spanning forest of what it has linked, never all pairs; components over the forests give the groups.

Defined cases: a text without words (null, empty) has fingerprint zero and is linked like any other; rows that repeat an
id appear once each with equal results; rows with a null id get a null component; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SEPARATORS, checkpointed, shuffle_width, tidy
from .components import Forest, components

_RUN = re.compile(SEPARATORS.encode())
_LEAF, _UPPER = 16, 16
#: Pairs of fingerprints or nodes that are compared at once.
_AT_ONCE = 1 << 20


def shingle_hashes(text: bytes, shingle: int) -> np.ndarray:
    """XXH64 of every shingle, repeats included; none for a text without words."""
    import xxhash

    words = _RUN.sub(b" ", text.lower()).strip(b" ")
    if not words:
        return np.empty(0, np.uint64)
    buf = np.frombuffer(words, np.uint8)
    gaps = np.flatnonzero(buf == 32)
    if len(gaps) < shingle:
        return np.array([xxhash.xxh64_intdigest(words, 42)], np.uint64)
    starts = [0, *(gaps[: len(gaps) - shingle + 1] + 1).tolist()]
    ends = [*gaps[shingle - 1 :].tolist(), len(words)]
    digest = xxhash.xxh64_intdigest
    return np.fromiter((digest(words[i:j], 42) for i, j in zip(starts, ends, strict=True)), np.uint64, len(ends))


def majority(h: np.ndarray) -> int:
    """The bits that are set in over half of the hashes."""
    ones = np.zeros(64, np.int64)
    for at in range(0, len(h), 4096):
        bits = np.unpackbits(h[at : at + 4096].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
        ones += bits.sum(axis=0, dtype=np.int32)
    return int.from_bytes(np.packbits(2 * ones > len(h)).tobytes(), "big")


def fingerprint(text: bytes, shingle: int) -> int:
    return majority(shingle_hashes(text, shingle))


def _prints(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1).cast(pa.binary()).to_pylist()
            fps = np.array([fingerprint(t or b"", shingle) for t in texts], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps)], names=["doc_id", "fp"])

    return run


def fingerprints(docs: DataFrame, shingle: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fp (the 64 bits as a signed long)."""
    pairs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return pairs.mapInArrow(tidy(_prints(shingle)), "doc_id long, fp long")


def gray_rank(fp: np.ndarray) -> np.ndarray:
    """Position of each pattern in the reflected Gray order."""
    r = fp.copy()
    for s in (1, 2, 4, 8, 16, 32):
        r ^= r >> np.uint64(s)
    return r


def _shared(fp: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For runs of fingerprints: the mask of the bits that a run shares, and their values."""
    every, some = np.bitwise_and.reduceat(fp, starts), np.bitwise_or.reduceat(fp, starts)
    mask = ~(every ^ some)
    return mask, every & mask


def _near_nodes(mask: np.ndarray, value: np.ndarray, a: np.ndarray, b: np.ndarray, radius: int) -> np.ndarray:
    return np.bitwise_count((value[a] ^ value[b]) & mask[a] & mask[b]) <= radius


def _expand(a: np.ndarray, b: np.ndarray, fan: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (i, j), i < j, of the children of node pairs; child ids run in order, ``fan`` for each node."""
    k = np.arange(fan)
    i = (a[:, None, None] * fan + k[None, :, None] + 0 * k[None, None, :]).ravel()
    j = (b[:, None, None] * fan + k[None, None, :] + 0 * k[None, :, None]).ravel()
    ok = (i < n) & (j < n) & (i <= j)
    return i[ok], j[ok]


def group_links(fp: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of positions within the radius; ``fp``: distinct fingerprints in Gray order."""
    n = len(fp)
    leaf_mask, leaf_value = _shared(fp, np.arange(0, n, _LEAF))
    leaves = len(leaf_mask)
    top = np.arange(0, n, _LEAF * _UPPER)
    top_mask, top_value = _shared(fp, top)
    for t in range(len(top)):
        others = np.arange(t, len(top))
        near = others[_near_nodes(top_mask, top_value, np.full(len(others), t), others, radius)]
        for at in range(0, len(near), 64):
            b = near[at : at + 64]
            la, lb = _expand(np.full(len(b), t), b, _UPPER, leaves)
            keep = _near_nodes(leaf_mask, leaf_value, la, lb, radius)
            la, lb = la[keep], lb[keep]
            for cut in range(0, len(la), _AT_ONCE // (_LEAF * _LEAF)):
                part = slice(cut, cut + _AT_ONCE // (_LEAF * _LEAF))
                i, j = _expand(la[part], lb[part], _LEAF, n)
                ok = (i < j) & (np.bitwise_count(fp[i] ^ fp[j]) <= radius)
                if ok.any():
                    yield i[ok], j[ok]


def pairs_below(key: np.ndarray, fp: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of places within the radius under one top node; the rows are sorted by top node and Gray rank."""
    bounds = np.flatnonzero(np.r_[True, key[1:] != key[:-1], True]) if len(key) else np.zeros(1, int)
    sizes = np.diff(bounds)
    small = np.repeat(sizes <= 2 * _LEAF, sizes)
    for shift in range(1, 2 * _LEAF):  # small groups, all at once
        i = np.flatnonzero(small[:-shift] & (key[shift:] == key[:-shift]))
        if not len(i):
            break
        i = i[np.bitwise_count(fp[i] ^ fp[i + shift]) <= radius]
        yield i, i + shift
    for g in np.flatnonzero(sizes > 2 * _LEAF):
        for i, j in group_links(fp[bounds[g] : bounds[g + 1]], radius):
            yield bounds[g] + i, bounds[g] + j


def _link(radius: int):
    """Spanning forests of the links below each top node."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cols = [[], [], []]
        for batch in batches:
            for c, x in zip(cols, batch.columns, strict=True):
                c.append(x.to_numpy(zero_copy_only=False))
        if not cols[0]:
            return
        key, fp, node = (np.concatenate(c) for c in cols)
        fp = fp.view(np.uint64)
        order = np.lexsort((gray_rank(fp), key))
        key, fp, node = key[order], fp[order], node[order]
        nodes, at = np.unique(node, return_inverse=True)
        forest = Forest(len(nodes))
        for i, j in pairs_below(key, fp, radius):
            forest.add(at[i], at[j])
        moved = forest.label != np.arange(len(nodes))
        yield pa.RecordBatch.from_arrays([pa.array(nodes[moved]), pa.array(nodes[forest.label[moved]])], names=["a", "b"])

    return run


def block_masks(blocks: int, choose: int) -> list[int]:
    """Masks of every choice of ``choose`` out of ``blocks`` nearly equal bit blocks."""
    edges = [round(64 * i / blocks) for i in range(blocks + 1)]
    single = [((1 << (edges[i + 1] - edges[i])) - 1) << edges[i] for i in range(blocks)]
    return [sum(c) for c in combinations(single, choose)]


def near_groups(docs: DataFrame, shingle: int = 4, radius: int = 4, blocks: int = 7, choose: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id. Complete for a radius of at most ``blocks - choose``; beyond it,
    pairs are found that agree in ``choose`` blocks."""
    prints = checkpointed(fingerprints(docs, shingle, id_col, text_col))
    nodes = prints.filter("doc_id IS NOT NULL").groupBy("fp").agg(F.min("doc_id").alias("node"))
    signed = [m - (1 << 64) if m >> 63 else m for m in block_masks(blocks, choose)]
    top = F.array(*[F.struct(F.lit(i).alias("i"), F.col("fp").bitwiseAND(F.lit(m)).alias("v")) for i, m in enumerate(signed)])
    keyed = nodes.withColumn("top", F.explode(top)).select(F.xxhash64("top.i", "top.v").alias("key"), "fp", "node")
    links = keyed.repartition(shuffle_width(docs.sparkSession), "key").mapInArrow(tidy(_link(radius)), "a long, b long")
    found = components(links)
    named = nodes.join(found, "node", "left").select("fp", F.coalesce("component", "node").alias("component_id"))
    out = prints.join(named, "fp", "left").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"))
    return out
