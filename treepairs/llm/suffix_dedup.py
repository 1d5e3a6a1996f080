"""Removal of repeated byte spans through a range-partitioned sparse suffix array.

The suffixes are those that start at the anchors of :mod:`spans`, one for about 35 bytes. Splitters from a bounded sample
of documents partition them by their leading bytes. Copies of a whole stretch are settled in their bucket at once. What is
left, stretches that share an anchor but differ somewhere, is sorted as suffixes by multikey quicksort, eight bytes to
a key; runs that agree in all ``window`` bytes are equal strings. A bucket boundary never parts equal strings: the key
that is compared with the splitters is a function of the anchor run, which equal strings share.

Defined cases: a null text counts as empty; a text shorter than the window loses nothing; rows that repeat an id hold the
same places, none of which is earlier than the other; rows with a null id take part in no comparison and stay whole; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .span_jobs import batch_of, blobs, by_bucket, dealing, doc_bucket, repeated_spans
from .spans import OPEN, RUN, Powers, merged, mixed, pieces, records

WINDOW, GRAM = 100, 32
#: Documents from which the splitters come.
SAMPLE_DOCS = 2_000
#: Ranges that the splitters make at most; more buckets part each range by a digest of the key.
MOST_RANGES = 2_048
_SYMBOL = (mixed(np.arange(1, 257, dtype=np.uint64)) & ~np.uint64(255)) | np.arange(256, dtype=np.uint64)
_PART = np.dtype([("doc", "<i8"), ("start", "<u4"), ("size", "<u4")])


def byte_symbols(text: bytes) -> np.ndarray:
    return _SYMBOL[np.frombuffer(text, np.uint8)]


def splitters(rows: DataFrame, window: int, gram: int, buckets: int) -> np.ndarray:
    """Keys that part the anchors of the sampled documents evenly."""
    digest = F.xxhash64("doc_id")
    edge = rows.select(digest.alias("h")).orderBy("h").limit(SAMPLE_DOCS).agg(F.max("h")).first()[0]
    if edge is None or buckets < 2:
        return np.empty(0, np.uint64)

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        powers = Powers()
        for batch in batches:
            texts = batch.column(1).cast(pa.binary()).to_pylist()
            for part in pieces(batch.column(0).to_pylist(), (byte_symbols(t or b"") for t in texts), window):
                found = records(*part, window, gram, powers, True)["gram"]
                yield pa.RecordBatch.from_arrays([pa.array((found >> np.uint64(1)).astype(np.int64))], names=["key"])

    marks = [i / buckets for i in range(1, buckets)]
    got = rows.filter(digest <= F.lit(edge)).mapInArrow(keys, "key long").agg(F.percentile_approx("key", marks, 10_000)).first()[0]
    return np.array(got or [], np.uint64) << np.uint64(1)


def sort_windows(text: np.ndarray, at: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Multikey quicksort of the strings of ``window`` bytes at the places ``at``: (places in groups, group of each), equal
    strings only; strings that differ from all others leave as soon as that shows."""
    padded = np.concatenate([text, np.zeros(16, np.uint8)])
    words = np.ndarray((len(padded) - 7,), ">u8", padded, 0, (1,))
    group = np.zeros(len(at), np.int64)
    for depth in range(0, window, 8):
        if not len(at):
            break
        key = words[at + depth].astype(np.uint64)
        if depth + 8 > window:
            key >>= np.uint64(8 * (depth + 8 - window))
        order = np.lexsort((key, group))
        at, key, group = at[order], key[order], group[order]
        new = np.r_[True, (key[1:] != key[:-1]) | (group[1:] != group[:-1])]
        alone = new & np.r_[new[1:], True]
        group = np.cumsum(new)
        at, group = at[~alone], group[~alone]
    return at, group


def later_windows(text: np.ndarray, parts: np.ndarray, window: int) -> np.ndarray:
    """Runs of the windows of the stretches in ``text`` that have an earlier equal one."""
    ends = np.cumsum(parts["size"].astype(np.int64))
    counts = parts["size"].astype(np.int64) - window + 1
    owner = np.repeat(np.arange(len(parts)), counts)
    inner = np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts, counts)
    at, group = sort_windows(text, (ends - parts["size"])[owner] + inner, window)
    owner = np.searchsorted(ends, at, "right")
    doc, start = parts["doc"][owner], parts["start"][owner].astype(np.int64) + at - (ends - parts["size"])[owner]
    order = np.lexsort((start, doc, group))
    doc, start, group = doc[order], start[order], group[order]
    first = np.maximum.accumulate(np.where(np.r_[True, group[1:] != group[:-1]], np.arange(len(group)), 0)) if len(group) else group
    later = (doc != doc[first]) | (start != start[first])
    out = np.empty(int(later.sum()), RUN)
    out["doc"], out["start"], out["end"] = doc[later], start[later], start[later] + window
    return merged(out)


def _opener(window: int):
    def with_deal(deal, buckets):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                by: dict[int, tuple[list, list]] = {}
                for text, raw in zip(batch.column(1).cast(pa.binary()).to_pylist(), batch.column(2).to_pylist(), strict=True):
                    open_ = np.frombuffer(raw, OPEN)
                    for bucket, doc, start, n in zip(deal(open_["gram"], buckets).tolist(), open_["doc"].tolist(), open_["start"].tolist(), open_["n"].tolist(), strict=True):
                        head, body = by.setdefault(bucket, ([], []))
                        part = text[start : start + n + window - 1]
                        head.append((doc, start, len(part)))
                        body.append(part)
                rows = [(b, len(head), zlib.compress(np.array(head, _PART).tobytes() + b"".join(body), 1)) for b, (head, body) in by.items()]
                if rows:
                    yield batch_of(rows)

        return run

    return with_deal


def _comparer(window: int, buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for bucket in by_bucket(batches):
            heads, bodies = [], []
            for n, blob in bucket:
                raw = zlib.decompress(blob)
                heads.append(np.frombuffer(raw[: n * _PART.itemsize], _PART))
                bodies.append(np.frombuffer(raw[n * _PART.itemsize :], np.uint8))
            runs = later_windows(np.concatenate(bodies), np.concatenate(heads), window)
            if len(runs):
                yield batch_of(list(blobs(doc_bucket(runs["doc"], buckets), runs, 1)))

    return run


def _remove(text: bytes, starts: list[int], ends: list[int]) -> tuple[int, int, int, str, bytes]:
    kept, at = [], 0
    for a, b in zip(starts, ends, strict=True):
        kept.append(text[at:a])
        at = b
    kept.append(text[at:])
    rest = b"".join(kept)
    return len(text), len(text) - len(rest), len(starts), hashlib.sha256(rest).hexdigest(), rest


def remove_repeated_bytes(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, with_text: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and, if asked for, the kept bytes, which may cut characters."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).filter("doc_id IS NOT NULL")
    dealt = dealing(rows, "text")
    ranges = min(dealt[0], MOST_RANGES)
    edges, within = splitters(rows, window, gram, ranges), -(-dealt[0] // ranges)

    def deal(key: np.ndarray, n: int) -> np.ndarray:
        place = np.searchsorted(edges, key, "right")
        if within > 1:
            place = place * within + (mixed(key) % np.uint64(within)).astype(np.int64)
        return place % n

    fields = [("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string()), ("kept", pa.binary())][: 5 if with_text else 4]
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", kept binary" if with_text else "")
    return repeated_spans(docs, dealt, window, gram, byte_symbols, deal, _opener(window), _comparer(window, dealt[0]), _remove, fields, schema, id_col, text_col, leading=True)
