"""The Spark job around :mod:`spans`, shared by the two substring operators."""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed, shuffle_width, tidy
from .spans import OPEN, RECORD, RUN, Powers, as_runs, merged, pieces, records, settle, settle_copies

#: Bytes of records that a task gathers before it packs them by bucket.
PACKED_BYTES = 24 << 20
#: Bytes of text whose records one bucket holds on average, and buckets that one task reads, one after the other.
BUCKET_BYTES, BUCKETS_A_TASK = 16 << 20, 4
_BLOBS = "bucket int, kind int, blob binary"


def dealing(docs: DataFrame, text_col: str) -> tuple[int, int]:
    """Numbers of buckets and of tasks: they rise with the bytes of the texts, so a bucket does not."""
    width = shuffle_width(docs.sparkSession)
    size = docs.agg(F.sum(F.octet_length(F.col(f"`{text_col}`")))).first()[0] or 0
    buckets = max(2 * width, -(-size // BUCKET_BYTES))
    return buckets, max(width, -(-buckets // BUCKETS_A_TASK))


def to_tasks(packed: DataFrame, tasks: int) -> DataFrame:
    return packed.repartition(tasks, "bucket").sortWithinPartitions("bucket")


def by_bucket(batches: Iterator[pa.RecordBatch]) -> Iterator[list[tuple[int, bytes]]]:
    """The kinds and blobs of one bucket after the other; the rows of a task are sorted by bucket."""
    at, held = None, []
    for batch in batches:
        for bucket, kind, blob in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
            if bucket != at and held:
                yield held
                held = []
            at = bucket
            held.append((kind, blob))
    if held:
        yield held


def blobs(bucket: np.ndarray, rows: np.ndarray, kind: int) -> Iterator[tuple[int, int, bytes]]:
    """One blob per bucket: the columns one after the other, compressed lightly."""
    order = np.argsort(bucket, kind="stable")
    bucket, rows = bucket[order], rows[order]
    edges = np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1], True]) if len(rows) else [0]
    for a, b in zip(edges[:-1], edges[1:], strict=True):
        part = rows[a:b]
        if "gram" in rows.dtype.names:
            part = part[np.argsort(part["doc"], kind="stable")]
        yield int(bucket[a]), kind, zlib.compress(b"".join(np.ascontiguousarray(part[n]).tobytes() for n in rows.dtype.names), 1)


def unpacked(blob: bytes, dtype: np.dtype) -> np.ndarray:
    raw = zlib.decompress(blob)
    n, at = len(raw) // dtype.itemsize, 0
    out = np.empty(n, dtype)
    for name in dtype.names:
        size = dtype[name].itemsize * n
        out[name] = np.frombuffer(raw[at : at + size], dtype[name])
        at += size
    return out


def batch_of(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.binary())], names=["bucket", "kind", "blob"])


def doc_bucket(doc: np.ndarray, buckets: int) -> np.ndarray:
    x = doc.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return ((x >> np.uint64(33)) % np.uint64(buckets)).astype(np.int64)


def anchors(symbols: Callable, window: int, gram: int, deal: Callable, buckets: int, leading: bool):
    """Mapper: (doc_id, text) to packed records (kind 0) and, for copies met on the way, removed runs (kind 1)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        powers = Powers()
        held: list[np.ndarray] = []

        def packed() -> pa.RecordBatch:
            later, firsts = settle_copies(np.concatenate(held))
            runs = merged(as_runs(later, window))
            return batch_of([*blobs(deal(firsts["gram"], buckets), firsts, 0), *blobs(doc_bucket(runs["doc"], buckets), runs, 1)])

        for batch in batches:
            texts = batch.column(1).cast(pa.binary()).to_pylist()
            for part in pieces(batch.column(0).to_pylist(), (symbols(t or b"") for t in texts), window):
                held.append(records(*part, window, gram, powers, leading))
                if sum(h.nbytes for h in held) > PACKED_BYTES:
                    yield packed()
                    held.clear()
        if held:
            yield packed()

    return run


def bucket_settler(window: int, buckets: int):
    """Reducer, bucket by bucket: removed runs (kind 1) and open stretches (kind 2), dealt by document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        runs: list[np.ndarray] = []
        open_: list[np.ndarray] = []

        def packed() -> Iterator[pa.RecordBatch]:
            for kind, rows in ((1, merged(np.concatenate([np.empty(0, RUN), *runs]))), (2, np.concatenate([np.empty(0, OPEN), *open_]))):
                if len(rows):
                    yield batch_of(list(blobs(doc_bucket(rows["doc"], buckets), rows, kind)))

        for bucket in by_bucket(batches):
            runs += [unpacked(blob, RUN) for kind, blob in bucket if kind]
            held = [unpacked(blob, RECORD) for kind, blob in bucket if not kind]
            if held:
                removed, left = settle(np.concatenate(held), window)
                runs.append(removed)
                open_.append(left)
            if sum(x.nbytes for x in (*runs, *open_)) > PACKED_BYTES:
                yield from packed()
                runs.clear()
                open_.clear()
        yield from packed()

    return run


def _by_document(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each document: its removed runs and its open stretches."""
    for bucket in by_bucket(batches):
        r = merged(np.concatenate([np.empty(0, RUN), *(unpacked(blob, RUN) for kind, blob in bucket if kind == 1)]))
        o = np.concatenate([np.empty(0, OPEN), *(unpacked(blob, OPEN) for kind, blob in bucket if kind == 2)])
        o = o[np.argsort(o["doc"], kind="stable")]
        docs = np.unique(np.concatenate([r["doc"], o["doc"]]))
        r_at, r_to = np.searchsorted(r["doc"], docs), np.searchsorted(r["doc"], docs, "right")
        o_at, o_to = np.searchsorted(o["doc"], docs), np.searchsorted(o["doc"], docs, "right")
        for at in range(0, len(docs), 5000):
            span = range(at, min(at + 5000, len(docs)))
            yield pa.RecordBatch.from_arrays(
                [pa.array(docs[at : at + 5000]), pa.array([r[r_at[i] : r_to[i]].tobytes() for i in span], pa.binary()), pa.array([o[o_at[i] : o_to[i]].tobytes() for i in span], pa.binary())],
                names=["doc_id", "runs", "open"],
            )


def by_document(packed: DataFrame, tasks: int) -> DataFrame:
    return to_tasks(packed, tasks).mapInArrow(tidy(_by_document), "doc_id long, runs binary, open binary")


def finisher(remove: Callable, fields: list[tuple[str, pa.DataType]]):
    """(doc_id, text, runs of the copies, runs of the comparison) to a document's row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                ids = part.column(0)
                rows = []
                for text, a, b in zip(part.column(1).cast(pa.binary()).to_pylist(), part.column(2).to_pylist(), part.column(3).to_pylist(), strict=True):
                    runs = merged(np.frombuffer((a or b"") + (b or b""), RUN))
                    rows.append(remove(text or b"", runs["start"].tolist(), runs["end"].tolist()))
                yield pa.RecordBatch.from_arrays([ids, *[pa.array([r[i] for r in rows], t) for i, (_, t) in enumerate(fields)]], names=["doc_id", *[n for n, _ in fields]])

    return run


def repeated_spans(docs: DataFrame, dealt: tuple[int, int], window: int, gram: int, symbols: Callable, deal: Callable, opener: Callable, comparer: Callable, remove: Callable, fields: list[tuple[str, pa.DataType]], schema: str, id_col: str, text_col: str, leading: bool = False) -> DataFrame:
    buckets, tasks = dealt
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    known = rows.filter("doc_id IS NOT NULL")
    mapped = known.mapInArrow(tidy(anchors(symbols, window, gram, deal, buckets, leading)), _BLOBS)
    packed = to_tasks(mapped, tasks).mapInArrow(tidy(bucket_settler(window, buckets)), _BLOBS)
    settled = checkpointed(by_document(packed, tasks))
    # One exchange of the texts serves both joins.
    texts = rows.repartition(tasks, "doc_id")
    open_ = settled.filter("length(open) > 0").select("doc_id", "open")
    stretches = texts.join(open_, "doc_id").select("doc_id", "text", "open").mapInArrow(tidy(opener(deal, buckets)), _BLOBS)
    more = by_document(to_tasks(stretches, tasks).mapInArrow(tidy(comparer), _BLOBS), tasks).select("doc_id", F.col("runs").alias("more"))
    found = settled.filter("length(runs) > 0").select("doc_id", "runs").join(more, "doc_id", "full")
    return texts.join(found, "doc_id", "left").select("doc_id", "text", "runs", "more").mapInArrow(tidy(finisher(remove, fields)), schema)
