"""Exact deduplication by Grace hash partitioning.

Records go to shuffle partitions by a digest of their normalised content. Inside a partition a bucket that is larger
than a memory bound is split into spill files by further digest bits, again and again, until its distinct contents fit
an open-addressing table that compares complete contents. Copies that meet in one Arrow batch are collapsed before the
shuffle, so a content held by a third of all rows arrives once per batch.

Defined cases: a null text counts as empty; very long texts are compared whole; rows that repeat an id are members of their
groups like any other row; a null id never becomes keep_id unless the whole group has null ids; any long may be an id; an empty table gives an empty result; other columns
of the input are ignored here and carried by :func:`keep_first`.
"""

from __future__ import annotations

import hashlib
import os
import re
import struct
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SEPARATORS, content_digest, one_row_per_text, repeats, shuffle_width, tidy, unused

_RUN = re.compile(SEPARATORS.encode())
_HEAD = struct.Struct("<32sIIq")
#: A bucket with more content than this many bytes is split into spill files.
BUCKET_BYTES = 48 << 20
_FAN = 16


class OpenTable:
    """Open addressing with linear probing over (digest, content); equality is that of the complete content."""

    def __init__(self) -> None:
        self.slots = [-1] * 1024
        self.digests: list[bytes] = []
        self.contents: list[bytes] = []
        self.smallest: list[int | None] = []
        self.rows: list[int] = []
        self.bytes = 0

    def _probe(self, digest: bytes, content: bytes) -> tuple[int, int]:
        mask = len(self.slots) - 1
        at = int.from_bytes(digest[-8:], "little") & mask
        while (entry := self.slots[at]) >= 0:
            if self.digests[entry] == digest and self.contents[entry] == content:
                return at, entry
            at = (at + 1) & mask
        return at, -1

    def find(self, digest: bytes, content: bytes) -> int:
        return self._probe(digest, content)[1]

    def add(self, digest: bytes, content: bytes, ids: np.ndarray, nulls: int) -> None:
        at, entry = self._probe(digest, content)
        low = int(ids.min()) if len(ids) else None
        if entry < 0:
            self.slots[at] = len(self.contents)
            self.digests.append(digest)
            self.contents.append(content)
            self.smallest.append(low)
            self.rows.append(len(ids) + nulls)
            self.bytes += len(content) + 120
            if 2 * len(self.contents) > len(self.slots):
                self._grow()
        else:
            self.rows[entry] += len(ids) + nulls
            if low is not None and (self.smallest[entry] is None or low < self.smallest[entry]):
                self.smallest[entry] = low

    def _grow(self) -> None:
        self.slots = [-1] * (2 * len(self.slots))
        mask = len(self.slots) - 1
        for entry, digest in enumerate(self.digests):
            at = int.from_bytes(digest[-8:], "little") & mask
            while self.slots[at] >= 0:
                at = (at + 1) & mask
            self.slots[at] = entry


def _write(out, digest: bytes, content: bytes, ids: bytes, nulls: int) -> None:
    out.write(_HEAD.pack(digest, len(content), len(ids), nulls))
    out.write(content)
    out.write(ids)


Record = tuple[bytes, bytes, bytes, int]


def _read(path: str) -> Iterator[Record]:
    with open(path, "rb", buffering=1 << 20) as src:
        while head := src.read(_HEAD.size):
            digest, n, m, nulls = _HEAD.unpack(head)
            yield digest, src.read(n), src.read(m), nulls


def _split(records: Iterator[Record], folder: str, level: int) -> list[str]:
    paths = [os.path.join(folder, f"{level}-{i}-{os.urandom(4).hex()}") for i in range(_FAN)]
    outs = [open(p, "wb", buffering=1 << 18) for p in paths]  # noqa: SIM115
    try:
        for record in records:
            _write(outs[(record[0][level // 2] >> (4 * (level % 2))) % _FAN], *record)
    finally:
        for out in outs:
            out.close()
    return paths


def _resolve(path: str, folder: str, level: int, limit: int) -> Iterator[tuple[bytes, np.ndarray, int, OpenTable, int]]:
    """Records of a spilled bucket with their table entries; splits it while its distinct contents exceed the limit."""
    table = OpenTable()
    for digest, content, ids, nulls in _read(path):
        table.add(digest, content, np.frombuffer(ids, np.int64), nulls)
        if table.bytes > limit and level < 24 and len(table.contents) > 1:
            table = None
            break
    if table is None:
        parts = _split(_read(path), folder, level)
        os.unlink(path)
        for part in parts:
            yield from _resolve(part, folder, level + 1, limit)
        return
    for digest, content, ids, nulls in _read(path):
        yield digest, np.frombuffer(ids, np.int64), nulls, table, table.find(digest, content)
    os.unlink(path)


def _collapse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        groups: dict[bytes, list[int]] = {}
        for row_id, text in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.binary()).to_pylist(), strict=True):
            groups.setdefault(_RUN.sub(b" ", text) if text else b"", []).append(row_id)
        digests = [hashlib.sha256(c).digest() for c in groups]
        yield pa.RecordBatch.from_arrays(
            [
                pa.array([int.from_bytes(d[:7], "little") for d in digests], pa.int64()),
                pa.array(digests, pa.binary()),
                pa.array(list(groups), pa.binary()),
                pa.array([np.array([i for i in v if i is not None], np.int64).tobytes() for v in groups.values()], pa.binary()),
                pa.array([v.count(None) for v in groups.values()], pa.int64()),
            ],
            names=["bucket", "digest", "content", "ids", "nulls"],
        )


def _emit(items: Iterator[tuple[bytes, np.ndarray, int, OpenTable, int]], most: int = 50_000) -> Iterator[pa.RecordBatch]:
    cols: list[list] = [[], [], [], [], [], []]
    held = 0

    def flush() -> pa.RecordBatch:
        ids, keep, size = (np.concatenate(c) for c in cols[:3])
        keep_null, null = np.concatenate(cols[4]), np.concatenate(cols[5])
        out = pa.RecordBatch.from_arrays(
            [
                pa.array(ids, mask=null),
                pa.array(keep, mask=keep_null),
                pa.array(size),
                pa.array((ids == keep) & ~null & ~keep_null | (null & keep_null)),
                pa.array(cols[3], pa.string()),
            ],
            names=["doc_id", "keep_id", "group_size", "kept", "text_sha256"],
        )
        for c in cols:
            c.clear()
        return out

    def parts(ids: np.ndarray, nulls: int) -> Iterator[tuple[np.ndarray, bool]]:
        for at in range(0, len(ids), most):
            yield ids[at : at + most], False
        for at in range(0, nulls, most):
            yield np.zeros(min(most, nulls - at), np.int64), True

    for digest, ids, nulls, table, entry in items:
        low = table.smallest[entry]
        for part, null in parts(ids, nulls):
            cols[0].append(part)
            cols[1].append(np.full(len(part), 0 if low is None else low, np.int64))
            cols[2].append(np.full(len(part), table.rows[entry], np.int64))
            cols[3].extend([digest.hex()] * len(part))
            cols[4].append(np.full(len(part), low is None))
            cols[5].append(np.full(len(part), null))
            held += len(part)
            if held >= most:
                yield flush()
                held = 0
    if held:
        yield flush()


def _grace(limit: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def records() -> Iterator[Record]:
            for batch in batches:
                yield from zip(*(batch.column(i).to_pylist() for i in (1, 2, 3, 4)), strict=True)

        with tempfile.TemporaryDirectory(prefix="grace-") as folder:

            def items():
                for part in _split(records(), folder, 0):
                    yield from _resolve(part, folder, 1, limit)

            yield from _emit(items())

    return run


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bucket_bytes: int = BUCKET_BYTES) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256 (of the normalised text)."""
    pairs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    collapsed = pairs.mapInArrow(tidy(_collapse), "bucket long, digest binary, content binary, ids binary, nulls long")
    dealt = collapsed.repartition(shuffle_width(docs.sparkSession), "bucket")
    return dealt.mapInArrow(tidy(_grace(bucket_bytes)), "doc_id long, keep_id long, group_size long, kept boolean, text_sha256 string")


def keep_first(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows that stay, with all their columns; rows with a null id stay as well. Of rows that repeat an id and a text one
    stays; rows that repeat an id with different texts are judged each by its text."""
    digest = unused(docs.columns, "digest")
    kept = exact_groups(docs, id_col, text_col).filter("kept AND doc_id IS NOT NULL").select(F.col("doc_id").alias(id_col), F.col("text_sha256").alias(digest)).distinct()
    known = docs.filter(F.col(id_col).isNotNull()).withColumn(digest, content_digest(text_col))
    stay = known.join(kept, [id_col, digest], "left_semi")
    if repeats(known, id_col, digest)[0]:
        stay = one_row_per_text(stay, id_col, text_col, digest)
    return stay.select([F.col(f"`{c}`") for c in docs.columns]).unionByName(docs.filter(F.col(id_col).isNull()))
