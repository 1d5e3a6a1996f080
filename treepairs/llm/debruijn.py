"""Removal of repeated word spans through a compacted De Bruijn graph.

A window of ``window`` words is an edge of the graph between its first and its last ``window - 1`` words. Consecutive edges
with one anchor run of words (:mod:`spans`) are a path without a branch inside its text; it travels as one compacted
edge. Joining the compacted edges by anchor run shows where the graph is simple (all paths through the run are equal) and
where it branches (several paths). Repeated simple paths are settled by their copies; at branches, a join with the texts
brings the words at the source coordinates, and single edges are compared by their words.

Defined cases: a null text has no words; a text shorter than the window loses nothing; rows that repeat an id hold the
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

from .span_jobs import batch_of, blobs, by_bucket, dealing, doc_bucket, repeated_spans
from .spans import OPEN, RUN, merged

WINDOW, GRAM = 20, 7


def word_symbols(text: bytes) -> np.ndarray:
    import xxhash

    digest = xxhash.xxh3_64_intdigest
    words = text.split()  # for bytes: space and 09 to 0D
    return np.fromiter(map(digest, words), np.uint64, len(words))


def deal(key: np.ndarray, buckets: int) -> np.ndarray:
    return ((key >> np.uint64(20)) % np.uint64(buckets)).astype(np.int64)


def _opener(window: int):
    def with_deal(deal, buckets):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                by: dict[int, list[bytes]] = {}
                for text, raw in zip(batch.column(1).cast(pa.binary()).to_pylist(), batch.column(2).to_pylist(), strict=True):
                    open_ = np.frombuffer(raw, OPEN)
                    words = text.split()
                    for bucket, doc, start, n in zip(deal(open_["gram"], buckets).tolist(), open_["doc"].tolist(), open_["start"].tolist(), open_["n"].tolist(), strict=True):
                        by.setdefault(bucket, []).append(b"%d %d %s" % (doc, start, b" ".join(words[start : start + n + window - 1])))
                rows = [(b, len(lines), zlib.compress(b"\n".join(lines), 1)) for b, lines in by.items()]
                if rows:
                    yield batch_of(rows)

        return run

    return with_deal


def later_edges(lines: Iterator[bytes], window: int) -> np.ndarray:
    """Runs of the edges of the open paths that also start earlier. The least place of each sequence of words is kept by a
    digest of 128 bits, and the words themselves only where two places meet."""
    import xxhash

    places: dict[int, list[tuple[int, int, bytes]]] = {}
    seen: dict[int, tuple[int, int, bytes, int, int]] = {}
    digest = xxhash.xxh3_128_intdigest
    for line in lines:
        doc, start, rest = line.split(b" ", 2)
        doc, start = int(doc), int(start)
        ends = np.flatnonzero(np.frombuffer(rest, np.uint8) == 32).tolist()
        ends.append(len(rest))
        begin = 0
        for i in range(len(ends) - window + 1):
            key = digest(rest[begin : ends[i + window - 1]])
            here = (doc, start + i, rest, begin, ends[i + window - 1])
            begin = ends[i] + 1
            before = seen.setdefault(key, here)
            if before is not here:
                places.setdefault(key, [before]).append(here)
    found = []
    for group in places.values():
        by_words: dict[bytes, list[tuple[int, int]]] = {}
        for doc, start, rest, a, b in group:
            by_words.setdefault(rest[a:b], []).append((doc, start))
        for same in by_words.values():
            low = min(same)
            found.extend((d, s, s + window) for d, s in same if (d, s) != low)
    return merged(np.array(found, RUN))


def _comparer(window: int, buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for bucket in by_bucket(batches):
            runs = later_edges((line for _, blob in bucket for line in zlib.decompress(blob).split(b"\n")), window)
            if len(runs):
                yield batch_of(list(blobs(doc_bucket(runs["doc"], buckets), runs, 1)))

    return run


def _remove(text: bytes, starts: list[int], ends: list[int]) -> tuple[int, int, str, str]:
    words = text.split()
    kept, at = [], 0
    for a, b in zip(starts, ends, strict=True):
        kept.extend(words[at:a])
        at = b
    kept.extend(words[at:])
    rest = b" ".join(kept)
    return len(words), len(words) - len(kept), hashlib.sha256(rest).hexdigest(), rest.decode()


def remove_repeated_words(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, with_text: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 and, if asked for, the kept words joined by single spaces."""
    fields = [("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string()), ("kept", pa.string())][: 4 if with_text else 3]
    schema = "doc_id long, n_words long, n_removed long, kept_sha256 string" + (", kept string" if with_text else "")
    dealt = dealing(docs, text_col)
    return repeated_spans(docs, dealt, window, gram, word_symbols, deal, _opener(window), _comparer(window, dealt[0]), _remove, fields, schema, id_col, text_col)
