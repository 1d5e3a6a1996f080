"""Token counts: lengths only, from batched encoding in Arrow functions.

A text is cut at ASCII white space, where this vocabulary's pre-tokeniser always cuts, so lengths of the pieces add up to
that of the whole text however long it is. Texts are taken in portions of bounded bytes; pieces that are new to a worker are
encoded in batches of nearly equal UTF-8 bytes, and their lengths are kept in a bounded table.

Defined cases: null and empty texts have 0 bytes and 0 tokens; other columns are ignored; an empty table gives an empty
result; repeated rows give repeated rows.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import tidy

#: Bytes of new pieces that one call of the library encodes.
BATCH_BYTES = 1 << 20
#: Pieces whose lengths a worker keeps; the table starts anew beyond it.
KEPT_PIECES = 700_000
#: Longer pieces are encoded each time and never kept.
KEPT_LENGTH = 200
_BLANK = str.maketrans("\t\n\r", "   ")


def utf8_bytes(text: str) -> int:
    return len(text) if text.isascii() else len(text.encode())


def balanced(pieces: list[str], most: int) -> Iterator[list[str]]:
    """The pieces in as few groups as keep to so many UTF-8 bytes, of nearly equal bytes; a longer piece is a group of its own.

    The longest pieces are dealt first, each to the group that has the fewest bytes.
    """
    sizes = sorted(((utf8_bytes(p), i) for i, p in enumerate(pieces)), reverse=True)
    alone = [i for n, i in sizes if n > most]
    rest = [(n, i) for n, i in sizes if n <= most]
    count = -(-sum(n for n, _ in rest) // most) if rest else 0
    if count <= 1:
        groups = [[i for _, i in rest]] if rest else []
    else:
        groups = [[] for _ in range(count)]
        held = [(0, g) for g in range(count)]
        for n, i in rest:
            size, g = held[0]
            if groups[g] and size + n > most:
                groups.append([i])
                heapq.heappush(held, (n, len(groups) - 1))
                continue
            groups[g].append(i)
            heapq.heapreplace(held, (size + n, g))
    for i in alone:
        yield [pieces[i]]
    for group in groups:
        yield [pieces[i] for i in group]


def portions(batch: pa.RecordBatch, most: int) -> Iterator[pa.RecordBatch]:
    """Consecutive rows of at most so many bytes of text; a longer text is a portion of its own."""
    sizes = np.array(pa.compute.fill_null(pa.compute.binary_length(batch.column(1)), 0), np.int64)
    at = held = 0
    for i, n in enumerate(sizes.tolist()):
        if i > at and held + n > most:
            yield batch.slice(at, i - at)
            at, held = i, 0
        held += n
    if at < batch.num_rows:
        yield batch.slice(at)


def token_lengths(path: str, batch_bytes: int = BATCH_BYTES, kept: int = KEPT_PIECES):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        tokenizer = Tokenizer.from_file(path)
        tokenizer.no_truncation()
        tokenizer.no_padding()
        lengths: dict[str, int] = {"": 0}
        for batch in batches:
            for part in portions(batch, batch_bytes):
                texts = [t or "" for t in part.column(1).to_pylist()]
                pieces = [t.translate(_BLANK).split(" ") for t in texts]
                new = list(set().union(*pieces).difference(lengths))
                if len(lengths) + len(new) > kept:
                    lengths = {"": 0}
                    new = list(set().union(*pieces).difference(lengths))
                for group in balanced(new, batch_bytes):
                    lengths.update(zip(group, map(len, tokenizer.encode_batch_fast(group, add_special_tokens=False)), strict=True))
                counts = [sum(map(lengths.__getitem__, p)) for p in pieces]
                for piece in new:
                    if len(piece) > KEPT_LENGTH:
                        del lengths[piece]
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array([utf8_bytes(t) for t in texts], pa.int64()), pa.array(counts, pa.int64())],
                    names=["doc_id", "n_bytes", "n_tokens"],
                )

    return run


def count_tokens(docs: DataFrame, path: str, limit: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit. ``path``: a vocabulary file that every executor can read."""
    pairs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    counted = pairs.mapInArrow(tidy(token_lengths(path)), "doc_id long, n_bytes long, n_tokens long")
    return counted.withColumn("over_limit", F.col("n_tokens") > limit)
