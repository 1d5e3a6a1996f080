"""BPE encoding and decoding with reuse of content-defined chunks.

A gear rolling hash over the UTF-8 bytes cuts a text where its low bits vanish, so equal passages of different documents
are cut alike. A chunk is encoded once: its body, from the first to the last place at which the pre-tokeniser certainly cuts (a
single space between two characters that are not white space), is kept with its ids and its decoded form, and with the head
and the tail beside it. A chunk join is repaired by encoding the tail on its left with the head on its right anew; a chunk
without a certain cut has no body and goes on into the next join, until a chunk with one is met. From there on the ids agree
with those of the whole text, since a certain cut is an end of a token on either side.

New bodies and joins are split into units at the certain cuts; units that are new to a worker are encoded together as one text
and their ids parted where the ends of tokens agree with the ends of units. Chunks and units are kept in bounded tables of a
worker. A global chunk table would have to shuffle every text and its ids, more than the disk that the operator may use.

Defined cases: null and empty texts have no ids and decode to the empty string; rows that repeat an id or have a null one give
a row each; very long texts are encoded whole; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import tidy

#: A chunk ends where this many low bits of the rolling hash are zero: 256 bytes on average.
CUT_BITS = 8
#: The rolling hash looks back over so many bytes.
ROLL = 16
#: Units and chunks that a worker keeps; the tables start anew beyond it.
KEPT_UNITS, KEPT_CHUNKS = 300_000, 60_000
_KEPT_LENGTH = 200
#: A piece that begins with a single space and ends without one stands apart from any other such piece.
_APART = re.compile(r" \S(?:.*\S)?\Z", re.DOTALL)
#: Characters of new pieces that are encoded as one text.
BLOCK_CHARS = 1 << 15
_CERTAIN = re.compile(r"(?<=\S) (?=\S)")


def _gear() -> np.ndarray:
    x = np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    return (x ^ (x >> np.uint64(32))).astype(np.uint32)


_GEAR = _gear()


def cuts(data: bytes, bits: int = CUT_BITS) -> np.ndarray:
    """Ends of the chunks but the last: places where the hash of the last ROLL bytes has ``bits`` zero bits."""
    if len(data) <= ROLL:
        return np.empty(0, np.int64)
    g = _GEAR[np.frombuffer(data, np.uint8)]
    h, width = g.copy(), 1
    while width < ROLL:  # doubling: the sum over 2w bytes is that over the last w and, shifted, that over the w before
        h[width:] += h[:-width] << np.uint32(width)
        width *= 2
    ends = np.flatnonzero((h[ROLL - 1 :] >> np.uint32(16 - bits) & np.uint32((1 << bits) - 1)) == 0) + ROLL
    raw = np.frombuffer(data, np.uint8)
    ends = ends[ends < len(data)]
    return ends[(raw[ends] & 0xC0) != 0x80]  # between characters only


class Chunk:
    """Head, units of the body and tail of a chunk; the body's ids and decoded form once it is encoded."""

    __slots__ = ("decoded", "head", "ids", "tail", "units")

    def __init__(self, head: str, units: list[str], tail: str) -> None:
        self.head, self.units, self.tail = head, units, tail
        self.ids: bytes | None = None
        self.decoded = ""


class ChunkEncoder:
    """Encodes texts as the library does for the whole text; keeps what it has encoded."""

    def __init__(self, path: str, units: int = KEPT_UNITS, chunks: int = KEPT_CHUNKS) -> None:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        special = self.library.get_added_tokens_decoder()
        vocabulary = self.library.get_vocab(with_added_tokens=True)
        # In a byte-level vocabulary a character of a token stands for a byte.
        self.token_bytes = np.zeros(max(vocabulary.values()) + 1, np.int64)
        for token, i in vocabulary.items():
            self.token_bytes[i] = len(token.encode()) if i in special else len(token)
        self.most_units, self.most_chunks = units, chunks
        self.units: dict[str, bytes] = {}
        self.unlike: dict[str, str] = {}  # decoded forms that differ from their pieces
        self.chunks: dict[str, Chunk | None] = {}
        self.seen = self.reused = 0  # chunks with a body, and those of them that were encoded before

    def chunk(self, text: str) -> Chunk | None:
        """The chunk from the table, or split and put there; None without a certain cut. All but the head start with their space."""
        found = self.chunks.get(text, 0)
        if found == 0:
            pieces = _CERTAIN.split(text)
            found = None if len(pieces) == 1 else Chunk(pieces[0], [" " + p for p in pieces[1:-1]], " " + pieces[-1])
            if len(self.chunks) >= self.most_chunks:
                self.chunks.clear()
            self.chunks[text] = found
            self.seen += found is not None
        elif found is not None:
            self.seen += 1
            self.reused += 1
        return found

    def parts(self, text: str) -> list[str | Chunk]:
        """The text as chunks, whose bodies count, and the units of the repaired joins between them."""
        if not text:
            return []
        data = text.encode()
        at, out, held = 0, [], ""
        for end in [*cuts(data).tolist(), len(data)]:
            piece = data[at:end].decode()
            at = end
            # A cut may fall beside a space: the certain places at the join itself are found on the joined piece.
            found = self.chunk(piece)
            if found is None:
                held += piece
                continue
            joined = held + found.head
            out.extend(self._rejoin(joined) if " " in joined[1:] else [joined] if joined else [])
            out.append(found)
            held = found.tail
        out.extend(self._rejoin(held))
        return out

    @staticmethod
    def _rejoin(piece: str) -> list[str]:
        if not piece:
            return []
        cut = _CERTAIN.split(piece)
        return [cut[0], *[" " + p for p in cut[1:]]]

    def _encode_each(self, pieces: list[str]) -> None:
        for at in range(0, len(pieces), 4096):
            group = pieces[at : at + 4096]
            ids = [e.ids for e in self.library.encode_batch_fast(group, add_special_tokens=False)]
            back = self.library.decode_batch(ids, skip_special_tokens=False)
            for piece, i, b in zip(group, ids, back, strict=True):
                self.units[piece] = array("I", i).tobytes()
                if b != piece:
                    self.unlike[piece] = b

    def _encode_block(self, pieces: list[str]) -> None:
        """Encode the pieces as one text and part the ids at their ends. Pieces whose ends are not ends of tokens, or a
        block that does not decode to itself, are left to be encoded one by one."""
        text = "".join(pieces)
        ids = self.library.encode_batch_fast([text], add_special_tokens=False)[0].ids
        if self.library.decode(ids, skip_special_tokens=False) != text:
            return
        packed = np.array(ids, np.uint32)
        token_ends = np.cumsum(self.token_bytes[packed])
        raw = packed.astype("<u4").tobytes()
        ends = np.cumsum([len(p.encode()) for p in pieces])
        at = np.searchsorted(token_ends, ends)
        sound = (at < len(token_ends)) & (token_ends[np.minimum(at, len(token_ends) - 1)] == ends)
        first = 0
        for piece, last, ok in zip(pieces, (4 * (at + 1)).tolist(), sound.tolist(), strict=True):
            if not ok:
                return
            self.units[piece] = raw[first:last]
            first = last

    def _encode_new(self, pieces: set[str]) -> list[str]:
        """Put the ids of the pieces into the table; those that were new."""
        new = pieces.difference(self.units)
        if len(self.units) + len(new) > self.most_units:
            self.units.clear()
            self.unlike.clear()
            new = pieces
        fresh = list(new)
        # Pieces that certainly stand apart are encoded as one text; the others one by one.
        block: list[str] = []
        size = 0
        for piece in fresh:
            if not _APART.match(piece):
                continue
            block.append(piece)
            size += len(piece)
            if size >= BLOCK_CHARS:
                self._encode_block(block)
                block, size = [], 0
        if block:
            self._encode_block(block)
        self._encode_each([p for p in fresh if p not in self.units])
        return fresh

    def encode(self, texts: list[str]) -> list[tuple[bytes, str]]:
        """For each text its ids, 32-bit little-endian, and their decoded form."""
        lists = [self.parts(t) for t in texts]
        open_ = {id(c): c for parts in lists for c in parts if type(c) is Chunk and c.ids is None}
        wanted = {p for parts in lists for p in parts if type(p) is str}
        fresh = self._encode_new(wanted.union(*(c.units for c in open_.values())))
        ids, odd = self.units, self.unlike
        for c in open_.values():
            c.ids = b"".join([ids[u] for u in c.units])
            c.decoded = "".join([odd.get(u, u) for u in c.units]) if odd else "".join(c.units)
            c.units = []
        out = []
        for parts in lists:
            packed = b"".join([ids[p] if type(p) is str else p.ids for p in parts])
            out.append((packed, "".join([odd.get(p, p) if type(p) is str else p.decoded for p in parts])))
        for piece in fresh:
            if len(piece) > _KEPT_LENGTH:
                del self.units[piece]
        return out


def _encoded(path: str, digest: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = ChunkEncoder(path)
        for batch in batches:
            for at in range(0, batch.num_rows, 128):
                part = batch.slice(at, 128)
                done = encoder.encode([t or "" for t in part.column(1).to_pylist()])
                counts = pa.array([len(i) // 4 for i, _ in done], pa.int64())
                if digest:
                    rest = [pa.array([hashlib.sha256(i).hexdigest() for i, _ in done]), pa.array([hashlib.sha256(d.encode()).hexdigest() for _, d in done])]
                    yield pa.RecordBatch.from_arrays([part.column(0), counts, *rest], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])
                else:
                    ids = pa.array([np.frombuffer(i, "<u4").astype(np.int32) for i, _ in done], pa.list_(pa.int32()))
                    yield pa.RecordBatch.from_arrays([part.column(0), counts, ids, pa.array([d for _, d in done], pa.string())], names=["doc_id", "n_tokens", "ids", "decoded"])

    return run


def _pairs(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))


def encode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_tokens, ids, decoded."""
    return _pairs(docs, id_col, text_col).mapInArrow(tidy(_encoded(path, False)), "doc_id long, n_tokens long, ids array<int>, decoded string")


def encode_digest(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256, made in the worker that encodes."""
    return _pairs(docs, id_col, text_col).mapInArrow(tidy(_encoded(path, True)), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
