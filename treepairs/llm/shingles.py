"""Sets of hashed word shingles for many texts at once, with array operations only.

A word is hashed by a polynomial over its bytes (differences of prefix sums, so all words of a piece at once), a word beyond
``_LONG`` bytes by XXH64; both are mixed. A shingle's hash is a mixed sum of its words' hashes with odd factors by place.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import cache

import numpy as np

from .common import SEPARATORS

_SEPARATOR = re.compile(SEPARATORS.encode())
#: Bytes that are hashed at once.
_PIECE = 1 << 20
#: Rows of bits that are added up at once.
_ROWS = 1 << 17
_LONG = 4096
_BASE = 0x9E3779B97F4A7C15
_IS_SEPARATOR = np.array([c == 0x20 or 0x09 <= c <= 0x0D for c in range(256)])


def mixed(h: np.ndarray, k: int = 1) -> np.ndarray:
    """Another hash of the same values (the finaliser of SplitMix64)."""
    z = h + np.uint64((k * 0x9E3779B97F4A7C15) & (2**64 - 1))
    z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return z ^ (z >> np.uint64(31))


@cache
def _powers() -> tuple[np.ndarray, np.ndarray]:
    out = []
    for base in (_BASE, pow(_BASE, -1, 1 << 64)):
        factors = np.full(_PIECE + 1, base, np.uint64)
        factors[0] = 1
        out.append(np.cumprod(factors))
    return out[0], out[1]


def _pieces(data: bytes) -> Iterator[tuple[int, int]]:
    """Bounds of pieces of at most ``_PIECE`` bytes that end at separators; a word that is longer is one piece."""
    at = 0
    while at < len(data):
        end = min(len(data), at + _PIECE)
        if end < len(data):
            seps = np.flatnonzero(_IS_SEPARATOR[np.frombuffer(data, np.uint8, end - at, at)])
            if len(seps):
                end = at + int(seps[-1]) + 1
            else:
                found = _SEPARATOR.search(data, end)
                end = found.start() if found else len(data)
        yield at, end
        at = end


def word_hashes(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Starts and hashes of the words of the bytes."""
    import xxhash

    power, inverse = _powers()
    starts, hashes = [np.empty(0, np.int64)], [np.empty(0, np.uint64)]
    for at, stop in _pieces(data):
        if stop - at > _PIECE:
            starts.append(np.array([at]))
            hashes.append(mixed(np.array([xxhash.xxh64_intdigest(data[at:stop])], np.uint64)))
            continue
        symbols = np.frombuffer(data, np.uint8, stop - at, at)
        turn = np.diff(np.concatenate([[True], _IS_SEPARATOR[symbols], [True]]).astype(np.int8))
        first, last = np.flatnonzero(turn == -1), np.flatnonzero(turn == 1)
        sums = np.zeros(len(symbols) + 1, np.uint64)
        np.cumsum((symbols.astype(np.uint64) + np.uint64(1)) * power[: len(symbols)], out=sums[1:])
        value = (sums[last] - sums[first]) * inverse[first]
        for i in np.flatnonzero(last - first > _LONG):
            value[i] = xxhash.xxh64_intdigest(data[at + int(first[i]) : at + int(last[i])])
        starts.append(first + at)
        hashes.append(mixed(value))
    return np.concatenate(starts), np.concatenate(hashes)


class ShingleSets:
    """The distinct shingle hashes of texts, ascending: those of text ``i`` are ``values[bounds[i]:bounds[i + 1]]``."""

    def __init__(self, texts: list[bytes], shingle: int) -> None:
        sizes = np.array([len(t) + 1 for t in texts], np.int64)
        offsets = np.r_[0, np.cumsum(sizes)]
        start, word = word_hashes(b"\n".join(texts).lower())
        doc = np.searchsorted(offsets, start, side="right") - 1
        count = np.bincount(doc, minlength=len(texts))
        begin = np.r_[0, np.cumsum(count)]
        factor = mixed(np.arange(shingle, dtype=np.uint64), 7) | np.uint64(1)
        n = max(0, len(word) - shingle + 1)
        h = np.zeros(n, np.uint64)
        for i in range(shingle):
            h += word[i : i + n] * factor[i]
        whole = doc[:n] == doc[shingle - 1 :] if n else np.empty(0, bool)
        short = np.flatnonzero((count > 0) & (count < shingle))
        few = np.full(len(short), 0xA24BAED4963EE407, np.uint64) * count[short].astype(np.uint64)
        for i in range(shingle - 1):
            has = count[short] > i
            few[has] += word[begin[short[has]] + i] * factor[i]
        value, owner = np.concatenate([mixed(h[whole]), mixed(few, 2)]), np.concatenate([doc[:n][whole], short])
        order = np.lexsort((value, owner))
        value, owner = value[order], owner[order]
        new = np.concatenate([[True], (value[1:] != value[:-1]) | (owner[1:] != owner[:-1])])[: len(value)]
        self.values, self.owner = value[new], owner[new]
        self.bounds = np.searchsorted(self.owner, np.arange(len(texts) + 1))

    def __len__(self) -> int:
        return len(self.bounds) - 1

    def __getitem__(self, i: int) -> np.ndarray:
        return self.values[self.bounds[i] : self.bounds[i + 1]]

    @property
    def sizes(self) -> np.ndarray:
        return np.diff(self.bounds)

    def majority(self, k: int = 0) -> np.ndarray:
        """A 64-bit fingerprint of each set: the bits that are set in over half of its hashes (mixed anew for ``k``)."""
        ones = np.zeros((len(self), 64), np.int64)
        for at in range(0, len(self.values), _ROWS):
            part, owner = self.values[at : at + _ROWS], self.owner[at : at + _ROWS]
            bits = np.unpackbits((mixed(part, 16 + k) if k else part).astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
            first = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
            ones[owner[first]] += np.add.reduceat(bits, first, axis=0, dtype=np.int32)
        return np.packbits(2 * ones > self.sizes[:, None], axis=1).view(">u8").ravel().astype(np.uint64)

    def sums(self, k: int) -> np.ndarray:
        """The sum of each set's hashes, mixed anew: equal for equal sets."""
        total = np.r_[np.uint64(0), np.cumsum(mixed(self.values, k))]
        return total[self.bounds[1:]] - total[self.bounds[:-1]]

    def parities(self, classes: int = 256) -> np.ndarray:
        """Bits of each set, as words: whether the hashes in each class (a power of two) are odd in number. Two sets differ in
        at least as many hashes as these words do in bits."""
        kind = (mixed(self.values, 9) >> np.uint64(65 - classes.bit_length())).astype(np.int64)
        words = [np.empty((0, classes // 64), np.int64)]
        for low in range(0, len(self), 128):
            high = min(low + 128, len(self))
            at = slice(self.bounds[low], self.bounds[high])
            odd = np.bincount((self.owner[at] - low) * classes + kind[at], minlength=classes * (high - low)).reshape(-1, classes) & 1
            words.append(np.packbits(odd.astype(np.uint8), axis=1).view(np.int64))
        return np.concatenate(words)


def shingle_sets(texts: list[bytes | None], shingle: int) -> Iterator[tuple[int, ShingleSets]]:
    """The sets of consecutive texts, with the place of the first, in portions of bounded bytes."""
    first, held, size = 0, [], 0
    for i, text in enumerate(texts):
        if held and size + len(text or b"") > _PIECE:
            yield first, ShingleSets(held, shingle)
            first, held, size = i, [], 0
        held.append(text or b"")
        size += len(text or b"") + 1
    if held:
        yield first, ShingleSets(held, shingle)
