"""Repeated spans: windows of a fixed number of symbols that also start earlier.

Windows are not moved one by one. A window is anchored at the smallest, by hash, of its runs of ``gram`` symbols
(leftmost on ties). Equal windows have the same anchor run at the same offset, so neighbouring windows with one anchor
travel as one record: the hash of the anchor run, the hash of the stretch that the windows cover, and where it starts.
Records are dealt by anchor run to buckets; in a bucket

* equal stretches under one anchor run are copies: all but the earliest are removed as a whole;
* an anchor run with one distinct stretch is settled by that;
* where several distinct stretches share an anchor run, their windows may be equal in part. The earliest copy of each
  stretch is marked open, and the caller compares its windows by content.

Symbols are hashed by position in a power series modulo 2**64, with two bases, so that any stretch has its hash by one
subtraction. Records are packed by bucket into binary blobs, which the shuffle compresses and moves as few rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

_BASES = (0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93)
#: Symbols that are hashed at once; a longer document is cut into overlapping parts.
AT_ONCE = 1 << 20
RECORD = np.dtype([("gram", "<u8"), ("stretch", "<u8"), ("doc", "<i8"), ("start", "<u4"), ("n", "<u2")])
RUN = np.dtype([("doc", "<i8"), ("start", "<u4"), ("end", "<u4")])
OPEN = np.dtype([("doc", "<i8"), ("start", "<u4"), ("n", "<u2"), ("gram", "<u8")])


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Powers:
    """Powers of the bases and of their inverses modulo 2**64, as far as asked for."""

    def __init__(self) -> None:
        self.up = [np.ones(1, np.uint64) for _ in _BASES]
        self.down = [np.ones(1, np.uint64) for _ in _BASES]

    def to(self, n: int) -> None:
        for k, base in enumerate(_BASES):
            for rows, b in ((self.up, base), (self.down, pow(base, -1, 1 << 64))):
                while len(rows[k]) < n:
                    rows[k] = np.concatenate([rows[k], rows[k] * np.uint64(pow(b, len(rows[k]), 1 << 64))])


def sliding_first_min(x: np.ndarray, width: int) -> np.ndarray:
    """Position of the leftmost minimum of every ``width`` values; by the high 43 bits, with the position below them."""
    key = (x & ~np.uint64((1 << 21) - 1)) | np.arange(len(x), dtype=np.uint64)
    n, done = len(x) - width + 1, 1
    while 2 * done <= width:
        key = np.minimum(key[: len(key) - done], key[done:])
        done *= 2
    key = np.minimum(key[:n], key[width - done : width - done + n])
    return (key & np.uint64((1 << 21) - 1)).astype(np.int64)


def records(symbols: np.ndarray, lengths: np.ndarray, ids: np.ndarray, offsets: np.ndarray, window: int, gram: int, powers: Powers, leading: bool = False) -> np.ndarray:
    """The records of consecutive documents whose symbols are concatenated; ``offsets``: where each begins in its text."""
    n = len(symbols)
    if n < window:
        return np.empty(0, RECORD)
    powers.to(n + 1)
    sums = []
    for k in range(2):
        s = np.zeros(n + 1, np.uint64)
        np.cumsum(symbols * powers.up[k][:n], out=s[1:])
        sums.append(s)
    grams = mixed((sums[0][gram:] - sums[0][:-gram]) * powers.down[0][: n - gram + 1])
    anchor = sliding_first_min(grams, window - gram + 1)
    ends = np.cumsum(lengths)
    doc = np.repeat(np.arange(len(lengths)), lengths)[: n - window + 1]
    at = np.arange(n - window + 1)
    inside = at + window <= ends[doc]
    # Runs of windows of one document with one anchor.
    new = np.r_[True, (anchor[1:] != anchor[:-1]) | (doc[1:] != doc[:-1])] & inside
    start = np.flatnonzero(new)
    if not len(start):
        return np.empty(0, RECORD)
    last = np.flatnonzero(inside & np.r_[new[1:] | ~inside[1:], True])
    out = np.empty(len(start), RECORD)
    stop = last + window
    first = anchor[start]
    out["gram"] = grams[first]
    if leading:  # order by the first three bytes, which are the low bits of the symbols
        low = symbols & np.uint64(255)
        lead = low[first] << np.uint64(56) | low[first + 1] << np.uint64(48) | low[first + 2] << np.uint64(40)
        out["gram"] = lead | out["gram"] >> np.uint64(24)
    out["stretch"] = mixed((sums[1][stop] - sums[1][start]) * powers.down[1][start] + (stop - start).astype(np.uint64))
    d = doc[start]
    out["doc"] = ids[d]
    out["start"] = start - (ends[d] - lengths[d]) + offsets[d]
    out["n"] = last - start + 1
    return out


def pieces(ids: list, symbol_arrays: Iterator[np.ndarray], window: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Groups of whole documents, or overlapping parts of long ones, of at most AT_ONCE symbols."""
    group: list[tuple[int, int, np.ndarray]] = []
    size = 0

    def packed():
        return np.concatenate([g[2] for g in group]), np.array([len(g[2]) for g in group]), np.array([g[0] for g in group], np.int64), np.array([g[1] for g in group], np.int64)

    for doc_id, symbols in zip(ids, symbol_arrays, strict=True):
        step = AT_ONCE - window
        for at in range(0, max(1, len(symbols) - window + 1), step):
            part = symbols[at : at + step + window - 1]
            if group and size + len(part) > AT_ONCE:
                yield packed()
                group, size = [], 0
            if len(part) >= window:
                group.append((doc_id, at, part))
                size += len(part)
    if group:
        yield packed()


def settle_copies(r: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(records that have an earlier copy, earliest copies in order of gram)."""
    order = np.lexsort((r["start"], r["doc"], r["n"], r["stretch"], r["gram"]))
    r = r[order]
    same = np.r_[False, (r["gram"][1:] == r["gram"][:-1]) & (r["stretch"][1:] == r["stretch"][:-1]) & (r["n"][1:] == r["n"][:-1])]
    first = np.maximum.accumulate(np.where(same, 0, np.arange(len(r))))
    # Rows that repeat an id hold the same place, which is not an earlier one.
    later = same & ((r["doc"] != r["doc"][first]) | (r["start"] != r["start"][first]))
    return r[later], r[~same]


def settle(r: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """(removed runs, open stretches) of a bucket."""
    later, firsts = settle_copies(r)
    g = firsts["gram"]
    alike = np.r_[g[1:] == g[:-1], False] | np.r_[False, g[1:] == g[:-1]]
    firsts = firsts[alike]
    open_ = np.empty(len(firsts), OPEN)
    for name in OPEN.names:
        open_[name] = firsts[name]
    return as_runs(later, window), open_


def as_runs(r: np.ndarray, window: int) -> np.ndarray:
    out = np.empty(len(r), RUN)
    out["doc"], out["start"] = r["doc"], r["start"]
    out["end"] = r["start"] + r["n"].astype(np.uint32) + np.uint32(window - 1)
    return out


def merged(runs: np.ndarray) -> np.ndarray:
    """Runs sorted by document, with those that touch or overlap made one."""
    if not len(runs):
        return runs
    runs = runs[np.lexsort((runs["start"], runs["doc"]))]
    doc = np.r_[0, np.cumsum(runs["doc"][1:] != runs["doc"][:-1])].astype(np.int64) << 33
    reach = np.maximum.accumulate(runs["end"].astype(np.int64) + doc)
    new = np.r_[True, runs["start"][1:].astype(np.int64) + doc[1:] > reach[:-1]]
    first = np.flatnonzero(new)
    out = np.empty(len(first), RUN)
    out["doc"], out["start"] = runs["doc"][first], runs["start"][first]
    out["end"] = (reach - doc)[np.r_[first[1:] - 1, len(runs) - 1]]
    return out
