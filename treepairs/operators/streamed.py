"""A set against a small one: the small side is sent to all tasks, the other passes through them once.

No row of the large side is shuffled or repeated. Nearly exact distances of all pairs come from arrays: nodes that many of
the sent objects touch as dense columns, the rest by a join on nodes; exact integers follow for pairs below the kth.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .coded import Coded, Numbers
from .dense import ANSWERS, Block, Spec, answer_table, exact_numbers

#: Nodes of all objects of the side that is sent.
SENT_NODES = 2_000_000
#: Rows of the passing side met at once, and rows of the sent side in one array step.
STEP_ROWS, CHUNK_ROWS = 512, 256
#: Slack of distances summed in single precision.
SLACK = 1e-4
#: Steps of the depth of a tree in which shares are counted, so that their sums fit 16 bits, and sent rows met at once then.
STEPS, SHORT_ROWS = 16_000, 64
#: Passing rows whose candidates are held before their exact distances are taken.
HELD_ROWS = 65_536


class Sent:
    """The sent side with its frequent nodes as columns and the others sorted by node."""

    def __init__(self, block: Block, spec: Spec) -> None:
        self.block, self.spec = block, spec
        codes, counts = np.unique(block.node, return_counts=True)
        self.columns = codes[counts * 32 >= len(block.id)]
        self.dense, self.deep, code, row, value = self.parts(block)
        order = np.argsort(code, kind="stable")
        self.code, self.row, self.value = code[order], row[order], value[order]

    def parts(self, b: Block) -> tuple[np.ndarray, ...]:
        """Dense columns, the rest of the distance to the root, and the entries of the other nodes."""
        share = b.c / b.n[b.row]
        at = np.searchsorted(self.columns, b.node)
        frequent = np.zeros(len(b.node), bool)
        if len(self.columns):
            frequent = self.columns[np.minimum(at, len(self.columns) - 1)] == b.node
        weight = b.w / self.spec.scale
        value = share * (weight if self.spec.measure == "emd" else np.sqrt(weight))
        dense = np.zeros((len(b.id), len(self.columns)), np.float32)
        dense[b.row[frequent], at[frequent]] = value[frequent]
        rest = ~frequent
        deep = b.s / (b.n * self.spec.scale)
        if self.spec.measure == "emd":  # not the sum of the rest: an object may lie below nodes that the tree at hand lacks
            deep = deep - np.bincount(b.row[frequent], value[frequent], len(b.id))
        return dense, deep.astype(np.float32), b.node[rest], b.row[rest], value[rest]

    def close(self, y: Block) -> np.ndarray:
        """Distances of all pairs up to SLACK."""
        dense, deep, code, row, value = self.parts(y)
        out = self.deep[:, None] + deep[None, :]
        if self.spec.measure == "avg":
            out -= 2 * (self.dense @ dense.T)
        else:
            columns = np.ascontiguousarray(dense.T)
            for lo in range(0, len(out), CHUNK_ROWS):
                part, mine = out[lo : lo + CHUNK_ROWS], self.dense[lo : lo + CHUNK_ROWS]
                gap = np.empty_like(part)
                for v in range(len(columns)):
                    np.subtract(mine[:, v, None], columns[v][None, :], out=gap)
                    np.abs(gap, out=gap)
                    part += gap
        first, last = np.searchsorted(self.code, code), np.searchsorted(self.code, code, "right")
        lengths = last - first
        where = np.arange(int(lengths.sum())) - np.repeat(np.cumsum(lengths) - lengths - first, lengths)
        theirs = np.repeat(value, lengths)
        both = np.minimum(self.value[where], theirs) if self.spec.measure == "emd" else self.value[where] * theirs
        np.subtract.at(out, (self.row[where], np.repeat(row, lengths)), (2 * both).astype(np.float32))
        return out


class Counted:
    """The sent side with shares in whole steps: shared sums of all pairs in 16 bits, distances up to ``slack``."""

    def __init__(self, sent: Sent, numbers: Numbers) -> None:
        self.sent, b = sent, sent.block
        self.step = max(float(numbers.depth.max()) / numbers.scale, 1e-12) / STEPS
        dense, self.root, self.code, self.row, self.value = self.parts(b)
        order = np.argsort(self.code, kind="stable")
        self.code, self.row, self.value = self.code[order], self.row[order], self.value[order]
        self.dense = dense
        rare = int(np.bincount(self.row, minlength=1).max()) if len(self.row) else 0
        self.slack = (dense.shape[1] + rare + 3) * self.step + SLACK

    def parts(self, b: Block) -> tuple[np.ndarray, ...]:
        """Shares of the frequent nodes in steps, distance to the root, and the entries of the other nodes."""
        dense, _, code, row, value = self.sent.parts(b)
        root = np.bincount(b.row, b.c / b.n[b.row] * b.w / self.sent.spec.scale, len(b.id))
        return np.rint(dense / self.step).astype(np.int16), root, code, row, value

    def near(self, y: Block, limit: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """i, j and about their distance, of all pairs that can be within the limits."""
        dense, root, code, row, value = self.parts(y)
        columns = np.ascontiguousarray(dense.T)
        shared = np.empty((len(self.root), len(y.id)), np.int16)
        far = np.rint(root / (2 * self.step)).astype(np.int16)
        for lo in range(0, len(shared), SHORT_ROWS):
            part, mine = shared[lo : lo + SHORT_ROWS], self.dense[lo : lo + SHORT_ROWS]
            part[:] = -far
            less = np.empty_like(part)
            for v in range(len(columns)):
                np.minimum(mine[:, v, None], columns[v][None, :], out=less)
                part += less
        first, last = np.searchsorted(self.code, code), np.searchsorted(self.code, code, "right")
        lengths = last - first
        where = np.arange(int(lengths.sum())) - np.repeat(np.cumsum(lengths) - lengths - first, lengths)
        both = np.rint(np.minimum(self.value[where], np.repeat(value, lengths)) / self.step).astype(np.int16)
        np.add.at(shared, (self.row[where], np.repeat(row, lengths)), both)
        if shared.shape[1] >= k and np.isinf(limit).any():
            kth = np.partition(shared, shared.shape[1] - k, axis=1)[:, shared.shape[1] - k]
            limit = np.minimum(limit, self.root - 2 * self.step * kth + self.slack)
        least = np.floor((self.root - self.slack - limit) / (2 * self.step)).clip(-32768, 32767).astype(np.int16)
        i, j = np.nonzero(shared >= least[:, None])
        return i, j, self.root[i] - 2 * self.step * shared[i, j]


def _nearest(spec: Spec, left_sent: bool, load: Callable[[], pa.Table], numbers) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The k best of each sent object: nearly exact distances tighten the limits, exact ones are taken of what is left after
    HELD_ROWS rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes, k, exact, total = numbers.value, spec.k or 1, 0, 0
        sent = counted = None
        best = tuple(np.empty(0, np.int64) for _ in range(5)) + (np.empty(0),)
        limit, held, rows = np.empty(0), [], 0
        group, value = np.empty(0, np.int64), np.empty(0)

        def settle() -> None:
            nonlocal best, exact, held, rows
            found = []
            for part, i, j, d in held:
                keep = d <= limit[i] + slack
                used, at = np.unique(j[keep], return_inverse=True)
                found.append((part.take(pa.array(used)), i[keep], at))
            held, rows = [], 0
            y = Block(pa.Table.from_batches([p for p, _, _ in found]).combine_chunks(), codes)
            shift = np.cumsum([0] + [p.num_rows for p, _, _ in found])
            i, j = np.concatenate([f[1] for f in found]), np.concatenate([f[2] + s for f, s in zip(found, shift, strict=False)])
            num, den = exact_numbers(sent.block, y, i, j, spec, len(codes))
            exact += len(i)
            a, b = (sent.block.id[i], y.id[j]) if left_sent else (y.id[j], sent.block.id[i])
            best = tuple(np.concatenate(p) for p in zip(best, (i, a, b, num, den, num / den), strict=True))
            order = np.lexsort((best[2], best[1], best[5], best[0]))
            best = tuple(f[order] for f in best)
            keep = np.arange(len(order)) - np.searchsorted(best[0], best[0]) < k
            best = tuple(f[keep] for f in best)

        for batch in batches:
            for lo in range(0, batch.num_rows, STEP_ROWS):
                if sent is None:
                    sent = Sent(Block(load(), codes), spec)
                    counted = Counted(sent, codes) if spec.measure == "emd" else None
                    slack = counted.slack if counted else SLACK
                    limit = np.full(len(sent.block.id), np.inf)
                part = batch.slice(lo, STEP_ROWS)
                y = Block(pa.Table.from_batches([part]), codes)
                total += len(limit) * len(y.id)
                if counted:
                    i, j, d = counted.near(y, limit, k)
                else:
                    near = sent.close(y)
                    if near.shape[1] >= k and np.isinf(limit).any():
                        limit = np.minimum(limit, np.partition(near, k - 1, axis=1)[:, k - 1] + slack)
                    i, j = np.nonzero(near <= (limit + slack).astype(np.float32)[:, None])
                    d = near[i, j].astype(float)
                rows += len(y.id)
                if len(i):
                    held.append((part, i, j, d))
                    group, value = np.concatenate([group, i]), np.concatenate([value, d])
                    order = np.lexsort((value, group))
                    group, value = group[order], value[order]
                    keep = np.arange(len(group)) - np.searchsorted(group, group) < k
                    group, value = group[keep], value[keep]
                    first, counts = np.unique(group, return_index=True, return_counts=True)[1:]
                    full = first[counts == k]
                    limit[group[full]] = np.minimum(limit[group[full]], value[full + k - 1] + slack)
                if rows >= HELD_ROWS and held:
                    settle()
        if held:
            settle()
        yield from answer_table(best[1:], total, exact).to_batches()

    return run


def _passed(spec: Spec, left_sent: bool, load: Callable[[], pa.Table], numbers=None) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes = {} if numbers is None else numbers.value
        sent, k, exact, total = None, spec.k or 1, 0, 0
        best = tuple(np.empty(0, np.int64) for _ in range(5)) + (np.empty(0),)
        limit = np.empty(0)
        for batch in batches:
            for lo in range(0, batch.num_rows, STEP_ROWS):
                if sent is None:
                    sent = Sent(Block(load(), codes), spec)
                    limit = np.full(len(sent.block.id) if spec.per_left else 1, np.inf)
                x, y = sent.block, Block(pa.Table.from_batches([batch.slice(lo, STEP_ROWS)]), codes)
                near = sent.close(y)
                total += near.size
                if spec.per_left and near.shape[1] >= k and np.isinf(limit).any():
                    limit = np.minimum(limit, np.partition(near, k - 1, axis=1)[:, k - 1] + SLACK)
                elif not spec.per_left and near.size >= k and np.isinf(limit[0]):
                    limit[0] = np.partition(near.ravel(), k - 1)[k - 1] + SLACK
                i, j = np.nonzero(near <= (limit[:, None] + SLACK))
                if not len(i):
                    continue
                num, den = exact_numbers(x, y, i, j, spec, len(codes))
                exact += len(i)
                a, b = (x.id[i], y.id[j]) if left_sent else (y.id[j], x.id[i])
                group = i if spec.per_left else np.zeros(len(i), np.int64)
                best = tuple(np.concatenate(p) for p in zip(best, (group, a, b, num, den, num / den), strict=True))
                order = np.lexsort((best[2], best[1], best[5], best[0]))
                best = tuple(f[order] for f in best)
                keep = np.arange(len(order)) - np.searchsorted(best[0], best[0]) < k
                best = tuple(f[keep] for f in best)
                groups, starts, counts = np.unique(best[0], return_index=True, return_counts=True)
                full = counts == k
                limit[groups[full]] = np.minimum(limit[groups[full]], best[5][starts[full] + k - 1])
        yield from answer_table(best[1:], total, exact).to_batches()

    return run


def streamed(small: DataFrame, large: DataFrame, spec: Spec, left_sent: bool, coded: Coded | None = None) -> DataFrame:
    """Rows of ANSWERS: the k best of each task, or of each sent object and task; both sides as packed rows, or as rows of a
    numbered tree."""
    spark = small.sparkSession
    plain = lambda rows: rows.select("obj_id", "terms") if coded else rows.drop("share", "self")
    table = plain(small).toArrow()
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, table.schema) as writer:
        writer.write_table(table)
    sent = spark.sparkContext.broadcast(sink.getvalue().to_pybytes())
    run = _nearest if coded and spec.per_left else _passed
    return plain(large).mapInArrow(run(spec, left_sent, lambda: pa.ipc.open_stream(sent.value).read_all(), coded.numbers if coded else None), ANSWERS)
