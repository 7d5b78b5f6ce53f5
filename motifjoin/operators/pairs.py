"""Large binary relations of longs on the move: sorted, without repeats, and as differences of few bytes.

A task sorts its pairs, drops repeats and sends each part its pairs as one blob per buffer:
the smallest pair and the steps from one pair to the next, byte by byte of equal weight, so
that bytes that are zero or alike lie together and the shuffle's own compression takes them.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Pairs that a task holds before it sends them.
BUFFER = 1 << 22
BLOBS = "b int, blob binary"
_ODD = np.uint64(0x9E3779B97F4A7C15)


def class_of(values: np.ndarray, share: int) -> np.ndarray:
    x = values.view(np.uint64) * _ODD
    x = (x ^ (x >> np.uint64(32))) * _ODD
    return ((x >> np.uint64(33)) % np.uint64(share)).astype(np.int64)


def distinct(k: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The pairs in order, each once."""
    if not len(k):
        return k, x
    low, base, span = int(k.min()), int(x.min()), int(x.max()) - int(x.min()) + 1
    if (int(k.max()) - low + 1) * span < 1 << 63:
        code = np.sort((k - low) * span + (x - base))
        code = code[np.append(True, code[1:] != code[:-1])]
        k, x = np.divmod(code, span)
        return k + low, x + base
    order = np.lexsort((x, k))
    k, x = k[order], x[order]
    keep = np.append(True, (k[1:] != k[:-1]) | (x[1:] != x[:-1]))
    return k[keep], x[keep]


def encode(k: np.ndarray, x: np.ndarray) -> bytes:
    """Pairs in order as a blob."""
    low, base, span = int(k[0]), int(x.min()), int(x.max()) - int(x.min()) + 1
    if (int(k[-1]) - low + 1) * span >= 1 << 63:
        return np.array([len(k), 0, 0, 0, 0, 0], np.int64).tobytes() + k.tobytes() + x.tobytes()
    code = (k - low) * span + (x - base)
    step = np.diff(code)
    width = max(1, (int(step.max(initial=0)).bit_length() + 7) // 8)
    return np.array([len(k), low, base, span, code[0], width], np.int64).tobytes() + step.view(np.uint8).reshape(-1, 8)[:, :width].T.tobytes()


def decode(blob: bytes) -> tuple[np.ndarray, np.ndarray]:
    n, low, base, span, first, width = np.frombuffer(blob, np.int64, 6).tolist()
    if not width:
        return np.frombuffer(blob, np.int64, n, 48), np.frombuffer(blob, np.int64, n, 48 + 8 * n)
    step = np.zeros((n - 1, 8), np.uint8)
    step[:, :width] = np.frombuffer(blob, np.uint8, (n - 1) * width, 48).reshape(width, n - 1).T
    k, x = np.divmod(np.cumsum(np.append(first, step.reshape(-1).view(np.int64))), span)
    return k + low, x + base


def by_class(parts: int) -> Callable[[np.ndarray], np.ndarray]:
    return partial(class_of, share=parts)


def by_bounds(bounds: list[int]) -> Callable[[np.ndarray], np.ndarray]:
    """Numbers of ranges with these upper bounds, the last one open."""
    return partial(np.searchsorted, np.array(bounds, np.int64))


def blobs(pairs: Iterator[tuple[np.ndarray, np.ndarray]], part_of: Callable[[np.ndarray], np.ndarray]) -> Iterator[pa.RecordBatch]:
    """Pairs as ``(b, blob)`` by the part of their first value; a buffer at a time."""

    def flush() -> Iterator[pa.RecordBatch]:
        k, x = distinct(*(np.concatenate(c) for c in zip(*held)))
        part = part_of(k)
        order = np.argsort(part, kind="stable")
        part = part[order]
        cuts = np.flatnonzero(np.append(True, part[1:] != part[:-1])).tolist()
        for lo, hi in zip(cuts, [*cuts[1:], len(part)]):
            mine = order[lo:hi]
            yield pa.RecordBatch.from_arrays([pa.array([int(part[lo])], pa.int32()), pa.array([encode(k[mine], x[mine])], pa.binary())], ["b", "blob"])

    held, rows = [], 0
    for k, x in pairs:
        for at in range(0, len(k), BUFFER):
            held.append((k[at : at + BUFFER], x[at : at + BUFFER]))
            rows += len(held[-1][0])
            if rows >= BUFFER:
                yield from flush()
                held, rows = [], 0
    if rows:
        yield from flush()


def of_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Two columns of longs without nulls as pairs, some 100,000 at a time."""
    held, rows = [], 0
    for b in batches:
        held.append((b.column(0).to_numpy(), b.column(1).to_numpy()))
        rows += b.num_rows
        if rows >= 100_000:
            yield tuple(np.concatenate(c) for c in zip(*held))
            held, rows = [], 0
    if rows:
        yield tuple(np.concatenate(c) for c in zip(*held))


def parts_of(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """``(b, k, x)``: the pairs of each part of a partition that holds whole parts, in order, each once."""
    held: dict[int, list] = {}
    for batch in batches:
        for b, blob in zip(batch.column(0).to_pylist(), batch.column(1)):
            held.setdefault(b, []).append(blob.as_buffer())
    for b in sorted(held):
        yield b, *distinct(*(np.concatenate(c) for c in zip(*map(decode, held.pop(b)))))


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for _, k, x in parts_of(batches):
        for at in range(0, len(k), 1 << 16):
            yield pa.RecordBatch.from_arrays([pa.array(k[at : at + (1 << 16)]), pa.array(x[at : at + (1 << 16)])], ["k", "x"])


def distinct_pairs(sent: DataFrame, parts: int) -> DataFrame:
    """Blobs ``(b, blob)`` of ``parts`` parts as rows ``(k, x)``, each once."""
    return sent.repartitionById(parts, F.col("b")).mapInArrow(_rows, "k long, x long")


def pairs_within(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All pairs of an earlier and a later value of one list, over a column of lists."""
    for batch in batches:
        lists = batch.column(0)
        flat, ends = lists.flatten().to_numpy(), lists.offsets.to_numpy()
        ends = ends - ends[0]
        left = np.repeat(ends[1:], np.diff(ends)) - np.arange(len(flat)) - 1
        at = np.arange(len(flat))
        step = 1
        while len(at := at[left[at] >= step]):
            yield flat[at], flat[at + step]
            step += 1


def _tagged(batches: Iterator[pa.RecordBatch], tag: int, parts: int) -> Iterator[pa.RecordBatch]:
    return blobs(of_batches(batches), lambda k: class_of(k, parts) * 3 + tag)


def _states(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held: dict[int, list] = {}
    for b, k, x in parts_of(batches):
        held.setdefault(b // 3, []).append((k, x, np.full(len(k), b % 3)))
    for b in sorted(held):
        k, x, tag = (np.concatenate(c) for c in zip(*held.pop(b)))
        order = np.lexsort((tag, x, k))
        k, x, tag = k[order], x[order], tag[order]
        again = np.append(False, (k[1:] == k[:-1]) & (x[1:] == x[:-1]))  # a change of an old row follows it
        state = np.where(tag == 1, 1, -(np.append(again[1:], False) & (np.append(tag[1:], 0) == 2)).astype(np.int32)).astype(np.int32)
        keep = np.flatnonzero((tag == 0) | (tag == 1) & ~again)
        for at in range(0, len(keep), 1 << 16):
            some = keep[at : at + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(k[some]), pa.array(x[some]), pa.array(state[some])], ["c0", "c1", "s"])


def states(old: DataFrame, net: DataFrame, parts: int) -> DataFrame:
    """Pairs ``(c0, c1, s)`` of an old relation and net changes (with ``w``): kept (0), deleted (-1) or inserted (1).

    Inserting what is there and deleting what is not change nothing.
    """
    sides = (old, net.filter("w > 0").drop("w"), net.filter("w < 0").drop("w"))
    sent = [df.mapInArrow(partial(_tagged, tag=i, parts=parts), BLOBS) for i, df in enumerate(sides)]
    return sent[0].union(sent[1]).union(sent[2]).repartitionById(parts, F.expr("b div 3").cast("int")).mapInArrow(_states, "c0 long, c1 long, s int")
