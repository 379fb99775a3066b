"""Token-id matrices by best-fit-decreasing packing.

Documents are encoded, closed by an end id and split losslessly into pieces of
at most a window. Each task packs its pieces in rounds of about ``ROUND`` ids:
longest first, each into the row with the least room that still takes it. A
segment tree over free capacities finds that row in logarithmic time. Rows are
written as padded little-endian uint16 ids with the cumulative segment lengths,
and positions, as wide as the ids, that restart at each segment.

No shuffle; a round bounds a task's memory. Null text counts as empty (one end
id); null doc_id stays null; repeated rows are packed each.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_slices
from .token_codec import codec, default_vocabulary

WINDOW, END, PAD, ROUND = 4096, 2, 0, 2_000_000
SCHEMA = "sequence_id long, n_tokens long, n_segments long, doc_ids array<long>, starts array<long>, cu_seqlens array<int>, input_ids binary, ids_crc32 long, positions binary"


class CapacityTree:
    """How many rows have each free capacity, in a segment tree over capacities 0..size."""

    def __init__(self, size: int):
        self.leaves = 1 << size.bit_length()
        self.sums = [0] * (2 * self.leaves)

    def add(self, capacity: int, n: int) -> None:
        at = self.leaves + capacity
        while at:
            self.sums[at] += n
            at >>= 1

    def least(self, capacity: int) -> int:
        """The least capacity of a row that is at least ``capacity``; -1 if none."""
        at = self.leaves + capacity
        if self.sums[at]:
            return capacity
        while at > 1:
            if not at & 1 and self.sums[at + 1]:
                at += 1
                while at < self.leaves:
                    at = 2 * at if self.sums[2 * at] else 2 * at + 1
                return at - self.leaves
            at >>= 1
        return -1


def best_fit_decreasing(sizes: list[int], window: int) -> list[list[int]]:
    """Rows of indices into ``sizes`` (each 1..window), longest placed first, ties by index."""
    tree, free, rows = CapacityTree(window), {}, []
    for i in sorted(range(len(sizes)), key=lambda i: (-sizes[i], i)):
        room = tree.least(sizes[i])
        if room < 0:
            room, row = window, len(rows)
            rows.append([])
        else:
            row = free[room].pop()
            tree.add(room, -1)
        rows[row].append(i)
        left = room - sizes[i]
        if left:
            free.setdefault(left, []).append(row)
            tree.add(left, 1)
    return rows


def position_ids(cu_seqlens: list[int]) -> np.ndarray:
    """Positions of a row's ids, restarting at each segment."""
    cu = np.asarray(cu_seqlens)
    return np.arange(cu[-1]) - np.repeat(cu[:-1], np.diff(cu))


def pack_matrices(docs: DataFrame, vocabulary: str | None = None, window: int = WINDOW, end: int = END, pad: int = PAD) -> DataFrame:
    """One row per packed sequence, SCHEMA: its documents, where in them each segment starts, cumulative lengths, padded ids, their CRC-32 and padded positions."""
    path = vocabulary or default_vocabulary()

    def run(batches):
        words, number = codec(path), (TaskContext.get().partitionId() if TaskContext.get() else 0) << 36
        pieces: list[tuple] = []
        held = 0

        def rows():
            nonlocal number
            out = []
            for row in best_fit_decreasing([len(p[2]) for p in pieces], window):
                parts = [pieces[i] for i in row]
                cu = [0, *np.cumsum([len(p[2]) for p in parts]).tolist()]
                ids = np.full(window, pad, dtype="<u2")
                ids[: cu[-1]] = np.concatenate([p[2] for p in parts])
                raw = ids.tobytes()
                at = np.zeros(window, dtype="<u2" if window <= 1 << 16 else "<u4")
                at[: cu[-1]] = position_ids(cu)
                out.append((number, cu[-1], len(parts), [p[0] for p in parts], [p[1] for p in parts], cu, raw, zlib.crc32(raw), at.tobytes()))
                number += 1
            pieces.clear()
            types = [pa.int64()] * 3 + [pa.list_(pa.int64())] * 2 + [pa.list_(pa.int32()), pa.binary(), pa.int64(), pa.binary()]
            names = [f.split()[0] for f in SCHEMA.split(", ")]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], names)

        for got in batches:
            for lo, n in byte_slices(got.column(1), 4 << 20):
                part = got.slice(lo, n)
                for doc, ids in zip(part.column(0).to_pylist(), words.encode(part.column(1))):
                    ids = np.append(ids, np.uint16(end))
                    for at in range(0, len(ids), window):
                        pieces.append((doc, at, ids[at : at + window]))
                    held += len(ids)
                if held >= ROUND:
                    yield rows()
                    held = 0
        if pieces:
            yield rows()

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, SCHEMA)


def write_matrices(docs: DataFrame, path: str, **options) -> None:
    """Write the packed rows as Parquet; a row group holds whole matrices of ids."""
    pack_matrices(docs, **options).write.mode("overwrite").parquet(path)
