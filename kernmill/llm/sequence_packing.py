"""Online packing of documents into fixed windows by the sum-of-squares rule.

A level array counts the partially filled windows at each fill. A document goes
to the fill whose move keeps the sum of the squared counts smallest, opening a
window counting as fill 0. Documents longer than a window give off whole windows
first. Windows left open at the end of a task, or beyond ``OPEN`` of them, are
cut and joined again into full ones; the rest of a task splits into windows of
powers of two, which need no padding.

No shuffle: each input split packs its own documents, in order, so a lost task
gives the same rows again. Null text counts as empty (one closing id); null
doc_id stays null; repeated rows are packed each.
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

WINDOW, END, OPEN, NONE = 4096, 2, 2048, 1 << 30
FIELDS = [("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64()), ("sequence_id", pa.int64()), ("offset", pa.int64()), ("ids", pa.binary())]
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, ids binary"


class Levels:
    """Windows of ``size`` by fill; a window is a list of pieces (doc, start, ids, doc_tokens)."""

    def __init__(self, size: int):
        self.size = size
        self.count = np.zeros(size + 1, dtype=np.int32)
        #: What a level gives up with a window: its count below zero, or a lot where it has none.
        self.taken = np.full(size + 1, NONE, dtype=np.int32)
        self.change = np.empty(size + 1, dtype=np.int32)
        self.windows: list[list[list]] = [[] for _ in range(size + 1)]
        self.open = 0

    def _step(self, fill: int, by: int) -> None:
        self.count[fill] += by
        self.taken[fill] = -self.count[fill] or NONE
        self.open += by

    def place(self, piece: tuple) -> list | None:
        """Put a piece of at most ``size`` ids; the window if that fills it.

        Half the change of the sum of squares, less one, is the count at the new fill less that at the old one;
        a new window takes nothing away, a filled one adds nothing. Ties go to the lowest fill.
        """
        n = len(piece[2])
        last = self.size - n
        best, fill = 2 * int(self.count[n]) + 1, 0
        if last > 1:
            change = np.add(self.count[n + 1 : self.size], self.taken[1:last], out=self.change[1:last])
            at = int(change.argmin())
            if 2 * int(change[at]) + 2 < best:
                best, fill = 2 * int(change[at]) + 2, at + 1
        if last and 2 * int(self.taken[last]) + 1 < best:
            fill = last
        if fill:
            window = self.windows[fill].pop()
            self._step(fill, -1)
        else:
            window = []
        window.append(piece)
        if fill + n == self.size:
            return window
        self.windows[fill + n].append(window)
        self._step(fill + n, 1)
        return None

    def drain(self) -> tuple[list[list], list]:
        """Full windows cut from all open ones, and the pieces that remain (fewer than ``size`` ids)."""
        full, held, room = [], [], self.size
        for fill in range(self.size - 1, 0, -1):
            for window in self.windows[fill]:
                for doc, start, ids, total in window:
                    while len(ids) >= room:
                        held.append((doc, start, ids[:room], total))
                        start, ids, room = start + room, ids[room:], self.size
                        full.append(held)
                        held = []
                    if len(ids):
                        held.append((doc, start, ids, total))
                        room -= len(ids)
            self.windows[fill] = []
        self.count[:] = 0
        self.taken[:] = NONE
        self.open = 0
        return full, held


def powers_of_two(pieces: list) -> list[list]:
    """Cut pieces into windows whose lengths are the powers of two in their total."""
    total = sum(len(p[2]) for p in pieces)
    out, queue = [], list(pieces)
    for bit in range(total.bit_length() - 1, -1, -1):
        room = total & (1 << bit)
        window = []
        while room:
            doc, start, ids, n = queue.pop(0)
            window.append((doc, start, ids[:room], n))
            if len(ids) > room:
                queue.insert(0, (doc, start + room, ids[room:], n))
            room -= min(room, len(ids))
        if window:
            out.append(window)
    return out


def pack(docs: DataFrame, vocabulary: str | None = None, window: int = WINDOW, end: int = END, with_ids: bool = True) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset and, if asked for, ids (little-endian uint32)."""
    path = vocabulary or default_vocabulary()

    def run(batches):
        words, levels = codec(path), Levels(window)
        number = [(TaskContext.get().partitionId() if TaskContext.get() else 0) << 36]
        rows: list[tuple] = []

        def close(pieces: list) -> None:
            at = 0
            for doc, start, ids, total in pieces:
                wide = ids.astype("<u4").tobytes()
                rows.append((doc, start, len(ids), zlib.crc32(wide), total, number[0], at, wide if with_ids else None))
                at += len(ids)
            number[0] += 1

        def batch() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(zip(*rows), FIELDS)], [n for n, _ in FIELDS])
            rows.clear()
            return out

        for got in batches:
            for lo, n in byte_slices(got.column(1), 1 << 20):
                part = got.slice(lo, n)
                for doc, ids in zip(part.column(0).to_pylist(), words.encode(part.column(1))):
                    ids = np.append(ids, np.uint16(end))
                    whole = len(ids) // window * window
                    for at in range(0, whole, window):
                        close([(doc, at, ids[at : at + window], len(ids))])
                    if whole < len(ids):
                        done = levels.place((doc, whole, ids[whole:], len(ids)))
                        if done:
                            close(done)
                    if levels.open > OPEN:
                        full, rest = levels.drain()
                        for w in full:
                            close(w)
                        for piece in rest:
                            done = levels.place(piece)
                            if done:
                                close(done)
                if len(rows) >= 512:
                    yield batch()
        full, rest = levels.drain()
        for w in full + powers_of_two(rest):
            close(w)
        if rows:
            yield batch()

    packed = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, SCHEMA)
    return packed if with_ids else packed.drop("ids")
