"""Process grid, loop and storage settings, and the packing of points into blocks."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class GridSpec:
    """g x g workers over n points; fine blocks 0..g*g-1 of equal length (the last ones ragged or empty), g of them to a grid row."""

    n: int
    g: int = 2

    def __post_init__(self):
        if self.n < 1 or self.g < 1:
            raise ValueError("a grid needs at least one point and one worker")

    @classmethod
    def of_workers(cls, n: int, workers: int) -> GridSpec:
        g = round(workers**0.5)
        if g * g != workers:
            raise ValueError(f"{workers} workers make no square grid")
        return cls(n, g)

    @property
    def p(self) -> int:
        return self.g * self.g

    @property
    def step(self) -> int:
        return -(-self.n // self.p)

    def bounds(self, fine: int) -> tuple[int, int]:
        return min(self.n, fine * self.step), min(self.n, (fine + 1) * self.step)

    def wide(self, row: int) -> tuple[int, int]:
        """First and end point of a grid row (or column)."""
        return self.bounds(row * self.g)[0], self.bounds(row * self.g + self.g - 1)[1]

    def block_of(self, idx: int) -> int:
        return idx // self.step

    def row_blocks(self, i: int) -> list[int]:
        return list(range(i * self.g, (i + 1) * self.g))

    def rank(self, i: int, j: int) -> int:
        """Column-major: the workers of one grid column are neighbours."""
        return j * self.g + i

    def owner(self, j: int, piece: int) -> int:
        """The worker that sums piece ``piece`` of grid column j; it owns the fine block of that number."""
        return piece + j * self.g


@dataclass(frozen=True)
class LoopSpec:
    """max_iter: most sweeps, or None to go on until the labels settle."""

    max_iter: int | None = 100
    fixed: bool = False
    tol: float | None = None
    empty: str = "skip"
    copy_v: str = "broadcast"
    split: str = "points"
    v: str = "dense"
    checkpoint: str | None = None
    checkpoint_every: int = 10
    resume: bool = False
    barrier: bool = False

    def __post_init__(self):
        for value, allowed in ((self.empty, ("skip", "origin", "reseed", "error")), (self.copy_v, ("broadcast", "row_join", "diagonal")), (self.split, ("points", "clusters")), (self.v, ("dense", "sparse"))):
            if value not in allowed:
                raise ValueError(f"{value!r} is none of {allowed}")
        if self.max_iter is None and self.fixed:
            raise ValueError("a fixed number of sweeps needs max_iter")


@dataclass(frozen=True)
class StoreSpec:
    """dtype: f64, f32 or f32acc64 (stored as f32, summed as f64); symmetric: build tiles bi <= bj only and use each twice.

    K of over ``keep_bytes`` is not kept: the points stay on the workers in its place.
    """

    dtype: str = "f64"
    symmetric: bool = False
    max_bytes: int = 1 << 40
    keep_bytes: int = 1 << 29

    def __post_init__(self):
        if self.dtype not in ("f64", "f32", "f32acc64"):
            raise ValueError(f"no such dtype: {self.dtype}")

    @property
    def stored(self) -> str:
        return "<f8" if self.dtype == "f64" else "<f4"

    @property
    def summed(self) -> str:
        return "<f4" if self.dtype == "f32" else "<f8"

    def keeps(self, n: int) -> bool:
        """Whether K of n points is kept."""
        return n * n * np.dtype(self.stored).itemsize <= self.keep_bytes


BLOCK = "blk int, lo long, cnt int, dim int, data binary"


def matrix(raw: bytes, rows: int, dtype: str = "<f8") -> np.ndarray:
    return np.frombuffer(raw, dtype=dtype).reshape(rows, -1)


def packed(x: np.ndarray) -> bytes:
    """A block of points as row-major float64, or, where that takes less than half, as its values other than zero, compressed, after a mark that no finite value has."""
    rows, cols = np.nonzero(x)
    if 2 * (16 + 8 * len(x) + 12 * len(rows)) >= 8 * x.size:
        return x.astype("<f8").tobytes()
    parts = np.bincount(rows, minlength=len(x)).astype("<i8"), x[rows, cols].astype("<f8"), cols.astype(_place(x.shape[1]))
    return np.array([-1, x.shape[1], len(rows)], "<i8").tobytes() + pa.compress(b"".join(a.tobytes() for a in parts), "zstd", asbytes=True)


def _place(dim: int) -> np.dtype:
    return np.dtype("<u2" if dim <= 1 << 16 else "<i4")


def unpacked(raw: bytes, rows: int) -> np.ndarray:
    flat = np.frombuffer(raw, np.uint8)
    if flat.size < 16 or flat[:8].min() < 255:
        return matrix(raw, rows)
    dim, n = (int(v) for v in flat[8:24].view("<i8"))
    place, at, end = _place(dim), 8 * rows, 8 * rows + 8 * n
    flat = np.frombuffer(pa.decompress(pa.py_buffer(flat[24:]), end + place.itemsize * n, "zstd"), np.uint8)
    x = np.zeros((rows, dim))
    x[np.repeat(np.arange(rows), flat[:at].view("<i8")), flat[end:].view(place)] = flat[at:end].view("<f8")
    return x


def to_blocks(points: DataFrame, step: int, most: int | None = None) -> DataFrame:
    """BLOCK rows of ``step`` points each, in order of idx: row-major float64 bytes. With ``most`` a block is several rows of so many points, as ``packed`` has them."""
    if most:
        return _packed_blocks(points, step, most)
    cut = points.select(F.floor(F.col("idx") / step).cast("int").alias("blk"), F.struct(F.col("idx").cast("long").alias("idx"), "x").alias("p"))
    blocks = cut.groupBy("blk").agg(F.array_sort(F.collect_list("p")).alias("p"))

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                rows = batch.column(1)[i].values
                idx = rows.field("idx").to_numpy(zero_copy_only=False)
                x = rows.field("x").flatten().to_numpy(zero_copy_only=False)
                dim = len(x) // len(idx)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(i, 1), pa.array([int(idx[0])], pa.int64()), pa.array([len(idx)], pa.int32()), pa.array([dim], pa.int32()), pa.array([x.astype("<f8").tobytes()], pa.binary())],
                    ["blk", "lo", "cnt", "dim", "data"],
                )

    return blocks.mapInArrow(run, BLOCK)


def _packed_blocks(points: DataFrame, step: int, most: int) -> DataFrame:
    """Points are packed where they are read, the neighbours of a batch together, and put in order where their block meets."""

    def cut(batches):
        for batch in batches:
            idx = batch.column(0).to_numpy()
            if not len(idx):
                continue
            x = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(len(idx), -1)
            part = idx // step * (step // most + 1) + idx % step // most
            order = np.argsort(part, kind="stable")
            for at in np.split(order, np.flatnonzero(np.diff(part[order])) + 1):
                yield pa.RecordBatch.from_arrays([pa.array([idx[at[0]] // step], pa.int32()), pa.array([idx[at[0]] % step // most], pa.int32()), pa.array([idx[at].astype("<i8").tobytes()], pa.binary()), pa.array([packed(x[at])], pa.binary())], ["blk", "part", "idx", "data"])

    def meet(batches):
        for batch in batches:
            for blk, pieces in zip(batch.column(0), batch.column(1)):
                idx = [np.frombuffer(p["idx"].as_buffer(), "<i8") for p in pieces]
                x = np.concatenate([unpacked(p["data"].as_buffer(), len(i)) for i, p in zip(idx, pieces)])
                idx = np.concatenate(idx)
                x = x[np.argsort(idx)]
                yield pa.RecordBatch.from_arrays([pa.array([blk.as_py()], pa.int32()), pa.array([int(idx.min())], pa.int64()), pa.array([len(x)], pa.int32()), pa.array([x.shape[1]], pa.int32()), pa.array([packed(x)], pa.binary())], ["blk", "lo", "cnt", "dim", "data"])

    pieces = points.select(F.col("idx").cast("long").alias("idx"), F.col("x").cast("array<double>").alias("x")).mapInArrow(cut, "blk int, part int, idx binary, data binary")
    return pieces.groupBy("blk", "part").agg(F.collect_list(F.struct("idx", "data")).alias("p")).select("blk", "p").mapInArrow(meet, BLOCK)


def from_blocks(blocks: DataFrame) -> DataFrame:
    """(idx, x) of every point."""

    def run(batches):
        for batch in batches:
            for r in batch.to_pylist():
                x = matrix(r["data"], r["cnt"])
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(r["lo"], r["lo"] + r["cnt"])), pa.array(list(x), pa.list_(pa.float64()))], ["idx", "x"])

    return blocks.mapInArrow(run, "idx long, x array<double>")
