"""Pairwise kernel values: relational entries, grid tiles, column panels.

Blocks of points are sent to the worker that will hold their product; the
product is made there and never moves. A tile is kept as strips of its rows.
"""

from __future__ import annotations

from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.kernels import KernelSpec
from ..plans.layout import GridSpec, StoreSpec, matrix, unpacked

TILE = "bi int, bj int, rank int, lo_i long, lo_j long, rows int, cols int, data binary"
PLACED = "rank int, side int, blk int, lo long, cnt int, data binary"
RELATIONAL_LIMIT = 20_000
#: Points of a group whose pairs with another one task gives out, and rows it gives out at once.
ENTRY_SIDE, ENTRY_ROWS = 1024, 1 << 16
#: Rows of K go in strips of about this size, so that no single cell grows with the tile; smaller ones where K only passes.
STRIP_BYTES, PASSING_BYTES = 32 << 20, 4 << 20


def entries(points: DataFrame, kernel: KernelSpec, limit: int = RELATIONAL_LIMIT) -> DataFrame:
    """(i, j, v) of all pairs, v null where a vector is. The relational tier is the small reference; it refuses more than ``limit`` points.

    Groups of points meet in pairs, one task each, which makes their values as a block and gives them out as rows.
    """
    n = points.limit(limit + 1).count()
    if n > limit:
        raise ValueError(f"more than {limit} points: use a block engine, 8 * n * n bytes would be needed")
    g = max(2, -(-n // ENTRY_SIDE))
    group = F.pmod(F.col("idx"), F.lit(g)).cast("int")
    groups = points.select(group.alias("blk"), F.struct(F.col("idx").cast("long").alias("idx"), F.col("x").cast("array<double>").alias("x")).alias("p")).groupBy("blk").agg(F.collect_list("p").alias("p"))
    others = F.sequence(F.lit(0), F.lit(g - 1))
    as_row = F.transform(others, lambda j: F.struct((j * g + F.col("blk")).alias("rank"), F.lit(0).alias("side")))
    as_col = F.transform(others, lambda i: F.struct((F.col("blk") * g + i).alias("rank"), F.lit(1).alias("side")))
    at = by_rank(groups.select(F.inline(F.concat(as_row, as_col)), "p"), g * g)

    def run(batches):
        waiting: dict[int, tuple] = {}
        for batch in batches:
            for rank, side, p in zip(batch.column("rank").to_pylist(), batch.column("side").to_pylist(), batch.column("p")):
                other = waiting.pop(rank, None)
                if other is None:
                    waiting[rank] = (side, p)
                    continue
                yield from _entry_rows(*[_vectors(q) for q in ((p, other[1]) if other[0] else (other[1], p))], kernel)

    return at.mapInArrow(run, "i long, j long, v double")


def _vectors(group: pa.Scalar) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """idx, vectors, and whether a vector or one of its values is null; those are zeros here."""
    idx, x = group.values.field("idx").to_numpy(), group.values.field("x")
    lost = x.is_null().to_numpy(zero_copy_only=False)
    cells, sizes = x.flatten(), np.diff(x.offsets.to_numpy())[~lost]
    if len(sizes) and sizes.min() != sizes.max():
        raise ValueError(f"vectors of {sizes.min()} and of {sizes.max()} values")
    some = np.zeros((len(sizes), sizes[0] if len(sizes) else 0), bool)
    if cells.null_count:
        some = cells.is_null().to_numpy(zero_copy_only=False).reshape(some.shape)
        cells = cells.fill_null(0.0)
    out = np.zeros((len(idx), some.shape[1]))
    out[~lost] = cells.to_numpy(zero_copy_only=False).reshape(some.shape)
    lost[~lost] = some.any(axis=1)
    return idx, out, lost


def _entry_rows(rows: tuple, cols: tuple, kernel: KernelSpec):
    (i, x, lost_i), (j, y, lost_j) = rows, cols
    if x.shape[1] != y.shape[1] and not lost_i.all() and not lost_j.all():
        raise ValueError(f"vectors of {x.shape[1]} and of {y.shape[1]} values")
    dim = max(x.shape[1], y.shape[1])
    x, y = (np.zeros((len(a), dim)) if a.shape[1] < dim else a for a in (x, y))
    step = max(1, ENTRY_ROWS // len(j))
    for lo in range(0, len(i), step):
        part, lost = x[lo : lo + step], lost_i[lo : lo + step, None] | lost_j[None, :]
        v = kernel.block(part @ y.T, _norms(part), _norms(y))
        at = np.repeat(i[lo : lo + step], len(j)), np.tile(j, len(part))
        yield pa.RecordBatch.from_arrays([*[pa.array(a) for a in at], pa.array(v.ravel(), mask=lost.ravel() if lost.any() else None)], ["i", "j", "v"])


def _norms(x: np.ndarray) -> np.ndarray:
    return np.einsum("ij,ij->i", x, x)


def product(a: np.ndarray, b: np.ndarray, kernel: KernelSpec, store: StoreSpec) -> np.ndarray:
    """Kernel values between the rows of two blocks, as they are stored."""
    if store.dtype == "f32":
        a, b = a.astype(np.float32), b.astype(np.float32)
    return np.ascontiguousarray(kernel.block(a @ b.T, _norms(a), _norms(b)), dtype=store.stored)


def rows_of(batches):
    """Rows as dicts; binary cells are views of the batch, not copies."""
    for batch in batches:
        cols = [(name, batch.column(j), pa.types.is_binary(batch.schema.field(j).type)) for j, name in enumerate(batch.schema.names)]
        for i in range(batch.num_rows):
            yield {name: col[i].as_buffer() if raw else col[i].as_py() for name, col, raw in cols}


def cell(values: np.ndarray) -> pa.Array:
    """One binary cell over the bytes of an array."""
    flat = np.ascontiguousarray(values)
    return pa.Array.from_buffers(pa.binary(), 1, [None, pa.py_buffer(np.array([0, flat.nbytes], np.int32)), pa.py_buffer(flat)])


def tile_count(grid: GridSpec, store: StoreSpec) -> int:
    return grid.g * (grid.g + 1) // 2 if store.symmetric else grid.p


def by_rank(df: DataFrame, parts: int, rank: str = "rank") -> DataFrame:
    """Each row to the partition of its rank itself."""
    return df.repartitionById(parts, F.col(rank)) if hasattr(df, "repartitionById") else df.repartition(parts, rank)


def placed(wide: DataFrame, grid: GridSpec, store: StoreSpec) -> DataFrame:
    """PLACED rows: every wide block is copied along its grid row and its grid column, to the worker of the tile; the only move of the kernel stage.

    Symmetric stores place the tiles of bi <= bj alone, numbered column by column.
    """
    others, own = F.sequence(F.lit(0), F.lit(grid.g - 1)), F.col("blk")
    as_row = F.transform(others, lambda j: F.struct(own.alias("bi"), j.alias("bj"), F.lit(0).alias("side")))
    as_col = F.transform(others, lambda i: F.struct(i.alias("bi"), own.alias("bj"), F.lit(1).alias("side")))
    both = wide.select(F.inline(F.concat(as_row, as_col)), "blk", "lo", "cnt", "data")
    if store.symmetric:
        rank = F.floor(F.col("bj") * (F.col("bj") + 1) / 2) + F.col("bi")
        both = both.where("bi <= bj")
    else:
        rank = F.col("bj") * grid.g + F.col("bi")
    return by_rank(both.select(rank.cast("int").alias("rank"), "side", "blk", "lo", "cnt", "data"), tile_count(grid, store))


def products(batches, kernel: KernelSpec, store: StoreSpec, height: int | None = None):
    """(rank, bi, bj, lo_i, lo_j, K) for strips of every tile whose two blocks meet among these PLACED rows."""
    waiting: dict[int, dict] = {}
    for r in rows_of(batches):
        other = waiting.pop(r["rank"], None)
        if other is None:
            waiting[r["rank"]] = r
            continue
        a, b = (other, r) if r["side"] else (r, other)
        x, y = matrix(a["data"], a["cnt"]), matrix(b["data"], b["cnt"])
        step = height or max(1, STRIP_BYTES // (8 * len(y)))
        for lo in range(0, len(x), step):
            yield r["rank"], a["blk"], b["blk"], a["lo"] + lo, b["lo"], product(x[lo : lo + step], y, kernel, store)


def tile_row(bi: int, bj: int, rank: int, lo_i: int, lo_j: int, k: np.ndarray) -> pa.RecordBatch:
    values = [(bi, pa.int32()), (bj, pa.int32()), (rank, pa.int32()), (lo_i, pa.int64()), (lo_j, pa.int64()), (k.shape[0], pa.int32()), (k.shape[1], pa.int32())]
    return pa.RecordBatch.from_arrays([*[pa.array([v], t) for v, t in values], cell(k)], ["bi", "bj", "rank", "lo_i", "lo_j", "rows", "cols", "data"])


def tiles(at: DataFrame, kernel: KernelSpec, store: StoreSpec, height: int | None = None) -> DataFrame:
    """TILE strips of the grid product, made where the PLACED blocks lie."""

    def run(batches):
        for rank, bi, bj, lo_i, lo_j, k in products(batches, kernel, store, height):
            yield tile_row(bi, bj, rank, lo_i, lo_j, k)

    return at.mapInArrow(run, TILE)


def everywhere(blocks: DataFrame, grid: GridSpec) -> DataFrame:
    """PLACED rows: every fine block on every worker, its own first (side 0)."""
    everyone = F.sequence(F.lit(0), F.lit(grid.p - 1))
    sent = blocks.select(F.explode(everyone).alias("rank"), "blk", "lo", "cnt", "data")
    own_first = F.when(F.col("rank") == F.col("blk"), 0).otherwise(1)
    return by_rank(sent.select("rank", own_first.alias("side"), "blk", "lo", "cnt", "data"), grid.p).sortWithinPartitions("rank", "side", "blk", "lo")


def panels(blocks: DataFrame, kernel: KernelSpec, grid: GridSpec, store: StoreSpec) -> DataFrame:
    """Column panels, one per fine block, as TILE strips (bi: the block of rows).

    All blocks go to every worker (n * d words each), which is what limits this
    layout; a worker reads them one at a time beside its own.
    """
    at = everywhere(blocks, grid)

    def run(batches):
        mine = None
        for r in rows_of(batches):
            x = matrix(r["data"], r["cnt"])
            if r["side"] == 0:
                mine = (r["rank"], r["lo"], x.copy())
            if mine is not None and mine[0] == r["rank"]:  # a worker beyond the last block owns no panel
                step = max(1, STRIP_BYTES // (8 * len(mine[2])))
                for lo in range(0, len(x), step):
                    yield tile_row(r["blk"], mine[0], mine[0], r["lo"] + lo, mine[1], product(x[lo : lo + step], mine[2], kernel, store))

    return at.mapInArrow(run, TILE)


def regrid(at: DataFrame, kernel: KernelSpec, grid: GridSpec, store: StoreSpec) -> DataFrame:
    """Tiles re-laid to column panels: strips are cut by fine column block and all of K moves once, to the panels' owners."""

    def cut(batches):
        for _, bi, bj, lo_i, lo_j, k in products(batches, kernel, store):
            both = [(bj, lo_i, lo_j, k)]
            if store.symmetric and bi != bj:
                both.append((bi, lo_j, lo_i, k.T))
            for col, lo_r, lo_c, part in both:
                for f in grid.row_blocks(col):
                    lo, hi = (min(max(b, lo_c), lo_c + part.shape[1]) for b in grid.bounds(f))
                    if lo < hi:
                        yield tile_row(0, f, f, lo_r, lo, part[:, lo - lo_c : hi - lo_c])

    return by_rank(at.mapInArrow(cut, TILE), grid.p)


def regrid_slice(at: DataFrame, kernel: KernelSpec, grid: GridSpec, store: StoreSpec, bounds) -> DataFrame:
    """As ``regrid``, of the columns within ``bounds`` of each fine block alone; ``at`` has the sorted PLACED rows of all tiles."""

    def cut(batches):
        for _, group in groupby(rows_of(batches), key=lambda r: r["rank"]):
            rows = []
            for r in group:
                x = unpacked(r["data"], r["cnt"])
                if r["side"] == 0:
                    rows.append((r["lo"], x.copy()))
                    continue
                for f in grid.row_blocks(r["blk"]):
                    lo, hi = (min(max(b, r["lo"]), r["lo"] + r["cnt"]) for b in bounds(f))
                    if lo < hi:
                        y = x[lo - r["lo"] : hi - r["lo"]]
                        step = max(1, PASSING_BYTES // (8 * len(y)))
                        for at_row, part in ((at_row + i, part[i : i + step]) for at_row, part in rows for i in range(0, len(part), step)):
                            yield tile_row(0, f, f, at_row, lo, product(part, y, kernel, store))

    return by_rank(at.mapInArrow(cut, TILE), grid.p)
