"""Neighbours of the exact engines: plain k-means, the exact quadratic lift, landmarks, spectral clustering."""

from __future__ import annotations

import json
from dataclasses import dataclass, replace
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.kernels import KernelSpec, linear, polynomial
from ..plans.layout import GridSpec, LoopSpec, StoreSpec, matrix, to_blocks
from .engines import FitResult, Fused, _piece, _rows, choose, validate
from .gram import by_rank, cell, product, products, rows_of

STEP, FANIN = 4096, 64
PART = "key int, sums binary, counts binary, inner double, changed double"


def quadratic_lift(x: np.ndarray, kernel: KernelSpec) -> np.ndarray:
    """Rows whose inner products are (gamma * <x, y> + coef0) ** 2: squares, scaled cross terms, scaled singles, a constant."""
    if kernel.name != "polynomial" or kernel.degree != 2 or kernel.gamma < 0 or kernel.coef0 < 0:
        raise ValueError("the lift is exact for degree 2, gamma and coef0 of at least 0")
    n, d = x.shape
    i, j = np.triu_indices(d, 1)
    return np.concatenate(
        [kernel.gamma * x**2, kernel.gamma * np.sqrt(2) * x[:, i] * x[:, j], np.sqrt(2 * kernel.gamma * kernel.coef0) * x, np.full((n, 1), kernel.coef0)],
        axis=1,
    )


@dataclass
class MeansResult:
    """A fit in an explicit feature space: k means; labels stay with the blocks of points and are made on reading."""

    spark: SparkSession
    n: int
    k: int
    sizes: np.ndarray
    means: np.ndarray
    norms: np.ndarray
    history: list[tuple]
    blocks: DataFrame
    rule: Rule
    feature: Feature
    traffic: tuple = ()
    final: bool = True

    sizes_df = FitResult.sizes_df
    history_df = FitResult.history_df

    @cached_property
    def labels(self) -> np.ndarray:
        """All labels on the driver, by idx: for few points only."""
        out = np.zeros(self.n, np.int32)
        rows = self.labels_df().toPandas()
        out[rows["idx"].to_numpy()] = rows["cl"].to_numpy()
        return out

    def labels_df(self) -> DataFrame:
        rule, feature = self.rule, self.feature

        def run(batches):
            for r in _rows(batches):
                cl = rule.labels(r["lo"], feature(matrix(r["data"], r["cnt"])))
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(r["lo"], r["lo"] + len(cl))), pa.array(cl, pa.int32())], ["idx", "cl"])

        return self.blocks.mapInArrow(run, "idx long, cl int")


@dataclass(frozen=True)
class Rule:
    """What gives a point its label: round robin without means, else the nearest mean; ``moved`` are the points that empty clusters took."""

    k: int
    empty: str = "skip"
    means: np.ndarray | None = None
    norms: np.ndarray | None = None
    sizes: np.ndarray | None = None
    moved: tuple = ()

    def labels(self, lo: int, f: np.ndarray, scores: bool = False):
        if self.means is None:
            return ((lo + np.arange(len(f))) % self.k).astype(np.int32)
        cl, d = choose(self.means @ f.T, self.norms, self.sizes, self.empty)
        for idx, to in self.moved:
            if lo <= idx < lo + len(f):
                cl[idx - lo] = to
        return (cl, d) if scores else cl


def _collected(blocks: DataFrame, run, parts: int, k: int) -> tuple:
    """Sums over all blocks of ``run``'s rows (sums, counts, inner, changed): within each task first, then over FANIN tasks, so that the driver gets few rows of k * m words."""
    fanin = FANIN

    def total(rows):
        out = None
        for row in rows:
            out = row if out is None else tuple(a + b for a, b in zip(out, row))
        if out is not None:
            key = TaskContext.get().partitionId() % fanin
            yield pa.RecordBatch.from_arrays([pa.array([key], pa.int32()), cell(out[0]), cell(out[1]), *[pa.array([float(v)]) for v in out[2:]]], ["key", "sums", "counts", "inner", "changed"])

    def again(batches):
        yield from total((matrix(r["sums"], k), np.frombuffer(r["counts"], np.int64), r["inner"], r["changed"]) for r in _rows(batches))

    rows = blocks.mapInArrow(lambda batches: total(run(batches)), PART)
    if parts > fanin:
        rows = by_rank(rows, fanin, "key").mapInArrow(again, PART)
    rows = rows.collect()
    return sum(matrix(r.sums, k) for r in rows), sum(np.frombuffer(r.counts, np.int64) for r in rows), sum(r.inner for r in rows), sum(r.changed for r in rows)


def _farthest(blocks: DataFrame, rule: Rule, feature) -> tuple:
    """(idx, cluster) that empty clusters take: by id, each the farthest point (lowest idx on ties) of a cluster that keeps a member.

    A block sends its k farthest points of each cluster at most.
    """
    k = rule.k

    def run(batches):
        sizes, best = np.zeros(k, np.int64), []
        for r in _rows(batches):
            f = feature(matrix(r["data"], r["cnt"]))
            cl, d = rule.labels(r["lo"], f, scores=True)
            sq = d + (f * f).sum(axis=1)
            sizes += np.bincount(cl, minlength=k)
            order = np.lexsort((np.arange(len(cl)), -sq, cl))
            rank = np.arange(len(order)) - np.searchsorted(cl[order], cl[order])
            best += [(int(cl[i]), float(sq[i]), int(i) + r["lo"]) for i in order[rank < k]]
        yield pa.RecordBatch.from_arrays([cell(sizes), pa.array([json.dumps(best)])], ["sizes", "best"])

    rows = blocks.mapInArrow(run, "sizes binary, best string").collect()
    sizes = sum(np.frombuffer(r.sizes, np.int64) for r in rows).copy()
    far = sorted((-sq, idx, cl) for r in rows for cl, sq, idx in json.loads(r.best))
    out = []
    for cl in np.flatnonzero(sizes == 0):
        at = next((i for i, (_, _, own) in enumerate(far) if sizes[own] > 1), None)
        if at is None:
            break
        _, idx, own = far.pop(at)
        sizes[own] -= 1
        out.append((idx, int(cl)))
    return tuple(out)


def _mean_loop(blocks: DataFrame, n: int, k: int, loop: LoopSpec, feature) -> MeansResult:
    """Averages in an explicit feature space: one scan a sweep, features made per block and never stored.

    Labels are kept nowhere: a scan makes those of the sweep before from its means,
    adds up their members, and counts how many differ from the labels before them.
    Only k means of m words reach the driver, whatever the number of points.
    """
    spark = blocks.sparkSession
    blocks = blocks.persist()
    before, rule, history, parts = None, Rule(k, loop.empty), [], blocks.rdd.getNumPartitions()
    norms, sizes, t = np.zeros(k), np.zeros(k), 0
    while True:
        sent = spark.sparkContext.broadcast((before, rule))

        def add(batches):
            old, now = sent.value
            for r in _rows(batches):
                f = feature(matrix(r["data"], r["cnt"]))
                cl = now.labels(r["lo"], f)
                hot = np.zeros((k, len(cl)))
                hot[cl, np.arange(len(cl))] = 1
                changed = 0 if old is None else int((old.labels(r["lo"], f) != cl).sum())
                yield hot @ f, np.bincount(cl, minlength=k).astype(np.int64), float((f * f).sum()), float(changed)

        sums, sizes, inner, changed = _collected(blocks, add, parts, k)
        sent.destroy()
        if t:
            history[-1] = (t, int(changed), *history[-1][2:])
        if t == loop.max_iter or (t and changed == 0 and not loop.fixed):
            break
        if loop.empty == "error" and (sizes == 0).any():
            raise ValueError(f"clusters {np.flatnonzero(sizes == 0).tolist()} are empty before sweep {t + 1}")
        t += 1
        means = sums / np.maximum(sizes, 1)[:, None]
        norms = (means * means).sum(axis=1)
        history.append((t, 0, inner - float((sizes * norms).sum()), int((sizes == 0).sum()), 0.0))
        before, rule = rule, Rule(k, loop.empty, means, norms, sizes)
        if loop.empty == "reseed":
            rule = replace(rule, moved=_farthest(blocks, rule, feature))
    means = sums / np.maximum(sizes, 1)[:, None]
    return MeansResult(spark, n, k, sizes, means, (means * means).sum(axis=1), history, blocks, rule, feature)


@dataclass(frozen=True)
class Feature:
    """Points as they are (linear), their quadratic lift, or their place among landmarks; made per block."""

    kernel: KernelSpec
    base: np.ndarray | None = None
    onto: np.ndarray | None = None

    def __call__(self, x: np.ndarray) -> np.ndarray:
        if self.base is not None:
            return product(x, self.base, self.kernel, StoreSpec()) @ self.onto
        return x if self.kernel.name == "linear" else quadratic_lift(x, self.kernel)


def lloyd(points: DataFrame, k: int, loop: LoopSpec | None = None) -> MeansResult:
    """Plain k-means from the round-robin start: the same labels as the linear kernel at n * k * d work."""
    n, _ = validate(points, k)
    return _mean_loop(to_blocks(points, STEP), n, k, loop or LoopSpec(), Feature(linear()))


def lift(points: DataFrame, k: int, kernel: KernelSpec | None = None, loop: LoopSpec | None = None) -> MeansResult:
    """Exact kernel k-means for degree-2 polynomials in the explicit feature space."""
    kernel = kernel or polynomial()
    quadratic_lift(np.zeros((1, 1)), kernel)
    n, _ = validate(points, k)
    return _mean_loop(to_blocks(points, STEP), n, k, loop or LoopSpec(), Feature(kernel))


def landmark(points: DataFrame, k: int, kernel: KernelSpec | None = None, m: int = 100, seed: int = 0, loop: LoopSpec | None = None) -> MeansResult:
    """Approximate: m sampled points span the feature space, all points are mapped onto it and clustered there."""
    kernel = kernel or polynomial()
    n, _ = validate(points, k)
    drawn = points.orderBy(F.xxhash64("idx", F.lit(seed)), "idx").limit(min(m, n)).orderBy("idx").collect()
    base = np.array([r.x for r in drawn])
    values, vectors = np.linalg.eigh(product(base, base, kernel, StoreSpec()))
    good = values > max(values.max() * 1e-10, 0)
    return _mean_loop(to_blocks(points, STEP), n, k, loop or LoopSpec(), Feature(kernel, base, vectors[:, good] / np.sqrt(values[good])))


def spectral(points: DataFrame, k: int, kernel: KernelSpec, rounds: int = 30, seed: int = 0, g: int = 2, limit_bytes: int = 1 << 31) -> MeansResult:
    """Normalised spectral clustering: subspace iteration on the degree-scaled kernel, then plain k-means.

    Blocks of points meet in pairs as in ``fused``; K is made anew in every round.
    The driver holds the n x k basis, which must stay within ``limit_bytes``.
    """
    n, dim = validate(points, k)
    if n * k * 8 > limit_bytes:
        raise ValueError(f"a basis of {n * k * 8} bytes does not fit the driver; use mixed_15d or landmark")
    spark, grid, store = points.sparkSession, GridSpec(n, g), StoreSpec()
    run = Fused(points, k, kernel, grid, LoopSpec(), store, dim)
    run.prepare()
    at = run.at

    def times(v: np.ndarray) -> np.ndarray:
        sent, width = spark.sparkContext.broadcast(v), v.shape[1]

        def partial(batches):
            held: dict[tuple[int, int], np.ndarray] = {}
            for _, bi, bj, lo_i, lo_j, block in products(batches, kernel, store):
                sums = sent.value[lo_i : lo_i + len(block)].T @ block
                held[bi, bj] = held.get((bi, bj), 0) + sums
            for (bi, bj), sums in held.items():
                yield _piece(bj, bi, grid.wide(bj)[0], sums)

        def merge(batches):
            held: dict[int, list] = {}
            for r in rows_of(batches):
                held.setdefault(r["owner"], []).append(r)
            for parts in held.values():
                parts.sort(key=lambda r: r["bi"])
                yield pa.RecordBatch.from_arrays([pa.array([parts[0]["lo"]], pa.int64()), cell(sum(matrix(r["data"], width) for r in parts))], ["lo", "out"])

        pieces = at.mapInArrow(partial, "owner int, bi int, lo long, cnt int, data binary")
        rows = sorted(by_rank(pieces, grid.g, "owner").mapInArrow(merge, "lo long, out binary").collect(), key=lambda r: r.lo)
        sent.destroy()
        return np.concatenate([matrix(r.out, width).T for r in rows])

    scale = 1 / np.sqrt(np.maximum(times(np.ones((n, 1)))[:, 0], 1e-300))
    v = np.linalg.qr(np.random.Generator(np.random.PCG64(seed)).normal(size=(n, k)))[0]
    for _ in range(rounds):
        v = np.linalg.qr(scale[:, None] * times(scale[:, None] * v))[0]
    rows = v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-300)
    run.close()
    table = pa.table({"idx": np.arange(n), "x": pa.FixedSizeListArray.from_arrays(pa.array(rows.ravel()), k).cast(pa.list_(pa.float64()))})
    return lloyd(spark.createDataFrame(table), k)
