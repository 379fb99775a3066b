"""A fitted clustering: scoring of unseen points, members, storage."""

from __future__ import annotations

import uuid
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.kernels import KernelSpec, polynomial
from ..plans.layout import LoopSpec, StoreSpec
from ..plans.planner import choose as plan
from ..sources.store import materialize, read_json_row, write_json_row
from . import baselines, engines, moments
from .gram import STRIP_BYTES, cell, product


#: Training points up to this many bytes are copied to every worker for scoring; beyond it blocks of queries meet blocks of training points.
COPY_BYTES = 1 << 28
QUERY_BLOCK = 4096


@dataclass
class KernelClusterModel:
    """Training points, their labels, sizes and norms under one kernel; frozen."""

    spark: SparkSession
    points: DataFrame
    labels: DataFrame
    sizes: np.ndarray
    norms: np.ndarray
    kernel: KernelSpec
    copy_bytes: int = COPY_BYTES

    def _size(self) -> int:
        return self.points.agg(F.sum(F.size("x").cast("long") * 8)).first()[0] or 0

    def _moments(self) -> moments.Moments | None:
        """Those of all training points by label, where the kernel has them: k * d * d words in place of the points."""
        first = self.points.select("x").first()
        if first is None or not moments.fits(self.kernel, len(self.sizes), len(first.x)):
            return None
        k, dim, kernel = len(self.sizes), len(first.x), self.kernel

        def add(batches):
            found = moments.Moments(k, dim, kernel)
            for batch in batches:
                if batch.num_rows:
                    found.add(_rows_of(batch.column(0)), batch.column(1).to_numpy())
            yield pa.RecordBatch.from_arrays([cell(found.n), cell(found.first), cell(found.second if found.second is not None else np.zeros(0))], ["n", "first", "second"])

        total = moments.Moments(k, dim, kernel)
        for r in self.points.join(self.labels, "idx").select("x", "cl").coalesce(self.spark.sparkContext.defaultParallelism).mapInArrow(add, "n binary, first binary, second binary").collect():
            total.n += np.frombuffer(r.n)
            total.first += np.frombuffer(r.first).reshape(k, dim)
            if total.second is not None:
                total.second += np.frombuffer(r.second).reshape(k, dim, dim)
        return total

    def scorer(self, id_col: str):
        """(function for mapInArrow over (id, x), schema): kernel means of each row from the moments of the training points or, where there are none, against a copy of the points; refuses more than ``copy_bytes`` of them."""
        found = self._moments()
        if found is not None:
            return self._scored(id_col, self.spark.sparkContext.broadcast(found), lambda q, all_of: all_of.sums(q), STRIP_BYTES // 8)
        if self._size() > self.copy_bytes:
            raise ValueError(f"the training points take over {self.copy_bytes} bytes: score batches with assign, or fit with lloyd or lift, whose models are k means")
        rows = self.points.join(self.labels, "idx").select("idx", "x", "cl").orderBy("idx").toPandas()
        sent = self.spark.sparkContext.broadcast((np.array(rows["x"].tolist()), rows["cl"].to_numpy()))
        kernel, store, k = self.kernel, StoreSpec(), len(self.sizes)
        return self._scored(id_col, sent, lambda q, held: engines.label_sums(product(held[0], q, kernel, store), held[1], k), max(1, STRIP_BYTES // (8 * len(rows))))

    def _scored(self, id_col: str, sent, sums, step: int):
        """Labels and distances from ``sums``, the values of up to ``step`` rows added up by label. A column ``own`` after x holds labels to measure the distance to instead."""
        kernel, sizes, norms = self.kernel, self.sizes, self.norms

        def run(batches):
            for batch in batches:
                for lo in range(0, batch.num_rows, step):
                    part = batch.slice(lo, step)
                    q = _rows_of(part.column(1))
                    e = sums(q, sent.value) / np.maximum(sizes, 1)[:, None]
                    if part.num_columns > 2:
                        got = part.column(2).to_numpy()
                        d = norms[got] - 2 * e[got, np.arange(len(got))]
                    else:
                        got, d = engines.choose(e, norms, sizes, "skip")
                    yield pa.RecordBatch.from_arrays([part.column(0), pa.array(got, pa.int32()), pa.array(d + _own_values(q, kernel))], [id_col, "cl", "sq_distance"])

        return run, f"{id_col} long, cl int, sq_distance double"

    def _copied(self) -> bool:
        """Whether one task can score a row by itself: by moments or a copy of the points."""
        return moments.fits(self.kernel, len(self.sizes), len((self.points.select("x").first() or [[]])[0])) or self._size() <= self.copy_bytes

    def assign(self, queries: DataFrame, id_col: str = "idx") -> DataFrame:
        """(id, cl, sq_distance) of unseen points (id, x). A stream needs a kernel with moments, or training points within ``copy_bytes``; a batch does not."""
        rows = queries.select(F.col(id_col).cast("long").alias(id_col), "x")
        if queries.isStreaming or self._copied():
            run, schema = self.scorer(id_col)
            return rows.mapInArrow(run, schema)
        return self._assign_by_blocks(rows, id_col)

    def _assign_by_blocks(self, rows: DataFrame, id_col: str, own: bool = False) -> DataFrame:
        """Blocks of queries meet blocks of labelled training points pair by pair; a pair gives k sums a query, which add up by query block. ``own``: distances to the labels of a column cl."""
        k, kernel, store, sizes, norms = len(self.sizes), self.kernel, StoreSpec(), self.sizes, self.norms
        train = materialize(_blocks(self.points.join(self.labels, "idx").select("idx", "x", "cl"), "t"))
        asked = materialize(_blocks(rows.select(F.col(id_col).alias("idx"), "x", F.col("cl") if own else F.lit(0).alias("cl")), "q"))
        many = train.agg(F.max("blk")).first()[0] + 1
        pairs = asked.select(F.col("blk").alias("qb"), F.col("rows").alias("q"), F.explode(F.sequence(F.lit(0), F.lit(many - 1))).alias("tb")).join(train.select(F.col("blk").alias("tb"), F.col("rows").alias("t")), "tb")

        def partial(batches):
            for r in engines._rows(batches):
                ids, x, given = _unpacked(r["q"])
                _, y, cl = _unpacked(r["t"])
                yield pa.RecordBatch.from_arrays([pa.array([r["qb"]], pa.int32()), pa.array([r["tb"]], pa.int32()), cell(engines.label_sums(product(y, x, kernel, store), cl, k)), cell(ids), cell(_own_values(x, kernel)), cell(given)], ["qb", "tb", "sums", "ids", "own", "given"])

        def merge(table: pa.Table) -> pa.Table:
            parts = sorted(table.to_pylist(), key=lambda r: r["tb"])
            e = sum(np.frombuffer(r["sums"]).reshape(k, -1) for r in parts) / np.maximum(sizes, 1)[:, None]
            cl, d = engines.choose(e, norms, sizes, "skip")
            if own:
                cl = np.frombuffer(parts[0]["given"], np.int32)
                d = norms[cl] - 2 * e[cl, np.arange(len(cl))]
            return pa.table([pa.array(np.frombuffer(parts[0]["ids"], np.int64)), pa.array(cl, pa.int32()), pa.array(d + np.frombuffer(parts[0]["own"]))], names=[id_col, "cl", "sq_distance"])

        sums = pairs.mapInArrow(partial, "qb int, tb int, sums binary, ids binary, own binary, given binary")
        return sums.groupBy("qb").applyInArrow(merge, f"{id_col} long, cl int, sq_distance double")

    def members(self, top: int) -> DataFrame:
        """The ``top`` members nearest to each cluster's centre: (cl, rank, idx, sq_distance). Members are those of the fit, though another centre may have become nearer."""
        rows = self.points.join(self.labels, "idx").select(F.col("idx").cast("long").alias("idx"), "x", "cl")
        if self._copied():
            run, schema = self.scorer("idx")
            near = rows.mapInArrow(run, schema)
        else:
            near = self._assign_by_blocks(rows, "idx", own=True)
        near = near.withColumn("rank", F.row_number().over(Window.partitionBy("cl").orderBy("sq_distance", "idx")))
        return near.where(F.col("rank") <= top).select("cl", "rank", "idx", "sq_distance")

    def save(self, path: str) -> None:
        """Write under a fresh version, then point to it: readers see the old or the new model, never half of one."""
        version = f"{path}/{uuid.uuid4().hex}"
        self.points.select("idx", "x").write.parquet(f"{version}/points")
        self.labels.write.parquet(f"{version}/labels")
        meta = {"sizes": [int(s) for s in self.sizes], "norms": [float(c) for c in self.norms], "kernel": [self.kernel.name, self.kernel.gamma, self.kernel.coef0, self.kernel.degree]}
        write_json_row(self.spark, meta, f"{version}/meta")
        write_json_row(self.spark, {"version": version}, f"{path}/current")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> KernelClusterModel:
        version = read_json_row(spark, f"{path}/current")["version"]
        meta = read_json_row(spark, f"{version}/meta")
        return cls(spark, spark.read.parquet(f"{version}/points"), spark.read.parquet(f"{version}/labels"), np.array(meta["sizes"]), np.array(meta["norms"]), KernelSpec(*meta["kernel"]))


def _rows_of(column: pa.Array) -> np.ndarray:
    """Rows of an array column as a matrix."""
    return column.flatten().to_numpy(zero_copy_only=False).astype(float, copy=False).reshape(len(column), -1)


def _own_values(x: np.ndarray, kernel: KernelSpec) -> np.ndarray:
    """K(i, i) of each row."""
    nn = np.einsum("ij,ij->i", x, x)
    if moments.has_moments(kernel):
        return kernel.block(nn, nn, nn)
    return np.array([kernel.block(np.array([[v]]), np.array([v]), np.array([v]))[0, 0] for v in nn])


def _blocks(rows: DataFrame, name: str) -> DataFrame:
    """(blk, rows): lists of (idx, x, cl) of about QUERY_BLOCK rows, dealt by hash of idx."""
    number = max(1, -(-rows.count() // QUERY_BLOCK))
    dealt = rows.select(F.pmod(F.xxhash64("idx", F.lit(name)), F.lit(number)).cast("int").alias("blk"), F.struct(F.col("idx").cast("long").alias("idx"), "x", F.col("cl").cast("int").alias("cl")).alias("r"))
    return dealt.groupBy("blk").agg(F.array_sort(F.collect_list("r")).alias("rows"))


def _unpacked(rows: list[dict]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return np.array([r["idx"] for r in rows], np.int64), np.array([r["x"] for r in rows], float), np.array([r["cl"] for r in rows], np.int32)


@dataclass
class MeansModel:
    """k means in an explicit feature space (lloyd, lift, landmark): what a fit without K leaves, whatever the number of points."""

    spark: SparkSession
    feature: baselines.Feature
    means: np.ndarray
    sizes: np.ndarray

    def scorer(self, id_col: str):
        feature, means, sizes = self.feature, self.means, self.sizes
        norms = (means * means).sum(axis=1)

        def run(batches):
            for batch in batches:
                if batch.num_rows:
                    f = feature(np.array(batch.column(1).to_pylist(), dtype=float))
                    cl, d = engines.choose(means @ f.T, norms, sizes, "skip")
                    yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(cl, pa.int32()), pa.array(d + (f * f).sum(axis=1))], [id_col, "cl", "sq_distance"])

        return run, f"{id_col} long, cl int, sq_distance double"

    def assign(self, queries: DataFrame, id_col: str = "idx") -> DataFrame:
        """(id, cl, sq_distance) of unseen points (id, x); also on a stream."""
        run, schema = self.scorer(id_col)
        return queries.select(F.col(id_col).cast("long").alias(id_col), "x").mapInArrow(run, schema)

    def save(self, path: str) -> None:
        """As the kernel model's: a fresh version, then the pointer."""
        version = f"{path}/{uuid.uuid4().hex}"
        spec, base = self.feature.kernel, self.feature.base
        meta = {"means": self.means.tolist(), "sizes": [int(s) for s in self.sizes], "kernel": [spec.name, spec.gamma, spec.coef0, spec.degree]}
        if base is not None:
            meta |= {"base": base.tolist(), "onto": self.feature.onto.tolist()}
        write_json_row(self.spark, meta, f"{version}/meta")
        write_json_row(self.spark, {"version": version}, f"{path}/current")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> MeansModel:
        meta = read_json_row(spark, read_json_row(spark, f"{path}/current")["version"] + "/meta")
        extra = [np.array(meta[name]) if name in meta else None for name in ("base", "onto")]
        return cls(spark, baselines.Feature(KernelSpec(*meta["kernel"]), *extra), np.array(meta["means"]), np.array(meta["sizes"]))


def fit(points: DataFrame, k: int, kernel: KernelSpec | None = None, engine: str = "auto", loop: LoopSpec | None = None, allow_approx: bool = False, workers: int = 4, **options):
    """Fit by the named engine or the planner's choice: the model and how it was reached."""
    kernel = kernel or polynomial()
    n, d = engines.validate(points, k)
    if engine == "auto":
        engine = plan(n, d, k, workers, kernel, allow_approx=allow_approx).engine
    if engine in ("lloyd", "lift", "landmark"):
        given = () if engine == "lloyd" else (kernel,)
        result = getattr(baselines, engine)(points, k, *given, loop=loop, **options)
        return MeansModel(points.sparkSession, result.feature, result.means, result.sizes), result
    result = engines.fit(points, k, kernel, engine, loop=loop, finish=True, **options)
    return frozen(points, result, kernel), result


def frozen(points: DataFrame, result: engines.FitResult, kernel: KernelSpec) -> KernelClusterModel:
    """Model of a result's final labels; the result must have been fitted with ``finish``."""
    if not result.final:
        raise ValueError("the norms are not those of the final labels: fit with finish=True")
    return KernelClusterModel(points.sparkSession, points.select("idx", "x"), result.labels_df(), result.sizes, result.norms, kernel)


def latest_before(events: DataFrame, versions: DataFrame, by: str, at: str, since: str, value: str) -> DataFrame:
    """As-of join: each event takes the latest ``value`` of its key not after it; one window over the union, no range join."""
    both = events.select(by, F.col(at).alias("_at"), F.lit(None).alias("_v"), F.lit(1).alias("_e"), F.struct(*events.columns).alias("_row")).unionByName(
        versions.select(by, F.col(since).alias("_at"), F.col(value).alias("_v"), F.lit(0).alias("_e"), F.lit(None).alias("_row"))
    )
    w = Window.partitionBy(by).orderBy("_at", "_e").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    found = both.withColumn("_last", F.last("_v", ignorenulls=True).over(w)).where("_e = 1")
    return found.select("_row.*", F.col("_last").alias(value))


def within(events: DataFrame, spans: DataFrame, at: str, start: str, end: str, width: int) -> DataFrame:
    """Interval join of numeric columns: spans are cut into bins of ``width``, met by equality and checked for start <= at < end."""

    def bin_of(c: Column) -> Column:
        return F.floor(c / width).cast("long")

    cut = spans.withColumn("_bin", F.explode(F.sequence(bin_of(F.col(start)), bin_of(F.col(end)))))
    return events.withColumn("_bin", bin_of(F.col(at))).join(cut, "_bin").where((F.col(at) >= F.col(start)) & (F.col(at) < F.col(end))).drop("_bin")
