"""Scaling experiments: weak, strong, stage breakdown and the recomputing window, as frames of runs.

Worker counts are grids of partitions; on one machine they share its cores, so
logical words moved and the model's values at published sizes stand beside the
seconds.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from .functions import metrics
from .functions.kernels import polynomial
from .operators import engines
from .plans.layout import GridSpec, LoopSpec, StoreSpec

RUNS = "dataset string, k long, algo string, g long, n long, stage string, seconds double, words long"
EXACT = ("panel_1d", "regrid_h1d", "tile_2d", "mixed_15d")


def timed(spark: SparkSession, name: str, points: DataFrame, ks: Iterable[int], engine: str, g: int, sweeps: int, **options) -> list[tuple]:
    """Run rows of one layout: seconds by stage, and measured words of kernel and sweeps; K is built once for all ``ks``."""
    points = points.select("idx", "x")
    if StoreSpec().keeps(points.count()):
        points = points.persist()  # else whole vectors may take far more room than their blocks
    n, dim = engines.validate(points, max(ks))
    run = engines.make(engine, points, max(ks), polynomial(), GridSpec(n, g), LoopSpec(), StoreSpec(), dim, **options)
    began = time.time()
    run.prepare()
    built = time.time() - began
    kernel = sum(w for (stage, _), (w, _) in run.traffic.items() if stage == "kernel")
    rows = []
    for k in ks:
        run.k, run.traffic, run.seconds = k, {}, {"means": 0.0, "update": 0.0}
        labels = (np.arange(n) % k).astype(np.int32)
        for _ in range(sweeps):
            labels = run.sweep(labels, np.bincount(labels, minlength=k))[0]
        words = {"kernel": kernel, "means": sum(w for (stage, _), (w, _) in run.traffic.items() if stage == "sweep"), "update": 0}
        rows += [(name, k, engine, run.grid.p if engine != "window" else 1, n, s, t, words[s]) for s, t in ({"kernel": built} | run.seconds).items()]
    run.close()
    points.unpersist()
    return rows


def weak(spark: SparkSession, sources: dict[str, Callable[[int], DataFrame]], base: int, ks: Iterable[int] = (16, 32, 64), grids: Iterable[int] = (1, 2, 4), algorithms: Iterable[str] = EXACT, sweeps: int = 5) -> DataFrame:
    """n grows with the root of the workers, so that K per worker stays."""
    rows = []
    for name, source in sources.items():
        for g in grids:
            p = source(base * g).persist()
            for algo in algorithms:
                rows += timed(spark, name, p, ks, algo, g, sweeps)
            p.unpersist()
    return spark.createDataFrame(rows, RUNS)


def strong(spark: SparkSession, sources: dict[str, Callable[[int], DataFrame]], n: int, ks: Iterable[int] = (16, 32, 64), grids: Iterable[int] = (1, 2, 4), algorithms: Iterable[str] = EXACT, sweeps: int = 5) -> DataFrame:
    """n stays while the workers grow."""
    rows = []
    for name, source in sources.items():
        p = source(n).persist()
        rows += [r for g in grids for algo in algorithms for r in timed(spark, name, p, ks, algo, g, sweeps)]
        p.unpersist()
    return spark.createDataFrame(rows, RUNS)


def against_window(spark: SparkSession, name: str, points: DataFrame, k: int, heights: Iterable[int] = (256, 512, 1024), g: int = 2, sweeps: int = 5) -> DataFrame:
    """The mixed layout beside the recomputing window at several heights (algo window_<height>)."""
    rows = timed(spark, name, points, (k,), "mixed_15d", g, sweeps)
    for b in heights:
        rows += [(r[0], r[1], f"window_{b}", *r[3:]) for r in timed(spark, name, points, (k,), "window", g, sweeps, height=b)]
    return spark.createDataFrame(rows, RUNS)


def weak_report(runs: DataFrame) -> DataFrame:
    """Geometric mean of the weak efficiency over datasets and k, per algorithm and worker count."""
    return metrics.geometric_mean(metrics.weak_efficiency(runs), "efficiency", "algo", "g")


def strong_report(runs: DataFrame) -> DataFrame:
    return metrics.geometric_mean(metrics.strong_speedup(runs), "speedup", "algo", "g")
