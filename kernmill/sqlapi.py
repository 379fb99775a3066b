"""Functions for SQL users."""

from __future__ import annotations

from collections import Counter

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import Row

from .functions.kernels import KernelSpec

SMALL = 5_000


def _kernel(name: str, gamma: float, coef0: float, degree: int) -> KernelSpec:
    return KernelSpec("polynomial" if name == "poly" else name, float(gamma), float(coef0), int(degree))


def cluster_small(x: np.ndarray, k: int, kernel: KernelSpec, max_iter: int = 100) -> np.ndarray:
    """All sweeps in memory, for a table that fits one task."""
    nn = np.einsum("ij,ij->i", x, x)
    big = kernel.block(x @ x.T, nn, nn)
    labels = np.arange(len(x)) % k
    for _ in range(max_iter):
        sizes = np.bincount(labels, minlength=k)
        hot = np.zeros((k, len(x)))
        hot[labels, np.arange(len(x))] = 1
        e = hot @ big / np.maximum(sizes, 1)[:, None]
        c = np.bincount(labels, weights=e[labels, np.arange(len(x))], minlength=k) / np.maximum(sizes, 1)
        d = c[:, None] - 2 * e
        d[sizes == 0] = np.inf
        fresh = d.argmin(axis=0)
        if (fresh == labels).all():
            break
        labels = fresh
    return labels


def register(spark: SparkSession) -> None:
    """kernel_value(x, y, name, gamma, coef0, degree), vec_sum(x) per group, and the table functions cost_table(n, d, k, p),
    kernel_clusters(TABLE(points) WITH SINGLE PARTITION, k, name, gamma, coef0, degree) and contingency(TABLE(pairs) WITH SINGLE PARTITION).

    kernel_clusters runs in one task and refuses more than SMALL rows; larger
    tables go through ``kernmill.operators.model.fit``.
    """

    @F.pandas_udf("double")
    def kernel_value(x: pd.Series, y: pd.Series, name: pd.Series, gamma: pd.Series, coef0: pd.Series, degree: pd.Series) -> pd.Series:
        out = []
        for a, b, *spec in zip(x, y, name, gamma, coef0, degree):
            a, b = np.asarray(a, float), np.asarray(b, float)
            out.append(float(_kernel(*spec).block(np.array([[a @ b]]), np.array([a @ a]), np.array([b @ b]))[0, 0]))
        return pd.Series(out, dtype=float)

    @F.pandas_udf("array<double>")
    def vec_sum(x: pd.Series) -> list:
        return np.sum(np.stack([np.asarray(v, float) for v in x]), axis=0).tolist()

    limit = SMALL

    @F.udtf(returnType="idx bigint, cl int")
    class KernelClusters:
        def __init__(self):
            self.rows, self.spec = [], None

        def eval(self, row: Row, k: int, name: str, gamma: float, coef0: float, degree: int):
            if len(self.rows) >= limit:
                raise ValueError("kernel_clusters is for small tables; use the Python entry point")
            self.rows.append((row["idx"], row["x"]))
            self.spec = (k, name, gamma, coef0, degree)

        def terminate(self):
            if self.rows:
                self.rows.sort()
                k, *spec = self.spec
                for (idx, _), cl in zip(self.rows, cluster_small(np.array([x for _, x in self.rows], float), k, _kernel(*spec))):
                    yield int(idx), int(cl)

    @F.udtf(returnType="cl int, truth int, cnt bigint")
    class Contingency:
        def __init__(self):
            self.counts = Counter()

        def eval(self, row: Row):
            self.counts[row["cl"], row["truth"]] += 1

        def terminate(self):
            for (cl, truth), n in sorted(self.counts.items()):
                yield cl, truth, n

    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION cost_table(n DOUBLE, d DOUBLE, k DOUBLE, p DOUBLE)
      RETURNS TABLE (algo STRING, kernel_messages DOUBLE, kernel_words DOUBLE, sweep_messages DOUBLE, sweep_words DOUBLE) RETURN
      SELECT stack(4,
        '1d', p, p * n * d, p, n,
        'h1d', p + sqrt(p), n * n / p + n * d / sqrt(p), p, n,
        '2d', sqrt(p), n * d / sqrt(p), sqrt(p) + 1, n * (k + 1) / sqrt(p) + n,
        '1.5d', sqrt(p), n * d / sqrt(p), sqrt(p) + 1, n * (k + 1) / sqrt(p))""")
    spark.udf.register("kernel_value", kernel_value)
    spark.udf.register("vec_sum", vec_sum)
    spark.udtf.register("kernel_clusters", KernelClusters)
    spark.udtf.register("contingency", Contingency)
