"""Communication, memory and arithmetic models, and exact counts of our engines' traffic.

Logical words, as expressions over columns n, d, k, p, so that one frame of
parameters gives one frame of costs. Logarithmic factors are dropped unless
``with_logs``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

ALGORITHMS = ("1d", "h1d", "2d", "1.5d")


def _terms() -> tuple[Column, ...]:
    """n, d, k, p and the root of p as doubles; made on use, as columns need a session."""
    n, d, k, p = (F.col(c).cast("double") for c in "ndkp")
    return n, d, k, p, F.sqrt(p)


def kernel_stage(algo: str, with_logs: bool = False) -> tuple[Column, Column]:
    """(messages, words) of building K; the 1d words are those of all receivers together."""
    n, d, k, p, root = _terms()
    log = F.log2(root) if with_logs else F.lit(1.0)
    grid = n * d / root * log
    return {"1d": (p, p * n * d), "h1d": (p + root * log, n * n / p + grid), "2d": (root * log, grid), "1.5d": (root * log, grid)}[algo]


def distance_stage(algo: str, with_logs: bool = False, collective: str = "allgather") -> tuple[Column, Column]:
    """(messages, words) of one sweep: labels, partial sums and updates."""
    n, d, k, p, root = _terms()
    log = F.log2(root) if with_logs else F.lit(1.0)
    rounds = log if collective == "rounds" else F.lit(1.0)
    shared = n * (k + 1) / root
    return {"1d": (p, n), "h1d": (p, n), "2d": (root * rounds + log, shared * rounds + n * log), "1.5d": (root + log, shared)}[algo]


def memory(algo: str, workspace: float = 1.0) -> Column:
    """Words per worker at the fullest moment."""
    n, d, k, p, root = _terms()
    tile = n * n / p
    base = {
        "1d": tile + n * d + n + k * n / p,
        "h1d": 2 * tile + 2 * n * d / root + n,
        "2d": tile + n * k / root + 2 * n * d / root,
        "1.5d": tile + 2 * n * d / root + n * k / root + n / root,
    }[algo]
    return base * workspace


def cube_3d(copies: float) -> Column:
    """Words of K that a layout with ``copies`` replicas holds: why none is built."""
    n, d, k, p, root = _terms()
    return n * n * copies


def stationary(kind: str) -> Column:
    """Words of K, V or E that move in a sweep when the named operand stays: only a still K avoids n * n words."""
    n, d, k, p, root = _terms()
    return {"K": n * (k + 1) / root, "V": n * n / root, "E": n * n / root}[kind]


def _over(params: DataFrame, expr) -> DataFrame:
    """``params`` crossed with the algorithms, ``expr(algo)`` giving named columns."""
    out = None
    for algo in ALGORITHMS:
        part = params.select(F.lit(algo).alias("algo"), "n", "d", "k", "p", *[c.alias(name) for name, c in expr(algo).items()])
        out = part if out is None else out.unionByName(part)
    return out


def table(params: DataFrame, with_logs: bool = False) -> DataFrame:
    n, d, k, p, root = _terms()
    def row(algo):
        (km, kw), (dm, dw) = kernel_stage(algo, with_logs), distance_stage(algo, with_logs)
        return {"kernel_messages": km, "kernel_words": kw, "sweep_messages": dm, "sweep_words": dw, "kernel_per_worker": kw / p if algo == "1d" else kw, "kernel_aggregate": kw if algo == "1d" else kw * p}

    return _over(params, row)


def memory_table(params: DataFrame, bytes_per_word: int = 4, workspace: float = 1.0) -> DataFrame:
    return _over(params, lambda a: {"memory_bytes": memory(a, workspace) * bytes_per_word})


def feasible(params: DataFrame, limit_bytes: float, bytes_per_word: int = 4, workspace: float = 1.0) -> DataFrame:
    held = memory_table(params, bytes_per_word, workspace)
    return held.withColumn("feasible", F.col("memory_bytes") <= limit_bytes)


def crossover(spark: SparkSession, ks: list[int]) -> DataFrame:
    """Workers beyond which a 1.5d sweep moves fewer words than a 1d sweep: (k + 1) squared."""
    return crossover_of(spark.createDataFrame([(k,) for k in ks], "k long"))


def crossover_of(ks: DataFrame) -> DataFrame:
    """The same for a frame of k."""
    return ks.withColumn("workers", (F.col("k") + 1) * (F.col("k") + 1))


def flops(params: DataFrame) -> DataFrame:
    n, d, k, p, root = _terms()
    return params.select("n", "d", "k", "p", (2 * n * n * d).alias("kernel_flops"), (n * n).alias("means_sparse"), (2 * n * n * k).alias("means_dense"), (n * k).alias("update"), (4 * n * n).alias("kernel_bytes"))


def grid_product_square(params: DataFrame) -> DataFrame:
    """The grid product on n x n operands against the dense lower bound: they differ by log of the root of p."""
    n, d, k, p, root = _terms()
    return params.select("n", "p", (n * n / root).alias("bound_words"), (n * n / root * F.log2(root)).alias("grid_words"), F.log2(root).alias("ratio"))


def max_n(bytes_total: float, bytes_per_word: int = 4) -> int:
    """Points whose K fits ``bytes_total``."""
    return int((bytes_total / bytes_per_word) ** 0.5)


def largest(bytes_total: Column, bytes_per_word: int = 4) -> Column:
    """``max_n`` of a column."""
    return F.floor(F.sqrt(bytes_total / bytes_per_word)).cast("long")


def weak_plan(spark: SparkSession, base: int = 96_000, workers=(1, 4, 16, 64, 256)) -> DataFrame:
    """Points per worker count that keep K's bytes per worker equal."""
    return spark.createDataFrame([(w,) for w in workers], "p long").select("p", F.round(F.sqrt("p") * base).cast("long").alias("n")).withColumn("kernel_bytes_per_worker", (4 * F.col("n") * F.col("n") / F.col("p")))


def replicating(copies: float) -> tuple[Column, Column]:
    """(replication words, sweep words) of 1.5-D products that hold ``copies`` replicas of the dense operand while the first one stays: K itself would be copied."""
    n, d, k, p, root = _terms()
    return n * n * copies / p, n * k * copies / p + n * k / copies


def expected(engine: str, n: int, d: int, k: int, g: int, sweeps: int) -> dict[tuple[str, str], int]:
    """Orders of the published costs in words of all workers together, beside which measured traffic can be put."""
    p = g * g
    return {
        "panel_1d": {("kernel", "points"): p * n * d, ("sweep", "labels"): sweeps * p * n},
        "regrid_h1d": {("kernel", "points"): 2 * g * n * d, ("kernel", "regrid"): n * n, ("sweep", "labels"): sweeps * p * n},
        "tile_2d": {("kernel", "points"): 2 * g * n * d, ("sweep", "labels"): sweeps * g * n, ("sweep", "pieces"): sweeps * g * n * k, ("sweep", "minimum_pairs"): sweeps * 2 * g * n},
        "mixed_15d": {("kernel", "points"): 2 * g * n * d, ("sweep", "labels"): sweeps * g * n, ("sweep", "pieces"): sweeps * g * n * k},
    }[engine]
