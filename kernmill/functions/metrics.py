"""Quality and scaling measures over label and run frames."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """Share of points with the same label; frames of (idx, cl)."""
    both = a.select("idx", F.col("cl").alias("a")).join(b.select("idx", F.col("cl").alias("b")), "idx", "full_outer")
    return both.agg(F.avg(F.when(F.col("a").eqNullSafe(F.col("b")), 1.0).otherwise(0.0)).alias("agreement"))


def contingency(labels: DataFrame, truth: DataFrame) -> DataFrame:
    """(cl, truth, cnt)."""
    return labels.join(truth.select("idx", "truth"), "idx").groupBy("cl", "truth").agg(F.count("*").alias("cnt"))


def _pairs(c):
    return c * (c - 1) / 2


def ari(table: DataFrame) -> DataFrame:
    """Adjusted Rand index of a contingency table."""
    cells = table.agg(F.sum(_pairs(F.col("cnt"))).alias("s"), F.sum("cnt").alias("n"))
    rows = table.groupBy("cl").agg(F.sum("cnt").alias("c")).agg(F.sum(_pairs(F.col("c"))).alias("a"))
    cols = table.groupBy("truth").agg(F.sum("cnt").alias("c")).agg(F.sum(_pairs(F.col("c"))).alias("b"))
    expected = F.col("a") * F.col("b") / _pairs(F.col("n"))
    most = (F.col("a") + F.col("b")) / 2
    return cells.crossJoin(rows).crossJoin(cols).select(F.when(most == expected, 1.0).otherwise((F.col("s") - expected) / (most - expected)).alias("ari"))


def nmi(table: DataFrame) -> DataFrame:
    """Mutual information over the mean of both entropies."""
    n = table.agg(F.sum("cnt").alias("n"))
    rows = table.groupBy("cl").agg(F.sum("cnt").alias("a"))
    cols = table.groupBy("truth").agg(F.sum("cnt").alias("b"))
    full = table.join(rows, "cl").join(cols, "truth").crossJoin(n)
    info = full.agg(F.sum(F.col("cnt") / F.col("n") * F.log(F.col("cnt") * F.col("n") / (F.col("a") * F.col("b")))).alias("i"))

    def entropy(side, c, name):
        return side.crossJoin(n).agg((-F.sum(F.col(c) / F.col("n") * F.log(F.col(c) / F.col("n")))).alias(name))

    out = info.crossJoin(entropy(rows, "a", "ha")).crossJoin(entropy(cols, "b", "hb"))
    return out.select(F.when(F.col("ha") + F.col("hb") == 0, 1.0).otherwise(2 * F.col("i") / (F.col("ha") + F.col("hb"))).alias("nmi"))


def purity(table: DataFrame) -> DataFrame:
    most = table.groupBy("cl").agg(F.max("cnt").alias("m"), F.sum("cnt").alias("c"))
    return most.agg((F.sum("m") / F.sum("c")).alias("purity"))


def balance(labels: DataFrame, k: int, g: int, n: int, layout: str) -> DataFrame:
    """(worker, nonzeros) of the membership matrix, and the ratio of most to mean: 1 in column blocks, more in cluster-by-point blocks."""
    step = -(-n // (g * g))
    fine = F.floor(F.col("idx") / step).cast("int")
    if layout == "1d":
        rank = fine
    else:
        width = -(-k // g)
        rank = F.floor(fine / g).cast("int") * g + F.floor(F.col("cl") / width).cast("int")
    counts = labels.groupBy(rank.alias("worker")).agg(F.count("*").alias("nonzeros"))
    every = labels.sparkSession.range(g * g).select(F.col("id").cast("int").alias("worker")).join(counts, "worker", "left").select("worker", F.coalesce("nonzeros", F.lit(0)).alias("nonzeros"))
    return every.withColumn("ratio", F.max("nonzeros").over(Window.partitionBy()) / F.avg("nonzeros").over(Window.partitionBy()))


def weak_efficiency(runs: DataFrame) -> DataFrame:
    """Per dataset, k and algorithm: seconds on the fewest workers over seconds on g."""
    return _against_first(runs, "efficiency")


def strong_speedup(runs: DataFrame) -> DataFrame:
    return _against_first(runs, "speedup")


def _against_first(runs: DataFrame, name: str) -> DataFrame:
    total = runs.groupBy("dataset", "k", "algo", "g").agg(F.sum("seconds").alias("seconds"))
    base = F.first("seconds").over(Window.partitionBy("dataset", "k", "algo").orderBy("g").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return total.withColumn(name, base / F.col("seconds"))


def geometric_mean(df: DataFrame, value: str, *by: str) -> DataFrame:
    return df.groupBy(*by).agg(F.exp(F.avg(F.log(value))).alias("geo_mean"))


def speedup(runs: DataFrame, fast: str, slow: str) -> DataFrame:
    """Seconds of ``slow`` over seconds of ``fast`` at equal dataset, k and g."""
    total = runs.groupBy("dataset", "k", "algo", "g").agg(F.sum("seconds").alias("s"))
    a = total.where(F.col("algo") == fast).select("dataset", "k", "g", F.col("s").alias("fast_s"))
    b = total.where(F.col("algo") == slow).select("dataset", "k", "g", F.col("s").alias("slow_s"))
    return a.join(b, ["dataset", "k", "g"]).withColumn("speedup", F.col("slow_s") / F.col("fast_s"))


def report(runs: DataFrame) -> DataFrame:
    """Seconds by every grouping of dataset, k and algorithm."""
    return runs.cube("dataset", "k", "algo").agg(F.sum("seconds").alias("seconds"), F.count("*").alias("rows"))
