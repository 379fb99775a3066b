"""One clustering sweep, relational form: grouped averages in place of the sparse product."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def round_robin(points: DataFrame, k: int) -> DataFrame:
    return points.select("idx", (F.col("idx") % k).cast("int").alias("cl"))


def hashed(points: DataFrame, k: int, seed: int = 0) -> DataFrame:
    return points.select("idx", F.pmod(F.xxhash64("idx", F.lit(seed)), F.lit(k)).cast("int").alias("cl"))


def sizes(labels: DataFrame, k: int) -> DataFrame:
    """(cl, cnt) of all k clusters, empty ones with 0."""
    every = labels.sparkSession.range(k).select(F.col("id").cast("int").alias("cl"))
    return every.join(labels.groupBy("cl").agg(F.count("*").alias("cnt")), "cl", "left").select("cl", F.coalesce("cnt", F.lit(0)).alias("cnt"))


def triplets(labels: DataFrame) -> DataFrame:
    """Membership as (cl, idx, w), w one over the cluster's size."""
    counts = labels.groupBy("cl").agg(F.count("*").alias("cnt"))
    return labels.join(F.broadcast(counts), "cl").select("cl", "idx", (1.0 / F.col("cnt")).alias("w"))


def cluster_means(entries: DataFrame, labels: DataFrame, transposed: bool = False) -> DataFrame:
    """(i, cl, e): mean kernel value of each point against each cluster; ``transposed`` reduces over rows, as K is symmetric."""
    own, other = ("j", "i") if transposed else ("i", "j")
    side = F.broadcast(labels.select(F.col("idx").alias(other), "cl"))  # few beside the entries, which would all move else
    return entries.join(side, other).groupBy(F.col(own).alias("i"), "cl").agg(F.avg("v").alias("e"))


def cluster_means_by_tile(entries: DataFrame, labels: DataFrame, n: int, side: int = 256) -> DataFrame:
    """As ``cluster_means``: tiles of ``side`` rows and columns meet their segment of the labels in a cogroup, and leave partial sums."""
    import numpy as np
    import pandas as pd

    def partial(tile: pd.DataFrame, segment: pd.DataFrame) -> pd.DataFrame:
        met = tile.merge(segment[["idx", "cl"]], left_on="j", right_on="idx")
        got = met.groupby(["i", "cl"], as_index=False).agg(total=("v", "sum"), cnt=("v", "size"))
        return got.astype({"i": np.int64, "cl": np.int32, "total": np.float64, "cnt": np.int64})

    bands = (n + side - 1) // side
    tiles = entries.withColumn("bi", F.floor(F.col("i") / side)).withColumn("bj", F.floor(F.col("j") / side))
    segments = labels.select("idx", "cl", F.floor(F.col("idx") / side).alias("bj")).withColumn("bi", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(bands - 1).cast("long"))))
    sums = tiles.groupBy("bi", "bj").cogroup(segments.groupBy("bi", "bj")).applyInPandas(partial, "i long, cl int, total double, cnt long")
    return sums.groupBy("i", "cl").agg((F.sum("total") / F.sum("cnt")).alias("e"))


def inner_pair_means(entries: DataFrame, labels: DataFrame) -> DataFrame:
    """(cl, c) straight from the entries whose two points share a cluster: the labels joined to both sides, the second time by cluster too."""
    rows = labels.select(F.col("idx").alias("i"), "cl")
    return entries.join(rows, "i").join(labels.select(F.col("idx").alias("j"), "cl"), ["j", "cl"]).groupBy("cl").agg(F.avg("v").alias("c"))


def own_cluster_mean(means: DataFrame, labels: DataFrame) -> DataFrame:
    """(i, cl, z): each point's mean against its own cluster."""
    return means.join(labels.select(F.col("idx").alias("i"), "cl"), ["i", "cl"]).select("i", "cl", F.col("e").alias("z"))


def centroid_norms(z: DataFrame) -> DataFrame:
    return z.groupBy("cl").agg(F.avg("z").alias("c"))


def scores(means: DataFrame, norms: DataFrame) -> DataFrame:
    """(i, cl, dist): squared distance without the point's own kernel value."""
    return means.join(F.broadcast(norms), "cl").select("i", "cl", (F.col("c") - 2 * F.col("e")).alias("dist"))


def with_empties_at_origin(dist: DataFrame, labels: DataFrame, k: int) -> DataFrame:
    """Adds score 0 of every empty cluster: it acts as if its centroid were the origin of the feature space."""
    empty = sizes(labels, k).where("cnt = 0").select("cl")
    extra = labels.select(F.col("idx").alias("i")).crossJoin(F.broadcast(empty)).select("i", "cl", F.lit(0.0).alias("dist"))
    return dist.unionByName(extra)


def sq_distances(dist: DataFrame, diagonal: DataFrame) -> DataFrame:
    return dist.join(diagonal.select("i", F.col("v").alias("kii")), "i").select("i", "cl", (F.col("dist") + F.col("kii")).alias("sq"))


def nearest(dist: DataFrame) -> DataFrame:
    """(idx, cl): least score, ties to the lowest cluster id."""
    return dist.groupBy(F.col("i").alias("idx")).agg(F.min(F.struct("dist", "cl")).alias("m")).select("idx", F.col("m.cl").alias("cl"))


def sweep(entries: DataFrame, labels: DataFrame, k: int, empty: str = "skip") -> DataFrame:
    """New labels after one whole sweep."""
    means = cluster_means(entries, labels)
    dist = scores(means, centroid_norms(own_cluster_mean(means, labels)))
    return nearest(with_empties_at_origin(dist, labels, k) if empty == "origin" else dist)


def objective(entries: DataFrame, labels: DataFrame) -> DataFrame:
    """One row: the sum of true squared distances at these labels."""
    means = cluster_means(entries, labels)
    z = own_cluster_mean(means, labels)
    trace = entries.where("i = j").agg(F.sum("v").alias("t"))
    return trace.crossJoin(z.agg(F.sum("z").alias("s"))).select((F.col("t") - F.col("s")).alias("objective"))
