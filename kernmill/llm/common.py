"""Shared pieces of the training-data operators: staging, hashing, components."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

LOWER = ("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
#: Links (of two longs) up to this number have their nodes' smallest neighbours broadcast.
BROADCAST_LINKS = 1_000_000
_own_dir: str | None = None
_staged: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share; an own temporary one where none is set and all runs on this machine (tests), else an error."""
    global _own_dir
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found
    if not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    if _own_dir is None:
        _own_dir = tempfile.mkdtemp(prefix="kernmill-")
    return _own_dir


def stage(df: DataFrame) -> DataFrame:
    """Cut lineage by a Parquet table in the shared folder: survives lost executors."""
    path = f"{shared_dir(df.sparkSession).rstrip('/')}/staged-{uuid.uuid4().hex}"
    _staged.append(path)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def clear_staged(spark: SparkSession) -> None:
    """Delete the tables this process has staged; frames built on them can't be read any more."""
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    while _staged:
        path = jvm.org.apache.hadoop.fs.Path(_staged.pop())
        path.getFileSystem(conf).delete(path, True)


def ascii_lower(col):
    """Lower-case A-Z only."""
    return F.translate(col, *LOWER)


def let(value: Column, f) -> Column:
    """f(value) with ``value`` computed once a row, however often f or lambdas in it use it."""
    return F.transform(F.array(value), f)[0]


def small_enough(df: DataFrame, rows: int) -> bool:
    """True if ``df`` has at most ``rows`` rows; reads no more than rows + 1 of them."""
    return df.limit(rows + 1).count() <= rows


def salted_join(rows: DataFrame, once: DataFrame, key: str, spread: str, salts: int = 16, how: str = "inner") -> DataFrame:
    """Join (inner or left) of ``rows`` with ``once``, which holds a key once: rows of one key go to ``salts`` tasks by hash of ``spread``."""
    copies = once.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return rows.withColumn("_salt", F.pmod(F.xxhash64(spread), F.lit(salts)).cast("int")).join(copies, [key, "_salt"], how).drop("_salt")


def bounded_broadcast(df: DataFrame, rows: int) -> DataFrame:
    """Broadcast hint for a staged table, only where its size has been checked."""
    return F.broadcast(df) if small_enough(df, rows) else df


# --- vectorised hashing of words ---------------------------------------------

_MULT = 0x9E3779B97F4A7C15 | 1
_INV = pow(_MULT, -1, 1 << 64)
_BYTE = np.random.Generator(np.random.PCG64(7)).integers(1, 1 << 63, 256, dtype=np.uint64)
_BYTE[ord("A") : ord("Z") + 1] = _BYTE[ord("a") : ord("z") + 1]
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, 9, 10, 11, 12, 13]] = True


@lru_cache(maxsize=2)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    out = []
    for base in (_MULT, _INV):
        p = np.full(n, base, dtype=np.uint64)
        p[0] = 1
        out.append(np.multiply.accumulate(p))
    return out[0], out[1]


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def word_hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the white-space separated words (A-Z folded), and words per text."""
    buf = np.frombuffer(b" " + b" ".join(texts) + b" ", dtype=np.uint8)
    gap = _SPACE[buf]
    edge = np.flatnonzero(gap[1:] != gap[:-1]) + 1
    begin, end = edge[0::2], edge[1::2]
    power, inverse = _powers(1 << max(16, (len(buf) - 1).bit_length()))
    total = np.concatenate(([np.uint64(0)], np.cumsum(_BYTE[buf] * power[: len(buf)])))
    words = mix((total[end] - total[begin]) * inverse[begin] + (end - begin).astype(np.uint64))
    stops = np.cumsum([len(t) + 1 for t in texts]) + 1
    upto = np.searchsorted(begin, stops - 1, side="left")
    return words, np.diff(upto, prepend=0)


def shingle_sets(texts: list[bytes], k: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashed k-word shingles, ascending within each text, and their number per text.

    A text of fewer than k words has its whole sequence as its one shingle; one
    without words has none.
    """
    words, counts = word_hashes(texts)
    doc = np.repeat(np.arange(len(texts)), counts)
    first = np.concatenate(([0], np.cumsum(counts)[:-1])).astype(np.int64)
    keys, owners = [], []
    if len(words) >= k:
        h = np.zeros(len(words) - k + 1, dtype=np.uint64)
        for j in range(k):
            h = mix(h * np.uint64(3) + words[j : len(words) - k + 1 + j])
        inside = doc[: len(h)] == doc[k - 1 :]
        keys.append(h[inside])
        owners.append(doc[: len(h)][inside])
    for d in np.flatnonzero((counts > 0) & (counts < k)):
        h = np.array([counts[d]], dtype=np.uint64)
        for w in words[first[d] : first[d] + counts[d]]:
            h = mix(h * np.uint64(5) + w)
        keys.append(h)
        owners.append(np.array([d]))
    if not keys:
        return np.zeros(0, np.uint64), np.zeros(len(texts), np.int64)
    h, d = np.concatenate(keys), np.concatenate(owners)
    order = np.lexsort((h, d))
    h, d = h[order], d[order]
    fresh = np.ones(len(h), dtype=bool)
    fresh[1:] = (h[1:] != h[:-1]) | (d[1:] != d[:-1])
    return h[fresh], np.bincount(d[fresh], minlength=len(texts))


def byte_slices(column: pa.Array, limit: int) -> Iterator[tuple[int, int]]:
    """(start, number) of runs of rows with about ``limit`` bytes of text each, one row at least."""
    sizes = np.nan_to_num(pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False)).astype(np.int64)
    run = np.cumsum(sizes + 64) // limit
    edges = np.flatnonzero(np.diff(run, prepend=-1, append=-1))
    for lo, hi in zip(edges[:-1].tolist(), edges[1:].tolist()):
        yield lo, hi - lo


# --- connected components ----------------------------------------------------


def components(edges: DataFrame) -> DataFrame:
    """(node, component) for every node of ``edges`` (a long, b long); component: the smallest node reachable.

    Alternating star contraction: each round hangs neighbours on the smallest
    neighbour until nothing moves. All rounds are staged, nothing is collected.
    The smallest neighbours, two longs a node, are broadcast while the links are
    few enough, so that the links of one hub need not meet in one task; beyond
    that the links of a node are salted.
    """

    def smallest(e: DataFrame) -> DataFrame:
        return e.groupBy("u").agg(F.min("v").alias("m"))

    def state_of(e: DataFrame):
        return e.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()

    links = stage(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    before = state_of(links)
    while before.n:
        few = before.n <= BROADCAST_LINKS

        def with_least(e: DataFrame, least: DataFrame) -> DataFrame:
            return e.join(F.broadcast(least), "u") if few else salted_join(e, least, "u", "v")

        both = links.union(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = smallest(both).withColumn("m", F.least("u", "m"))
        large = with_least(both.where("v > u"), least).select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.union(least.select("u", F.col("m").alias("v"))).where("u <> v").distinct()
        small = with_least(large, smallest(large)).select(F.col("v").alias("u"), F.col("m").alias("v"))
        small = small.union(smallest(large).select("u", F.col("m").alias("v"))).where("u <> v").distinct()
        links = stage(small)
        state = state_of(links)
        if state == before:
            break
        before = state
    return links.select(F.col("u").alias("node"), F.col("v").alias("component")).union(links.select("v", "v").distinct())
