"""Nearest neighbours by a block matrix join over int8 codes.

Vectors are rounded to int8 with a scale and an error each, and only these codes
are dealt into blocks and copied; every pair of blocks of queries and candidates
is one tile. A tile's integer product gives rounded distances, and the errors of
both vectors bound how far off they can be. Heaps keep the k least upper bounds
of each query, first over the tiles of a task and then over all; pairs whose
lower bound reaches beyond them go. The pairs left meet the original vectors
once and are recomputed in double precision. The result is exact.

Vectors too large for their squares, or too small for a scale, have no usable
bounds: their pairs all stay and are recomputed, so none is missed.

Rows whose vector is null, empty, zero or holds a null or non-finite component,
and rows without vec_id, take no part. Vectors compare with those of their own
length only. Of different query rows with one vec_id the least vector asks;
repeated candidates each count.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import bounded_broadcast, stage

QUERY_BLOCK, CANDIDATE_BLOCK, STRIP, EXACT_DIMS = 4096, 16384, 256, 1024
SMALLEST_SCALE = 1e-290
BROADCAST_ROWS = 1_000_000
CODED = "id long, dim int, code binary, scale double, off double"


def usable(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(id long, vec array<double>, dim) of the rows that take part."""
    rows = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<double>").alias("vec"))
    finite = F.forall("vec", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return rows.where(F.col("id").isNotNull() & F.col("vec").isNotNull() & finite & F.exists("vec", lambda x: x != 0)).withColumn("dim", F.size("vec"))


def codes(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """int8 codes, the scale of each row and the norm of its rounding error (infinite where squares overflow)."""
    scale = np.abs(x).max(axis=1) / 127.0
    scale = np.where(scale >= SMALLEST_SCALE, scale, 0.0)
    with np.errstate(over="ignore"):
        code = np.rint(x / np.where(scale > 0, scale, 1.0)[:, None]) * (scale > 0)[:, None]
        off = np.sqrt(((x - code * scale[:, None]) ** 2).sum(axis=1))
    return code.astype(np.int8), scale, off


def tile(q, c) -> tuple[np.ndarray, np.ndarray]:
    """Lower and upper bounds on the distances of all pairs of two sides (codes, scales, errors).

    Products of int8 codes are whole numbers below 2 ** 24 in every run of
    EXACT_DIMS components, so float32 multiplication gives them exactly.
    """
    (qc, qs, qe), (cc, cs, ce) = q, c
    dot = np.zeros((len(qc), len(cc)))
    for lo in range(0, qc.shape[1], EXACT_DIMS):
        dot += qc[:, lo : lo + EXACT_DIMS].astype(np.float32) @ cc[:, lo : lo + EXACT_DIMS].astype(np.float32).T
    with np.errstate(over="ignore", invalid="ignore"):
        qn, cn = ((side.astype(np.float64) ** 2).sum(axis=1) * s * s for side, s in ((qc, qs), (cc, cs)))
        about = np.sqrt(np.maximum(qn[:, None] + cn[None, :] - 2 * dot * (qs[:, None] * cs[None, :]), 0))
        # the last term: rounding of the double sums above and of the recomputed distance
        off = qe[:, None] + ce[None, :] + 1e-7 * (np.sqrt(qn)[:, None] + np.sqrt(cn)[None, :])
        known = np.isfinite(about + off)
        return np.where(known, about - off, -np.inf), np.where(known, about + off, np.inf)


def bounded_pairs(sides: list, k: int, best: dict[int, list[float]]) -> list[tuple]:
    """Arrays (query, candidate, low, high) of a pair of blocks that the k least upper bounds so far, kept in ``best``, do not exclude."""
    (qid, *q), (cid, *c) = sides
    out = []
    for lo in range(0, len(qid), STRIP):
        ids = qid[lo : lo + STRIP]
        low, high = tile([part[lo : lo + STRIP] for part in q], c)
        other = ids[:, None] != cid[None, :]
        for i, query in enumerate(ids.tolist()):
            own, held = other[i], best.setdefault(query, [])
            highs = high[i][own]
            least = np.partition(highs, k - 1)[:k] if len(highs) > k else highs
            held[:] = heapq.nsmallest(k, [*held, *least.tolist()])
            reach = held[-1] if len(held) == k else np.inf
            left = np.flatnonzero(own & (low[i] <= reach))
            out.append((np.full(len(left), query), cid[left], low[i][left], high[i][left]))
    return out


def coded(rows: DataFrame) -> DataFrame:
    """CODED rows: a byte a component."""

    def run(batches):
        for batch in batches:
            dims = np.asarray(batch.column(2))
            for dim in np.unique(dims):
                at = np.flatnonzero(dims == dim)
                part = batch.take(pa.array(at))
                code, scale, off = codes(part.column(1).flatten().to_numpy(zero_copy_only=False).reshape(len(at), dim))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array([r.tobytes() for r in code], pa.binary()), pa.array(scale), pa.array(off)], ["id", "dim", "code", "scale", "off"])

    return rows.mapInArrow(run, CODED)


def _blocks(rows: DataFrame, size: int, name: str) -> tuple[DataFrame, int]:
    number = max(1, -(-rows.count() // size))
    dealt = rows.withColumn(name, F.pmod(F.xxhash64("id", "code"), F.lit(number)).cast("int"))
    return dealt.groupBy("dim", name).agg(F.collect_list(F.struct("id", "code", "scale", "off")).alias(f"{name}_rows")), number


def _side(rows: pa.StructArray) -> list[np.ndarray]:
    ids, scale, off = (rows.field(n).to_numpy(zero_copy_only=False) for n in ("id", "scale", "off"))
    return [ids, np.frombuffer(b"".join(rows.field("code").to_pylist()), np.int8).reshape(len(ids), -1), scale, off]


def _distance(a: str, b: str) -> Column:
    """Euclidean distance in double precision, components added in their order."""
    parts = F.zip_with(a, b, lambda x, y: (x - y) * (x - y))
    return F.sqrt(F.aggregate(parts, F.lit(0.0), lambda s, v: s + v))


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 10, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): the k rows of ``vectors`` nearest to each row of ``queries``, itself left out.

    Ranks run from 1, nearest first, ties to the smaller id; fewer than k
    candidates give fewer rows.
    """
    asked = usable(queries, id_col, vector_col).groupBy("id").agg(F.min("vec").alias("vec")).withColumn("dim", F.size("vec"))
    every = usable(vectors, id_col, vector_col)
    q, q_blocks = _blocks(stage(coded(asked)), QUERY_BLOCK, "q")
    c, c_blocks = _blocks(stage(coded(every)), CANDIDATE_BLOCK, "c")
    q = q.withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(c_blocks - 1))))
    c = c.withColumn("q", F.explode(F.sequence(F.lit(0), F.lit(q_blocks - 1))))

    def run(batches):
        best: dict[int, list[float]] = {}
        for batch in batches:
            for i in range(batch.num_rows):
                sides = [_side(batch.column(n)[i].values) for n in ("q_rows", "c_rows")]
                cols = [np.concatenate(part) for part in zip(*bounded_pairs(sides, k, best))]
                yield pa.RecordBatch.from_arrays([pa.array(v) for v in cols], ["query_id", "vec_id", "low", "high"])

    schema = "query_id long, vec_id long, low double, high double"
    left = stage(q.join(c, ["dim", "q", "c"]).select("q_rows", "c_rows").mapInArrow(run, schema))
    by_high = Window.partitionBy("query_id").orderBy("high")
    reach = left.select("query_id", "high").withColumn("n", F.row_number().over(by_high)).where(F.col("n") <= k).groupBy("query_id").agg(F.max("high").alias("most"), F.count("*").alias("held"))
    reach = bounded_broadcast(stage(reach), BROADCAST_ROWS)
    pairs = left.join(reach, "query_id").where((F.col("held") < k) | (F.col("low") <= F.col("most"))).select("query_id", "vec_id").distinct()
    with_query = pairs.join(asked.select(F.col("id").alias("query_id"), F.col("vec").alias("q"), F.col("dim").alias("q_dim")), "query_id")
    both = with_query.join(every.select(F.col("id").alias("vec_id"), F.col("vec").alias("v"), "dim"), "vec_id").where("q_dim = dim")
    by = Window.partitionBy("query_id").orderBy("score", "vec_id")
    found = both.select("query_id", "vec_id", _distance("q", "v").alias("score")).withColumn("rank", F.row_number().over(by))
    return found.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
