"""MinHash near-duplicates with odd sketches.

Signatures: ``samples`` MinHash values per text fold, four to a band, into 32
band keys, and all of them into a parity bitmap: each sample flips one of
``SKETCH_BITS`` bits, so that the population count of the XOR of two bitmaps
estimates how many samples differ, sharply where they nearly agree. Texts whose
shingle sets are equal collapse first. Texts that share a band key, directly or
through others, form a family; inside a family the bitmaps choose the pairs and
full shingle sets confirm them.

Recall: a pair of similarity 0.8 misses all 32 bands of four with probability
5e-8, and the sketch margin of 0.2 is over five standard deviations.

Families are handled in blocks of about ``BLOCK`` texts, every pair of blocks as
a task of its own, and a task returns one link a text at most, not all pairs.
Work inside one family of m different texts grows with (m / BLOCK) ** 2 tasks.

Sets are of 64-bit hashes of shingles. Null, empty and blank texts: empty set,
linked with nothing. Null doc_id: the row takes no part and gets no result.
Repeated rows each keep their row; different texts under one doc_id are one node
of the links, so that what either is linked with is reachable from both.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_broadcast, byte_slices, components, mix, salted_join, shingle_sets, stage

SAMPLES, ROWS, SKETCH_BITS = 128, 4, 512
BLOCK, BLOCK_SHINGLES = 256, 400_000
MARGIN, CHUNK = 0.2, 1 << 20
BROADCAST_ROWS = 2_000_000  # of two or three longs
_rng = np.random.Generator(np.random.PCG64(20))
_A = _rng.integers(1, 1 << 63, SAMPLES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_B = _rng.integers(1, 1 << 63, SAMPLES, dtype=np.uint64)
_C = _rng.integers(1, 1 << 63, SAMPLES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)

SIGNATURE = "doc_id long, n_shingles long, set_id string, bands array<long>"


def minhash(keys: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """(texts, SAMPLES) minima; every count must be over 0."""
    at = np.concatenate(([0], np.cumsum(counts)[:-1]))
    return np.stack([np.minimum.reduceat(keys * a + b, at) for a, b in zip(_A, _B)], axis=1)


def band_keys(mins: np.ndarray) -> np.ndarray:
    parts = mix(mins * _C).reshape(len(mins), -1, ROWS)
    h = np.arange(parts.shape[1], dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    for j in range(ROWS):
        h = mix(h + parts[:, :, j] * np.uint64(2 * j + 1))
    return h.view(np.int64)


def odd_sketch(mins: np.ndarray) -> np.ndarray:
    """(texts, SKETCH_BITS / 64) words: bit b is the parity of the samples that fall on b."""
    bit = (mix(mins + np.arange(SAMPLES, dtype=np.uint64) * _C) % np.uint64(SKETCH_BITS)).astype(np.int64)
    flat = (bit + np.arange(len(mins))[:, None] * SKETCH_BITS).ravel()
    odd = np.bincount(flat, minlength=len(mins) * SKETCH_BITS).reshape(len(mins), SKETCH_BITS) & 1
    return np.packbits(odd.astype(np.uint8), axis=1).view(np.uint64)


def similarity_estimate(ones: np.ndarray) -> np.ndarray:
    """Similarity from the population count of the XOR of two sketches."""
    share = np.minimum(2.0 * ones / SKETCH_BITS, 0.999)
    return 1.0 + SKETCH_BITS / (4.0 * SAMPLES) * np.log1p(-share)


def _blobs(column: pa.ChunkedArray | pa.Array) -> list[bytes]:
    return [b or b"" for b in column.cast(pa.binary()).to_pylist()]


def signatures(docs: DataFrame, k: int) -> DataFrame:
    """SIGNATURE per row with a doc_id; set_id names the shingle set (null: empty), bands is empty with it."""

    def run(batches):
        for batch in batches:
            ids = batch.column(0)
            for lo, n in byte_slices(batch.column(1), CHUNK):
                keys, counts = shingle_sets(_blobs(batch.column(1).slice(lo, n)), k)
                full = np.flatnonzero(counts)
                set_id, bands = [None] * n, [[]] * n
                if len(full):
                    at = np.concatenate(([0], np.cumsum(counts[full])[:-1]))
                    sums = [np.add.reduceat(mix(keys * np.uint64(m)), at) for m in (3, 5)]
                    for i, key in zip(full, band_keys(minhash(keys, counts[full]))):
                        bands[i] = key
                    for i, x, y in zip(full, *sums):
                        set_id[i] = f"{x:016x}{y:016x}{counts[i]:x}"
                yield pa.RecordBatch.from_arrays(
                    [ids.slice(lo, n), pa.array(counts, pa.int64()), pa.array(set_id, pa.string()), pa.array(bands, pa.list_(pa.int64()))],
                    ["doc_id", "n_shingles", "set_id", "bands"],
                )

    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).where("doc_id IS NOT NULL")
    return rows.mapInArrow(run, SIGNATURE)


def _linked(percent: int):
    """Function for one pair of blocks: joins texts whose full sets reach ``percent``, and links each to the smallest it is joined with."""

    def run(group: pd.DataFrame) -> pd.DataFrame:
        side = group["block"].to_numpy()
        ids = group["doc_id"].to_numpy()
        sets = [np.frombuffer(b, np.uint64) for b in group["members"]]
        sizes = np.array([len(s) for s in sets])
        sketch = odd_sketch(minhash(np.concatenate(sets), sizes))
        across = side.min() != side.max()
        least = percent / 100
        held: dict[int, set] = {}
        parent = list(range(len(ids)))

        def root(i: int) -> int:
            while parent[i] != i:
                parent[i] = parent[parent[i]]
                i = parent[i]
            return i

        def members(i: int) -> set:
            if i not in held:
                held[i] = set(sets[i].tolist())
            return held[i]

        rows, cols, ests = [], [], []
        for i in range(len(ids) - 1):
            j = np.arange(i + 1, len(ids))
            fit = np.minimum(sizes[i], sizes[j]) * 100 >= percent * np.maximum(sizes[i], sizes[j])
            if across:
                fit &= side[j] != side[i]
            j = j[fit]
            est = similarity_estimate(np.bitwise_count(sketch[j] ^ sketch[i]).sum(axis=1))
            near = est >= least - MARGIN
            rows.append(np.full(near.sum(), i))
            cols.append(j[near])
            ests.append(est[near])
        if rows:
            i_all, j_all = np.concatenate(rows), np.concatenate(cols)
            for p in np.argsort(-np.concatenate(ests), kind="stable"):
                i, j = int(i_all[p]), int(j_all[p])
                a, b = root(i), root(j)
                if a == b:
                    continue
                common = len(members(i) & members(j))
                if 100 * common >= percent * (sizes[i] + sizes[j] - common):
                    parent[a] = b
        least_id: dict[int, int] = {}
        for i in np.argsort(ids, kind="stable").tolist():
            least_id.setdefault(root(i), int(ids[i]))
        out = [(least_id[root(i)], int(ids[i])) for i in range(len(ids)) if least_id[root(i)] != ids[i]]
        return pd.DataFrame(out, columns=["a", "b"]).astype("int64")

    return run


def block_pairs(docs: DataFrame, reps: DataFrame, family: DataFrame, shingle_words: int) -> DataFrame:
    """(family, doc_id, members, block, lo, hi): the full set of every text of a family, once for each pair of blocks it is in.

    The number of blocks goes to the ids, salted, and with them to the texts, so
    that no exchange brings the sets of one family together: were they dealt by
    family, Spark would keep that and run all its pairs of blocks in one task.
    """

    def as_sets(batches):
        for batch in batches:
            for lo, n in byte_slices(batch.column(3), CHUNK):
                keys, counts = shingle_sets(_blobs(batch.column(3).slice(lo, n)), shingle_words)
                ends = np.cumsum(counts)
                yield pa.RecordBatch.from_arrays(
                    [*[batch.column(c).slice(lo, n) for c in range(3)], pa.array([keys[e - c : e].tobytes() for e, c in zip(ends, counts)], pa.binary())],
                    ["family", "doc_id", "blocks", "members"],
                )

    size = reps.select("rep", "n_shingles").join(family, F.col("rep") == F.col("node"))
    blocks = size.groupBy("component").agg(F.count("*").alias("texts"), F.sum("n_shingles").alias("shingles"))
    blocks = blocks.select("component", F.ceil(F.greatest(F.col("texts") / BLOCK, F.col("shingles") / BLOCK_SHINGLES)).cast("int").alias("blocks"))
    several = stage(blocks.where("blocks > 1"))  # any other family is one block
    placed = stage(salted_join(family, several, "component", "node", how="left").select("node", "component", F.coalesce("blocks", F.lit(1)).alias("blocks")))
    texts = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).join(bounded_broadcast(placed, BROADCAST_ROWS), F.col("doc_id") == F.col("node"))
    sets = texts.select("component", "doc_id", "blocks", "text").mapInArrow(as_sets, "family long, doc_id long, blocks int, members binary")
    return (
        sets.withColumn("block", F.pmod(F.xxhash64("doc_id"), F.col("blocks")).cast("int"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        .select("family", "doc_id", "members", "block", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"))
    )


def near_duplicates(docs: DataFrame, shingle_words: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) per row of ``docs`` with a doc_id.

    Texts are linked where 100 * intersection >= percent * union of their
    distinct shingles; component_id is the smallest doc_id reachable over links.
    """
    marks = stage(signatures(docs, shingle_words))
    # sets that many rows hold are joined by set and row together, or through the few sets that need it: no hot key
    firsts = stage(marks.where("set_id IS NOT NULL").groupBy("set_id").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n")))
    reps = marks.select("set_id", F.col("doc_id").alias("rep"), "n_shingles", "bands").join(firsts.select("set_id", "rep"), ["set_id", "rep"]).dropDuplicates(["set_id", "rep"])
    keyed = reps.select("rep", F.explode("bands").alias("band"))
    hubs = keyed.groupBy("band").agg(F.min("rep").alias("hub"), F.count("*").alias("n")).where("n > 1").drop("n")
    hubs = stage(hubs)
    hubs = bounded_broadcast(hubs, BROADCAST_ROWS)
    family = stage(components(keyed.join(hubs, "band").where("rep <> hub").select(F.col("rep").alias("a"), F.col("hub").alias("b"))))

    dealt = block_pairs(docs, reps, family, shingle_words)
    links = dealt.groupBy("family", "lo", "hi").applyInPandas(_linked(percent), "a long, b long")
    joined = components(links)
    owner = firsts.join(joined, F.col("rep") == F.col("node"), "left").select("set_id", "n", "rep", F.coalesce("component", "rep").alias("component_id"))
    owner = bounded_broadcast(stage(owner.where("n > 1 OR component_id <> rep").select("set_id", "component_id")), BROADCAST_ROWS)
    alone = F.coalesce("set_id", F.concat(F.lit("-"), F.col("doc_id").cast("string")))  # empty texts meet nothing, each by itself
    return (
        marks.select("doc_id", "n_shingles", alone.alias("set_id"))
        .join(owner, "set_id", "left")
        .select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))
        .withColumn("kept", F.col("doc_id") == F.col("component_id"))
    )


def deduplicate(docs: DataFrame, shingle_words: int = 5, percent: int = 80) -> DataFrame:
    """Rows of ``docs`` whose text stands for its group; of repeated rows with one doc_id one stays. Rows without doc_id stay.

    What goes is the smaller side: texts meet only the ids that go or repeat,
    which are broadcast if their number allows.
    """
    found = near_duplicates(docs, shingle_words, percent)
    by_id = found.groupBy(F.col("doc_id").alias("id")).agg(F.max("kept").alias("kept"), F.count("*").alias("n"))
    odd = bounded_broadcast(stage(by_id.where("NOT kept OR n > 1")), BROADCAST_ROWS)
    twice = bounded_broadcast(odd.where("kept"), BROADCAST_ROWS)
    single = docs.join(odd, docs["doc_id"].cast("long") == odd["id"], "left_anti")
    again = docs.join(twice, docs["doc_id"].cast("long") == twice["id"], "left_semi").dropDuplicates(["doc_id"])
    return single.unionByName(again)
