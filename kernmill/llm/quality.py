"""Quality by positive-unlabelled learning.

Trusted positives and unlabelled web text train a small network on the
non-negative unbiased risk: the positive risk weighted by the class prior, plus
the negative risk that unlabelled text shows beyond the prior's share, taken as
zero and walked back where it turns negative. The prior is estimated on labelled
rows of the training part. Inputs are measures of the text alone: shares of
character kinds and of each sign, word and line statistics, repetition and
compressibility.

Fitting uses a bounded sample (``sample`` positives and as many unlabelled rows,
by hash of doc_id); scoring covers whole texts. Null and empty texts get the
score of a text of no words; repeated rows get equal scores; null doc_id counts
as not held out; a doc_id labelled both ways counts as bad. Where the table has
no unlabelled row (or no positive one), labelled rows of the training part stand
in for the missing side.
"""

from __future__ import annotations

import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_slices

SAMPLE, HIDDEN = 6000, 24
SIGNS = b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
_KIND = np.zeros(256, dtype=np.int64)
_KIND[[9, 10, 13, 32]] = 1
for _lo, _hi, _k in ((ord("A"), ord("Z"), 2), (ord("a"), ord("z"), 3), (ord("0"), ord("9"), 4), (128, 255, 5)):
    _KIND[_lo : _hi + 1] = _k
for _i, _c in enumerate(SIGNS):
    _KIND[_c] = 6 + _i
N_KINDS = 6 + len(SIGNS)


def measures(text: str | None) -> np.ndarray:
    text = text or ""
    raw = text.encode("utf-8", "replace")
    n = max(1, len(raw))
    share = np.bincount(_KIND[np.frombuffer(raw, np.uint8)], minlength=N_KINDS) / n
    words = text.split()
    m = max(1, len(words))
    counts = Counter(words)
    signed = sum(v for w, v in counts.items() if not w[-1].isalnum() and len(w) > 1 and not w[-2].isalnum())
    bare = sum(v for w, v in counts.items() if not any(map(str.isalnum, w)))
    upper = sum(v for w, v in counts.items() if w.isupper() and len(w) > 2)
    adjacent = sum(a == b for a, b in zip(words, words[1:]))
    lines = text.split("\n")
    # repetition falls with length by itself: against the usual growth of vocabulary
    rest = [
        np.log1p(m), len(raw) / m / 10, len(counts) / m**0.9, counts.most_common(1)[0][1] / m if counts else 0.0, sum(v for v in counts.values() if v > 1) / m,
        signed / m, bare / m, upper / m, adjacent / m, len(set(lines)) / len(lines), np.log1p(len(raw) / len(lines)) / 10, len(zlib.compress(raw, 1)) / (n + 40),
    ]
    return np.concatenate([np.sqrt(share), rest])


class Network:
    """One hidden layer; the output is positive for good text."""

    def __init__(self, centre, scale, w1, b1, w2, b2, curve=(1.0, 0.0)):
        self.p = [np.asarray(w1), np.asarray(b1), np.asarray(w2), np.asarray(b2)]
        self.centre, self.scale, self.curve = centre, scale, curve

    def margin(self, x: np.ndarray) -> np.ndarray:
        h = np.tanh(np.clip((x - self.centre) / self.scale, -6, 6) @ self.p[0] + self.p[1])
        return h @ self.p[2] + self.p[3]

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.curve[0] * self.margin(x) + self.curve[1], -30, 30)))


def train_nnpu(positive: np.ndarray, unlabelled: np.ndarray, prior: float, epochs: int = 60, seed: int = 5, rate: float = 0.01) -> Network:
    """Minimise the non-negative risk by mini-batches; the sigmoid loss l(z) = 1 / (1 + e^z)."""
    rng = np.random.Generator(np.random.PCG64(seed))
    both = np.concatenate([positive, unlabelled])
    centre, scale = both.mean(axis=0), both.std(axis=0) + 1e-3
    d = both.shape[1]
    net = Network(centre, scale, rng.normal(0, 1 / np.sqrt(d), (d, HIDDEN)), np.zeros(HIDDEN), rng.normal(0, 0.3, HIDDEN), np.zeros(()))
    first, second, step = [np.zeros_like(p) for p in net.p], [np.zeros_like(p) for p in net.p], 0
    norm = [np.clip((x - centre) / scale, -6, 6) for x in (positive, unlabelled)]
    size = 256
    for _ in range(epochs):
        order = [rng.permutation(len(x)) for x in norm]
        for b in range(max(1, max(len(x) for x in norm) // size)):
            xs = [x[np.take(o, range(b * size, (b + 1) * size), mode="wrap")] for x, o in zip(norm, order)]
            hs = [np.tanh(x @ net.p[0] + net.p[1]) for x in xs]
            zs = [h @ net.p[2] + net.p[3] for h in hs]
            good = [1 / (1 + np.exp(-np.clip(z, -30, 30))) for z in zs]
            slope = [g * (1 - g) for g in good]
            beyond = good[1].mean() - prior * good[0].mean()  # negative risk of the unlabelled beyond the positives in them
            grads = [-prior * slope[0] / size - prior * slope[0] / size, slope[1] / size]
            if beyond < 0:  # walk the negative part back
                grads = [prior * slope[0] / size, -slope[1] / size]
            step += 1
            total = [np.zeros_like(p) for p in net.p]
            for x, h, g in zip(xs, hs, grads):
                inner = g[:, None] * net.p[2] * (1 - h * h)
                for t, v in zip(total, (x.T @ inner, inner.sum(axis=0), h.T @ g, g.sum())):
                    t += v
            for i, g in enumerate(total):
                g = g + 1e-4 * net.p[i]
                first[i] = 0.9 * first[i] + 0.1 * g
                second[i] = 0.999 * second[i] + 0.001 * g * g
                net.p[i] = net.p[i] - rate * (first[i] / (1 - 0.9**step)) / (np.sqrt(second[i] / (1 - 0.999**step)) + 1e-8)
    return net


def _curve(z: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope (positive) and constant of a logistic curve of labels over margins."""
    from .toxicity import calibrate

    a, b = calibrate(z[:, None], y)
    return (float(a), float(b)) if a > 0 else (1.0, 0.0)


def fit(docs: DataFrame, labels: DataFrame, keep, sample: int = SAMPLE) -> Network:
    """Train on rows for which ``keep(doc_id)`` holds: at most ``sample`` trusted positives, as many unlabelled and labelled ones for prior and curve."""
    marked = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("y")).where("doc_id IS NOT NULL AND y IN (0, 1)").where(keep(F.col("doc_id"))).groupBy("doc_id").agg(F.min("y").alias("y"))
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id")).where("doc_id IS NOT NULL").where(keep(F.col("doc_id"))).distinct()

    def draw(rows: DataFrame, seed: int) -> DataFrame:
        return rows.orderBy(F.xxhash64("doc_id", F.lit(seed)), "doc_id").limit(sample)

    parts = [
        draw(marked.where("y = 1"), 1).select("doc_id", F.lit("p").alias("part")),
        draw(ids.join(labels.select(F.col("doc_id").cast("long").alias("doc_id")), "doc_id", "left_anti"), 2).select("doc_id", F.lit("u").alias("part")),
        draw(marked, 3).select("doc_id", F.concat(F.lit("l"), F.col("y").cast("string")).alias("part")),
    ]
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    chosen = texts.join(F.broadcast(parts[0].union(parts[1]).union(parts[2])), "doc_id")

    def run(batches):
        for batch in batches:
            for lo, n in byte_slices(batch.column(2), 1 << 20):
                part = batch.slice(lo, n)
                x = np.stack([measures(t) for t in part.column(2).to_pylist()])
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(list(x), pa.list_(pa.float64()))], ["doc_id", "part", "x"])

    rows = chosen.select("doc_id", "part", "text").mapInArrow(run, "doc_id long, part string, x array<double>").orderBy("part", "doc_id").toPandas()
    if rows.empty:
        blank = measures("")
        return Network(np.zeros_like(blank), np.ones_like(blank), np.zeros((len(blank), HIDDEN)), np.zeros(HIDDEN), np.zeros(HIDDEN), np.zeros(()))
    x = {k: np.stack(list(g)) for k, g in rows.groupby("part")["x"]}
    held = [x.get(k, np.zeros((0, len(rows["x"].iloc[0])))) for k in ("p", "u", "l0", "l1")]
    if not len(held[0]) or not len(held[1]):
        held[0] = held[0] if len(held[0]) else held[1] if len(held[1]) else held[2]
        held[1] = held[1] if len(held[1]) else np.concatenate([held[2], held[0]])
    prior = float(np.clip(len(held[3]) / max(1, len(held[2]) + len(held[3])) if len(held[2]) + len(held[3]) else 0.8, 0.05, 0.98))
    net = train_nnpu(held[0], held[1], prior)
    if len(held[2]) and len(held[3]):
        both = np.concatenate([held[2], held[3]])
        net.curve = _curve(net.margin(both), np.repeat([0.0, 1.0], [len(held[2]), len(held[3])]))
    return net


def score(docs: DataFrame, net: Network) -> DataFrame:
    """(doc_id, score) per row."""

    def run(batches):
        for batch in batches:
            for lo, n in byte_slices(batch.column(1), 1 << 20):
                part = batch.slice(lo, n)
                x = np.stack([measures(t) for t in part.column(1).to_pylist()])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(net.score(x), pa.float64())], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, score double")


def keep_good(docs: DataFrame, net: Network, least: float = 0.3) -> DataFrame:
    """Rows of ``docs`` whose text scores at least ``least``; all columns as they are."""
    at = docs.columns.index("text")
    schema = docs.schema

    def run(batches):
        for batch in batches:
            for lo, n in byte_slices(batch.column(at), 1 << 20):
                part = batch.slice(lo, n)
                x = np.stack([measures(t) for t in part.column(at).to_pylist()])
                yield part.filter(pa.array(net.score(x) >= least))

    return docs.mapInArrow(run, schema)
