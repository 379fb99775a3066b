"""Toxicity by compression distance.

Two dictionaries are trained by zstandard: one on ordinary text, one on toxic
text. A text is cut into windows at blanks, each window compressed with both;
the bytes that the toxic dictionary saves, at most, summed and by steps, are the
distance, and a logistic curve fitted on labelled texts calibrates them.

Toxic texts are mostly ordinary prose, and a dictionary trained on all of their
bytes learns that prose. So the toxic one is trained on their marking passages,
the stretches of words that labelled toxic texts hold far more often than
ordinary ones, and compresses together with the ordinary one: what it saves over
the ordinary one alone it saves on such passages.

Fitting uses a bounded sample of labelled rows (``sample`` per class, by hash of
doc_id, of which whole texts of ``sample_bytes`` in all); scoring covers whole
texts. A doc_id labelled both ways counts as toxic. Null and empty texts have
distance 0; repeated rows get equal scores; null doc_id counts as not held out.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import byte_slices

SAMPLE, WINDOW, LEVEL, RUN = 4000, 64, 9, 5
SIZE, TOXIC_SIZE, SEGMENT, MATCH = 8192, 2048, 24, 6
SAMPLE_BYTES = 256 << 20
STEPS, FOLDS = (2, 3, 4, 5, 6), 3
_LETTERS = re.compile(r"[^\W\d_]+")
_cache: dict = {}


def windows(text: str, size: int = WINDOW) -> list[bytes]:
    """UTF-8 pieces of about ``size`` bytes, cut after blanks where there are any, that make up the folded text."""
    raw = text.lower().encode("utf-8", "replace")
    out, at = [], 0
    while at < len(raw):
        end = at + size
        if end < len(raw):
            gap = raw.rfind(b" ", at + 1, end)
            end = gap if gap > at else end
        out.append(raw[at:end])
        at = end
    return out


def savings(text: str | None, ordinary, toxic) -> list[float]:
    """Largest saving of a window, logarithms of how many windows save at least each of STEPS bytes, of their sum, and of all windows."""
    parts = windows(text or "")
    gains = [len(ordinary.compress(p)) - len(toxic.compress(p)) for p in parts]
    return [
        float(max(gains, default=0)),
        *[math.log1p(sum(g >= s for g in gains)) for s in STEPS],
        math.log1p(sum(g - 1 for g in gains if g > 1)),
        math.log1p(len(parts)),
    ]


def _compressors(model: dict):
    import zstandard

    if _cache.get("key") != model["toxic"]:
        made = []
        for content in (model["ordinary"], model["toxic"]):
            held = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            held.precompute_compress(level=LEVEL)
            made.append(zstandard.ZstdCompressor(dict_data=held, write_content_size=False, write_checksum=False, write_dict_id=False))
        _cache.update(key=model["toxic"], made=made)
    return _cache["made"]


def runs_of(word: str, run: int = RUN) -> set[str]:
    """Letter runs that may mark a word: those of ``run`` characters, and its beginnings up to eight."""
    held = f" {word} "
    return {held[i : i + run] for i in range(len(held) + 1 - run)} | {held[:n] for n in range(run, min(9, len(held)) + 1)}


def marked(word: str, runs) -> list[str]:
    """The stretches of a word that marking runs cover."""
    held = f" {word} "
    on = [False] * len(held)
    for g in runs_of(word).intersection(runs):
        at = held.find(g)
        while at >= 0:
            on[at : at + len(g)] = [True] * len(g)
            at = held.find(g, at + 1)
    out, at = [], 0
    while at < len(held):
        end = at
        while end < len(held) and on[end]:
            end += 1
        if end > at:
            out.append(held[at:end])
        at = max(end, at + 1)
    return out


def toxic_runs(toxic: list[str], ordinary: list[str], least: int = 3, odds: float = 60.0) -> dict[str, int]:
    """Runs held by toxic texts ``odds`` times as often as by ordinary ones, with their counts of toxic texts.

    All words count on both sides. Words of more than 1/odds of the ordinary texts
    are left out of the toxic side: no run of theirs can pass.
    """
    pool: dict[str, str] = {}  # one string a word, however many texts hold it
    words = [[{pool.setdefault(w, w) for w in _LETTERS.findall(t.lower())} for t in side] for side in (toxic, ordinary)]
    seen = Counter(w for held in words[1] for w in held)
    common = {w for w, n in seen.items() if odds * n > len(ordinary)}
    counts: Counter = Counter()
    for held in words[0]:
        counts.update(set().union(*[runs_of(w) for w in held - common]))
    some = {g: n for g, n in counts.items() if n >= least}
    with_some = {w: found for w in seen if (found := runs_of(w) & some.keys())}
    against: Counter = Counter()
    for held in words[1]:
        against.update(set().union(*[with_some[w] for w in held if w in with_some]))
    return {g: n for g, n in some.items() if n / max(1, len(toxic)) >= odds * (against[g] + 0.5) / max(1, len(ordinary))}


def _trained(size: int, samples: list[bytes], **options) -> bytes:
    """Content of a dictionary trained by zstandard, without the tables before it; of samples too few to train on, their last ``size`` bytes."""
    import zstandard

    try:
        got = zstandard.train_dictionary(size, samples, **options).as_bytes()
    except zstandard.ZstdError:
        return b" ".join(samples)[-size:]
    return got[got.find(b" ") :] if got[:4] == b"\x37\xa4\x30\xec" else got


def passages(toxic: list[str], ordinary: list[str]) -> list[list[str]]:
    """The marking passages of each toxic text that has any, as often as they occur."""
    runs = toxic_runs(toxic, ordinary)
    found = [[m for w in _LETTERS.findall(t.lower()) for m in marked(w, runs)] for t in toxic]
    return [f for f in found if f]


def train_dictionaries(toxic: list[str], ordinary: list[str], size: int = SIZE, toxic_size: int = TOXIC_SIZE) -> dict[str, bytes]:
    """Contents of both dictionaries: that of ordinary text, and that of toxic text with the ordinary one behind it.

    Passages that training leaves out, as rare ones or for want of room, are put in front.
    """
    base = _trained(size, [w for t in ordinary for w in windows(t)])
    found = passages(toxic, ordinary)
    learnt = _trained(toxic_size, [" ".join(f).encode("utf-8", "replace") for f in found], k=SEGMENT, d=MATCH)
    counts = Counter(m for f in found for m in set(f))
    left = [m for m, _ in sorted(counts.items(), key=lambda m: (m[1], m[0])) if m.encode("utf-8", "replace") not in learnt]
    return {"ordinary": base, "toxic": "".join(left).encode("utf-8", "replace") + learnt + base}


def calibrate(features: np.ndarray, labels: np.ndarray, steps: int = 400) -> np.ndarray:
    """Weights of a logistic curve, the last the constant; Newton steps with a small ridge."""
    x = np.column_stack([features, np.ones(len(features))])
    w = np.zeros(x.shape[1])
    ridge = np.eye(len(w)) * 0.3
    for _ in range(min(steps, 50)):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve(x.T * (p * (1 - p)) @ x + ridge, x.T @ (labels - p) - ridge @ w)
        w += step
        if np.abs(step).max() < 1e-6:
            break
    return w


def _shingles(text: str) -> np.ndarray:
    """Distinct hashes, ascending, of the runs of three words; of shorter texts as a whole."""
    w = text.lower().split()
    return np.unique(np.array([zlib.crc32(" ".join(w[i : i + 3]).encode("utf-8", "replace")) for i in range(max(1, len(w) - 2))], dtype=np.uint32))


def _half_shared(a: np.ndarray, b: np.ndarray) -> bool:
    common = len(np.intersect1d(a, b, assume_unique=True))
    return 2 * common >= len(a) + len(b) - common


def _without_copies(texts: list[str]) -> list[str]:
    """Texts without those that share half of their shingles with an earlier one: copies and edited copies count once."""
    kept: list[str] = []
    sets: list[np.ndarray] = []
    by_low: dict[int, list[int]] = {}
    for t in texts:
        mine = _shingles(t)
        low = mine[:16].tolist()
        near = {i for h in low for i in by_low.get(h, ())}
        if any(_half_shared(mine, sets[i]) for i in near):
            continue
        for h in low:
            by_low.setdefault(h, []).append(len(kept))
        kept.append(t)
        sets.append(mine)
    return kept


def train(toxic: list[str], ordinary: list[str], folds: int = FOLDS) -> dict:
    """Dictionaries from all texts; the curve from savings of each fold under dictionaries of the others."""
    toxic, ordinary = _without_copies(toxic), _without_copies(ordinary)
    rows, labels = [], []
    for f in range(folds):
        pair = _compressors(train_dictionaries([t for i, t in enumerate(toxic) if i % folds != f], [t for i, t in enumerate(ordinary) if i % folds != f]))
        for y, texts in ((1.0, toxic), (0.0, ordinary)):
            held = texts[f::folds]
            rows += [savings(t, *pair) for t in held]
            labels += [y] * len(held)
    model = train_dictionaries(toxic, ordinary)
    if len(set(labels)) < 2:
        return model | {"weights": [0.5, *[0.0] * len(STEPS), 0.5, 0.0, -3.0]}
    return model | {"weights": calibrate(np.array(rows), np.array(labels)).tolist()}


def fit(docs: DataFrame, labels: DataFrame, keep, sample: int = SAMPLE, sample_bytes: int = SAMPLE_BYTES) -> dict:
    """Train on labelled rows for which ``keep(doc_id)`` holds: by hash of doc_id at most ``sample`` per class, and of these whole texts until ``sample_bytes``."""
    marked = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("y")).where("doc_id IS NOT NULL AND y IN (0, 1)").where(keep(F.col("doc_id"))).groupBy("doc_id").agg(F.max("y").alias("y"))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    drawn = [marked.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample) for y in (1, 0)]
    order = [F.xxhash64("doc_id"), "doc_id", F.xxhash64("text")]
    sized = texts.join(F.broadcast(drawn[0].union(drawn[1])), "doc_id").where("text IS NOT NULL")
    upto = F.sum(F.octet_length("text").cast("long")).over(Window.partitionBy("y").orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow))
    rows = sized.withColumn("upto", upto).where(F.col("upto") <= sample_bytes // 2).orderBy(*order).select("text", "y").collect()
    return train([r.text for r in rows if r.y == 1], [r.text for r in rows if r.y == 0])


def score(docs: DataFrame, model: dict) -> DataFrame:
    """(doc_id, score) per row."""

    def run(batches):
        pair = _compressors(model)
        w = np.array(model["weights"])
        for batch in batches:
            for lo, n in byte_slices(batch.column(1), 1 << 20):
                part = batch.slice(lo, n)
                f = np.array([savings(t, *pair) for t in part.column(1).to_pylist()])
                p = 1 / (1 + np.exp(-np.clip(f @ w[:-1] + w[-1], -30, 30)))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(p, pa.float64())], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, score double")
