"""Nearest neighbours on vectors whose squares overflow or vanish, and bounds of the codes."""

import numpy as np

from kernmill.llm import neighbours


def frame(spark, rows):
    return spark.createDataFrame([(i, [float(v) for v in r]) for i, r in rows], "vec_id long, embedding array<double>")


def brute(rows, k):
    out = {}
    for qid, q in rows:
        if qid % 100 == 0:
            with np.errstate(over="ignore"):
                d = [(float(np.sqrt(sum((a - b) ** 2 for a, b in zip(q, v)))), i) for i, v in rows if i != qid]
            out[qid] = [i for _, i in sorted(d)[:k]]
    return out


def test_huge_and_tiny_vectors_have_all_their_neighbours(spark):
    rng = np.random.Generator(np.random.PCG64(4))
    rows = [(i, rng.normal(size=6) * scale) for i, scale in enumerate([1e200] * 20 + [1.0] * 200 + [1e-300] * 20 + [5e-324] * 3)]
    df = frame(spark, rows)
    got = {}
    for r in sorted(neighbours.nearest(df, df.where("vec_id % 100 = 0"), 5).collect(), key=lambda r: (r.query_id, r.rank)):
        got.setdefault(r.query_id, []).append(r.vec_id)
    usable = [(i, v) for i, v in rows if np.abs(v).max() > 0]
    assert got == brute(usable, 5) and set(got) == {0, 100, 200}


def test_bounds_hold():
    rng = np.random.Generator(np.random.PCG64(5))
    x = rng.normal(size=(60, 9)) * rng.choice([1e-5, 1.0, 1e5], size=(60, 1))
    side = neighbours.codes(x)
    assert side[0].dtype == np.int8
    low, high = neighbours.tile(side, side)
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(axis=2))
    assert (low <= d).all() and (d <= high).all()


def test_one_id_with_two_vectors(spark):
    df = frame(spark, [(0, [1.0, 0.0]), (1, [1.0, 0.1]), (1, [5.0, 5.0]), (1, [1.0, 0.1]), (2, [1.0, 0.05])])
    got = [(r.vec_id, round(r.score, 3)) for r in sorted(neighbours.nearest(df, df.where("vec_id = 0"), 3).collect(), key=lambda r: r.rank)]
    assert got == [(2, 0.05), (1, 0.1), (1, 0.1)]
