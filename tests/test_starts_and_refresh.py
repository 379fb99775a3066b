"""Starts other than round robin, and the refresh of a published model."""

import numpy as np

from kernmill.functions import points
from kernmill.functions.kernels import linear, polynomial
from kernmill.operators import engines, model, sweep
from kernmill.plans.layout import LoopSpec
from kernmill.sources.store import materialize
from kernmill.streaming import streams


def sweeps(x: np.ndarray, labels: np.ndarray, k: int, times: int) -> np.ndarray:
    """Sweeps of the quadratic kernel over the whole matrix, one point and cluster at a time."""
    big = (x @ x.T + 1) ** 2
    for _ in range(times):
        held = [np.flatnonzero(labels == c) for c in range(k)]
        norms = [big[np.ix_(m, m)].mean() if len(m) else np.inf for m in held]
        labels = np.array([min(range(k), key=lambda c: (norms[c] - 2 * big[i, held[c]].mean() if len(held[c]) else np.inf, c)) for i in range(len(x))])
    return labels


def test_hashed_start_equals_brute_force(spark, sf_dir):
    p = points.part2(spark, sf_dir)
    rows = p.orderBy("idx").collect()
    start = [r.cl for r in sweep.hashed(p, 6, 3).orderBy("idx").collect()]
    got = engines.fit(p, 6, polynomial(), init="hash", seed=3, loop=LoopSpec(max_iter=4, fixed=True)).labels_df().orderBy("idx").collect()
    want = sweeps(np.array([r.x for r in rows]), np.array(start), 6, 4)
    assert [r.cl for r in got] == want.tolist()


def test_refresh_publishes_a_model_of_the_newest_points(spark, tmp_path):
    rows = [(i, i, [float(i % 2) * 10 + i / 100]) for i in range(40)]
    fed = materialize(spark.createDataFrame(rows, "idx long, key long, x array<double>").repartition(1)).inputFiles()[0].rsplit("/", 1)[0]
    seen = []

    def refit(newest):
        seen.append(sorted(r.idx for r in newest.collect()))
        own = points.dense_index(newest.select("key", "x"), ["key"], 1).select("idx", "key", "x")
        return model.fit(own, 2, linear(), engine="mixed_15d")[0]

    stream = streams.source(spark, fed, "idx long, key long, x array<double>")
    query = streams.refresh(stream, refit, 20, f"{tmp_path}/model", f"{tmp_path}/state")
    query.processAllAvailable()
    query.stop()
    assert seen == [list(range(20, 40))]
    again = model.KernelClusterModel.load(spark, f"{tmp_path}/model")
    labels = {r.idx: r.cl for r in again.assign(spark.createDataFrame([(0, 0, [0.3]), (1, 1, [10.3])], "idx long, key long, x array<double>")).collect()}
    assert labels[0] != labels[1]
