"""Queries over whole tables against brute force: no head and no filter."""

import numpy as np
import pyarrow.parquet as pq
import pytest

from kernmill.functions import points
from kernmill.functions.kernels import polynomial
from kernmill.operators import baselines, engines
from kernmill.plans.layout import LoopSpec
from kernmill.workloads import tables


def read(sf_dir, name):
    return pq.read_table(f"{sf_dir}/{name}.parquet").to_pandas()


def zscore(x):
    return (x - x.mean(axis=0)) / x.std(axis=0)


def test_line4_points_hold_every_row(spark, sf_dir):
    rows = read(sf_dir, "lineitem").sort_values(points.LINE_KEY)
    want = zscore(rows[points.LINE4].to_numpy(float))
    got = np.full(want.shape, np.nan)
    for r in tables.QUERIES["line4_points"](spark, sf_dir).collect():
        got[r.idx, r.pos - 1] = r.v
    assert len(want) > 2000 and np.allclose(got, want, atol=1e-4)


def test_wide28_and_eventday_hold_every_row(spark, sf_dir):
    for source, name in ((points.wide28, "lineitem"), (points.eventday, "events")):
        rows = source(spark, sf_dir).select("idx", "x").collect()
        assert sorted(r.idx for r in rows) == list(range(len(read(sf_dir, name))))
        x = np.array([r.x for r in sorted(rows)])
        still = x.std(axis=0) < 1e-9
        z = x if name == "lineitem" else x[:, 2:]
        assert np.allclose(z.mean(axis=0), 0, atol=1e-9)
        assert np.allclose(z.std(axis=0)[~still[-z.shape[1] :]], 1, atol=1e-9)


def test_gram_and_intervals_hold_every_row(spark, sf_dir):
    x = np.array(read(sf_dir, "embeddings").sort_values("vec_id").embedding.tolist(), dtype=float)
    got = tables.QUERIES["gram_poly"](spark, sf_dir).toPandas()
    assert len(got) == len(x) ** 2
    assert np.allclose(got.v, ((x @ x.T + 1) ** 2)[got.i, got.j], atol=2e-6)
    lo = read(sf_dir, "orders").o_orderkey.to_numpy()
    events = set(read(sf_dir, "events").event_id)
    want = {(e, k) for k in lo for e in range(k * 7 % 9000, k * 7 % 9000 + 3) if e in events}
    rows = tables.QUERIES["interval_events"](spark, sf_dir).collect()
    assert len(rows) == len(want) and {(r.event_id, r.span) for r in rows} == want


@pytest.mark.parametrize("empty", ["skip", "origin", "reseed"])
def test_fits_label_every_row(spark, sf_dir, empty):
    """The lift's labels against sweeps over all of K."""
    p = points.line4(spark, sf_dir)
    x = np.array([r.x for r in sorted(p.select("idx", "x").collect())])
    k = (x @ x.T + 1) ** 2
    cl = np.arange(len(x)) % 64
    for _ in range(12):
        member = np.zeros((64, len(x)))
        member[cl, np.arange(len(x))] = 1
        sizes = member.sum(axis=1)
        e = member @ k / np.maximum(sizes, 1)[:, None]
        norms = (e * member).sum(axis=1) / np.maximum(sizes, 1)
        d = norms[:, None] - 2 * e
        d[sizes == 0] = 0.0 if empty == "origin" else np.inf
        cl = d.argmin(axis=0)
        if empty == "reseed":
            cl = engines.reseed(cl, d.min(axis=0) + k.diagonal(), 64)
    got = {r.idx: r.cl for r in tables.QUERIES[f"empty_{empty}"](spark, sf_dir).collect()}
    assert [got[i] for i in range(len(x))] == cl.tolist()


def test_lift_reseeds_as_the_engines(spark):
    x = np.repeat(np.random.Generator(np.random.PCG64(3)).normal(size=(6, 3)), 3, axis=0)
    p = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "idx long, x array<double>")
    loop = LoopSpec(max_iter=3, empty="reseed")
    assert baselines.lift(p, 8, polynomial(), loop).labels.tolist() == engines.fit(p, 8, polynomial(), loop=loop).labels.tolist()
