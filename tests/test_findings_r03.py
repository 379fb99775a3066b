"""Findings of the third review: fits that end when their labels settle."""

import duckdb
import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from kernmill.functions import points
from kernmill.functions.kernels import linear, polynomial
from kernmill.operators import engines, gram, moments, sweep
from kernmill.plans.layout import LoopSpec, StoreSpec, packed, to_blocks, unpacked
from kernmill.sqlapi import cluster_small
from kernmill.workloads import oracles, tables

from .test_kernel_kmeans import data, frame


def settles(spark, path, name, source, kernel, before, seed):
    """On customers whose labels still move after ``before`` sweeps: labels that another sweep leaves alone, the same in SQL."""
    rng = np.random.default_rng(seed)
    pq.write_table(pa.table({"c_custkey": np.sort(rng.choice(2000, 240, replace=False)), "c_acctbal": rng.uniform(-999, 9999, 240).round(2)}), path / "customer.parquet")
    x = np.array([r.x for r in sorted(source(spark, str(path)).select("idx", "x").collect())])
    want = cluster_small(x, 2, kernel, 1000).tolist()
    assert want == cluster_small(x, 2, kernel, 1001).tolist() != cluster_small(x, 2, kernel, before).tolist()
    got = {r.idx: r.cl for r in tables.QUERIES[name](spark, str(path)).collect()}
    assert [got[i] for i in range(len(x))] == want
    con = duckdb.connect()
    con.sql(f"CREATE VIEW customer AS SELECT * FROM read_parquet('{path}/customer.parquet')")
    assert dict(con.sql(oracles.ORACLES[name]).fetchall()) == got


def test_lobes_linear_settles(spark, tmp_path):
    settles(spark, tmp_path, "lobes_linear", points.lobes, linear(), 2, 8)


def test_rings_poly_settles(spark, tmp_path):
    settles(spark, tmp_path, "rings_poly", points.rings, polynomial(), 6, 6)


def test_labels_that_come_back_end_a_fit(spark, monkeypatch):
    """Without a limit of sweeps; a fixed number of sweeps needs one."""
    calls, sweep_of = [], engines.Engine.sweep

    def turned(self, labels, sizes):
        calls.append(len(calls))
        return (1 - labels, *sweep_of(self, labels, sizes)[1:])

    monkeypatch.setattr(engines.Engine, "sweep", turned)
    engines.fit(frame(spark, data(12)), 2, linear(), loop=LoopSpec(max_iter=None))
    assert len(calls) == 3
    with pytest.raises(ValueError):
        LoopSpec(max_iter=None, fixed=True)


def test_entries_meet_as_blocks(spark, monkeypatch):
    """Values of whole blocks, not a lambda a pair; labels come to the entries, which do not move. Any idx, null vectors and null values as ever."""
    monkeypatch.setattr(gram, "ENTRY_SIDE", 3)
    monkeypatch.setattr(gram, "ENTRY_ROWS", 4)
    x = [[float(v) for v in r] for r in data(11, 3)]
    x[2], x[5] = None, [1.0, None, 2.0]
    p = spark.createDataFrame([(7 * i - 9, v) for i, v in enumerate(x)], "idx long, x array<double>")
    got = gram.entries(p, polynomial(2.0, 0.5))
    rows = {(r.i, r.j): r.v for r in got.collect()}
    assert len(rows) == got.count() == 121
    for i, a in enumerate(x):
        for j, b in enumerate(x):
            v = rows[7 * i - 9, 7 * j - 9]
            assert v is None if {i, j} & {2, 5} else np.isclose(v, (2 * np.dot(a, b) + 0.5) ** 2)
    assert gram.entries(p.where("idx > 1000"), linear()).count() == 0
    plan = sweep.cluster_means(got, sweep.round_robin(p, 2))._jdf.queryExecution().sparkPlan().toString()
    assert "BroadcastHashJoin" in plan and "zip_with" not in plan and "NestedLoop" not in plan


def test_documents_go_thin_to_the_tiles(spark, sf_dir, monkeypatch):
    """Bags of words without an exchange of tokens; blocks of them packed and compressed; their dense vectors are neither cached nor moved, and no files stay once the tiles have them."""
    monkeypatch.setattr(StoreSpec, "keeps", lambda self, n: False)
    seen = []

    def first(self, labels, sizes):
        (held,) = self.held
        seen.append(([e.shuffleDependency().shuffleId() for e in engines.meter._found(held.select("rank"), True)], self.grid.g, self.points.is_cached, held.agg({"cnt": "sum"}).first()[0], sum(len(r.data) for r in held.collect())))
        return sweep_of(self, labels, sizes)

    sweep_of = engines.Engine.sweep
    monkeypatch.setattr(engines.Engine, "sweep", first)
    monkeypatch.setattr(engines, "TILE_SIDE", 16)
    monkeypatch.setattr(engines, "SIDE_BYTES", 1 << 14)
    got = tables.QUERIES["docbag_fit_k4"](spark, sf_dir)
    x = np.array([r.x for r in sorted(points.docbag(spark, sf_dir).select("idx", "x").collect())])
    assert [r.cl for r in got.orderBy("idx").collect()] == cluster_small(x, 4, polynomial(), 9).tolist()
    ids, g, cached, rows, held = seen[0]
    tracker = spark.sparkContext._jsc.sc().env().mapOutputTracker()
    assert ids and not any(tracker.getNumAvailableOutputs(i) for i in ids)
    assert not cached and rows == 2 * g * len(x) and held < rows * 8 * (x != 0).sum() / len(x)


def test_wide_sides_for_moments(spark):
    """What a task holds is not its points, so wide points need no more tiles than narrow ones."""
    with pytest.MonkeyPatch.context() as patch:
        made, make = [], engines.make
        patch.setattr(engines, "make", lambda *args, **more: made.append(args[4].g) or make(*args, **more))
        patch.setattr(engines, "TILE_SIDE", 1)
        patch.setattr(engines, "SIDE_BYTES", 32 * 2 * 40)
        for engine, store in (("mixed_15d", {}), ("tile_2d", {}), ("mixed_15d", {"symmetric": True})):
            engines.fit(frame(spark, data(80, 40)), 2, engine=engine, loop=LoopSpec(max_iter=1), store=StoreSpec(keep_bytes=0, **store))
    assert made[:2] == [2, 2] and made[2] > 2


def test_forms_of_wide_rows():
    y, m = data(7, 700), data(700, 700, 4)
    m = m + m.T
    assert np.allclose(moments.forms(y, m), [r @ m @ r for r in y])


def test_blocks_of_scattered_points(spark):
    """Points that lie in no order come to their blocks in order."""
    x = np.where(np.random.default_rng(2).random((50, 40)) < 0.1, data(50, 40), 0.0)
    p = frame(spark, x).orderBy(points.F.md5(points.F.col("idx").cast("string")))
    got = {r.lo: unpacked(r.data, r.cnt) for r in to_blocks(p, 20, 8).collect()}
    assert {lo: len(v) for lo, v in got.items()} == {0: 8, 8: 8, 16: 4, 20: 8, 28: 8, 36: 4, 40: 8, 48: 2}
    assert all(np.array_equal(v, x[lo : lo + len(v)]) for lo, v in got.items())
    wide = np.zeros((2, 70_000))
    wide[1, 69_999] = 2.0
    assert np.array_equal(unpacked(packed(wide), 2), wide)


def test_window_seconds_takes_all_documents(spark, tmp_path, monkeypatch):
    """More than the 1,000 that it drew."""
    pq.write_table(pa.table({"doc_id": np.arange(1005), "text": [f"word{chr(97 + i % 26)} and more" for i in range(1005)], "lang": ["en"] * 1005}), tmp_path / "documents.parquet")
    monkeypatch.setattr(tables.experiments, "against_window", lambda spark, name, p, k, sweeps: p)
    got = tables.QUERIES["window_seconds"](spark, str(tmp_path))
    assert got.select("key").distinct().count() == 1005 and got.where("size(x) = 10000").count() == 1005
