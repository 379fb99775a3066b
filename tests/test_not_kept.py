"""K too large to keep: the same labels, traffic and members from the points alone."""

import numpy as np
import pytest

from kernmill.functions.kernels import linear, polynomial, rbf
from kernmill.operators import engines, model, moments
from kernmill.plans.layout import LoopSpec, StoreSpec, packed, unpacked
from kernmill.sqlapi import cluster_small

from .test_kernel_kmeans import data, frame


@pytest.fixture(autouse=True)
def small_chunks(monkeypatch):
    monkeypatch.setattr(engines, "TILE_SIDE", 5)
    monkeypatch.setattr(engines, "CHUNK_BYTES", 1)


CASES = [("panel_1d", {}, {}, {}), ("regrid_h1d", {}, {}, {}), ("tile_2d", {}, {}, {}), ("mixed_15d", {}, {}, {}), ("mixed_15d", {"split": "clusters"}, {}, {}), ("mixed_15d", {"copy_v": "row_join"}, {}, {}), ("mixed_15d", {"copy_v": "diagonal", "v": "sparse"}, {"symmetric": True}, {}), ("mixed_15d", {}, {"dtype": "f32acc64"}, {}), ("window", {}, {}, {"distributed": True})]


@pytest.mark.parametrize(("engine", "loop", "store", "options"), CASES)
def test_labels_without_k(spark, tmp_path, engine, loop, store, options):
    kernel = rbf(0.5) if engine == "tile_2d" else polynomial(2.0, 0.5)
    x = data(700, 3)
    more = options | ({"on_disk": str(tmp_path / "tiles")} if engine == "window" else {})
    got = engines.fit(frame(spark, x), 5, kernel, engine, 2, LoopSpec(max_iter=3, **loop), StoreSpec(keep_bytes=0, **store), **more)
    assert got.labels.tolist() == cluster_small(x, 5, kernel, 3).tolist()
    assert not (tmp_path / "tiles").exists()
    assert not any(item in ("regrid", "written", "read") for _, item, _, _ in got.traffic)


def test_limit_is_of_all_values():
    assert StoreSpec().keeps(8192) and not StoreSpec().keeps(8193) and StoreSpec("f32").keeps(11_000)


def test_sums_of_labels_without_members():
    x, y, cl = data(9, 3), data(4, 3, 2), np.array([0, 2, 2, 0, 2, 0, 0, 2, 2])
    for kernel in (polynomial(2.0, 0.5), linear(), rbf(0.5)):
        got = moments.summer(3, 3, kernel, StoreSpec(), "dense")
        got.add(x[:5], cl[:5])
        got.add(x[5:], cl[5:])
        k = np.array([[kernel.block(np.array([[a @ b]]), np.array([a @ a]), np.array([b @ b]))[0, 0] for b in y] for a in x])
        assert np.allclose(got.sums(y), [k[cl == c].sum(axis=0) for c in range(3)])


@pytest.mark.parametrize("kernel", [polynomial(), rbf(0.5)], ids=lambda k: k.name)
@pytest.mark.parametrize("copy_bytes", [1 << 28, 1])
def test_members_are_those_of_the_fit(spark, kernel, copy_bytes):
    """One sweep leaves points nearer to another centre than their own."""
    x = data(60, 3)
    fitted, _ = model.fit(frame(spark, x), 4, kernel, "mixed_15d", LoopSpec(max_iter=1))
    fitted.copy_bytes = copy_bytes
    own = {r.idx: r.cl for r in fitted.labels.collect()}
    near = {r.idx: r.cl for r in fitted.assign(fitted.points).collect()}
    assert own != near and {r.idx: r.cl for r in fitted.members(60).collect()} == own


@pytest.mark.parametrize("store", [{}, {"symmetric": True}, {"dtype": "f32acc64"}])
def test_relay_in_rounds(spark, store):
    """All of K passes the exchange in every sweep, a slice of it at a time, whose files are gone after its round."""
    x, dropped, drop = data(70, 3), [], engines.meter.drop_files
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(engines.meter, "drop_files", lambda df: (drop(df), dropped.append(df)))
        got = engines.fit(frame(spark, x), 5, polynomial(2.0, 0.5), "regrid_h1d", 2, LoopSpec(max_iter=2, fixed=True), StoreSpec(keep_bytes=8 * 70 * 4 * 5, **store), relay=True)
    assert got.labels.tolist() == cluster_small(x, 5, polynomial(2.0, 0.5), 2).tolist()
    (words,) = [w for _, item, w, _ in got.traffic if item == "regrid"]
    assert words == 2 * 70 * 70 // (2 if store.get("dtype") else 1)
    assert len(dropped) == 2 * (4 if not store.get("dtype") else 2)
    tracker = spark.sparkContext._jsc.sc().env().mapOutputTracker()
    assert not any(tracker.getNumAvailableOutputs(e.shuffleDependency().shuffleId()) for df in dropped for e in engines.meter._found(df, True))


def test_workers_get_small_batches(spark, monkeypatch):
    """A fit runs with batches of BATCH_BYTES; the session's own setting is back afterwards, failed or not."""
    name, seen, prepare = "spark.sql.execution.arrow.maxBytesPerBatch", [], engines.Mixed.prepare
    monkeypatch.setattr(engines.Mixed, "prepare", lambda self: (seen.append(spark.conf.get(name)), prepare(self)))
    before = spark.conf.get(name, None)
    engines.fit(frame(spark, data(20, 3)), 2, loop=LoopSpec(max_iter=1), store=StoreSpec(keep_bytes=0))
    with pytest.raises(ValueError):
        engines.fit(frame(spark, data(20, 3)), 21)
    assert seen == [str(engines.BATCH_BYTES)] and spark.conf.get(name, None) == before


def test_blocks_of_zeros_are_short(spark):
    """The same points, in under half the bytes where most values are zero, and the same labels from them."""
    full, thin = data(90, 3), np.where(np.random.default_rng(1).random((90, 40)) < 0.1, data(90, 40), 0.0)
    thin[7] = 0.0
    for x in (full, thin, np.zeros((3, 5)), full[:1, :1]):
        assert np.array_equal(unpacked(packed(x), len(x)), x)
    assert len(packed(full)) == full.nbytes and 2 * len(packed(thin)) < thin.nbytes
    for engine in ("mixed_15d", "panel_1d"):
        got = engines.fit(frame(spark, thin), 4, polynomial(), engine, 2, LoopSpec(max_iter=2), StoreSpec(keep_bytes=0))
        assert got.labels.tolist() == cluster_small(thin, 4, polynomial(), 2).tolist()


@pytest.mark.parametrize("keep_bytes", [0, 1 << 29])
@pytest.mark.parametrize(("engine", "loop", "store", "shuffles"), [("mixed_15d", {}, {}, 1), ("mixed_15d", {"split": "clusters"}, {}, 2), ("mixed_15d", {"barrier": True}, {}, 1), ("mixed_15d", {}, {"symmetric": True}, 1), ("tile_2d", {}, {}, 2), ("window", {}, {}, 1), ("regrid_h1d", {}, {}, 0)])
def test_files_of_a_sweep_go_with_it(spark, tmp_path, engine, loop, store, shuffles, keep_bytes):
    """Before a sweep nothing is left of the shuffles of those before; labels and traffic are as ever."""
    x, ids, shuffled = data(70, 3), [], engines.meter.shuffles
    tracker = spark.sparkContext._jsc.sc().env().mapOutputTracker()

    def seen(df, into_cache=False):
        found = list(engines.meter._found(df, into_cache))
        if sweeping:
            ids.extend(e.shuffleDependency().shuffleId() for e in found)
        return shuffled(df, into_cache)

    sweeping, left, sweep_of = [], [], engines.Engine.sweep

    def one(self, labels, sizes):
        left.append([i for i in ids if tracker.getNumAvailableOutputs(i)])
        sweeping.append(True)
        out = sweep_of(self, labels, sizes)
        sweeping.clear()
        return out

    more = {"distributed": True, "on_disk": str(tmp_path / "tiles")} if engine == "window" else {}
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(engines.meter, "shuffles", seen)
        patch.setattr(engines.Engine, "sweep", one)
        got = engines.fit(frame(spark, x), 5, polynomial(2.0, 0.5), engine, 2, LoopSpec(max_iter=3, fixed=True, **loop), StoreSpec(keep_bytes=keep_bytes, **store), **more)
    assert got.labels.tolist() == cluster_small(x, 5, polynomial(2.0, 0.5), 3).tolist()
    assert len(set(ids)) == 3 * shuffles and left == [[], [], []] and not any(tracker.getNumAvailableOutputs(i) for i in ids)
