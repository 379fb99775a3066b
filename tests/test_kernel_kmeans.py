"""Worked example, engine equality, brute force, invariants, costs, traffic and plans."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from kernmill.functions import metrics, points
from kernmill.functions.kernels import KernelSpec, cosine, linear, polynomial, rbf
from kernmill.operators import baselines, engines, gram, model, sweep
from kernmill.plans import costs, planner
from kernmill.plans.layout import GridSpec, LoopSpec, StoreSpec, from_blocks, to_blocks
from kernmill.sqlapi import cluster_small, register

SETTINGS = [
    ("panel_1d", {}, {}, {}), ("regrid_h1d", {}, {}, {}), ("tile_2d", {}, {}, {}), ("mixed_15d", {}, {}, {}), ("mixed_15d", {"split": "clusters"}, {}, {}), ("mixed_15d", {"copy_v": "row_join"}, {}, {}),
    ("mixed_15d", {"copy_v": "diagonal", "v": "sparse"}, {"symmetric": True}, {}), ("mixed_15d", {}, {"dtype": "f32"}, {}), ("window", {}, {}, {"height": 7}), ("window", {}, {}, {"height": 1000, "distributed": True}), ("local", {}, {}, {}),
]


def data(n=53, d=4, seed=1):
    return np.random.Generator(np.random.PCG64(seed)).normal(size=(n, d))


def frame(spark, x):
    return spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "idx long, x array<double>")


def test_worked_example(spark):
    p = points.mini(spark)
    k, labels = gram.entries(p, polynomial()), sweep.round_robin(p, 2)
    e = sweep.cluster_means(k, labels)
    assert {(r.i, r.cl): r.e for r in e.collect()} == {(0, 0): 2, (0, 1): 5, (1, 0): 5, (1, 1): 17, (2, 0): 2, (2, 1): 5, (3, 0): 5, (3, 1): 17}
    assert {r.cl: r.c for r in sweep.centroid_norms(sweep.own_cluster_mean(e, labels)).collect()} == {0: 2, 1: 17}
    got = engines.fit(p, 2)
    assert got.labels.tolist() == [0, 1, 0, 1] and got.history[0][2] == 20
    flat = engines.fit(p, 2, linear())
    assert flat.labels.tolist() == [0, 0, 0, 0] and flat.history[0][2] == 10


@pytest.mark.parametrize(("engine", "loop", "store", "options"), SETTINGS)
@pytest.mark.parametrize("g", [1, 3])
def test_engines_agree(spark, engine, loop, store, options, g):
    x = data()
    want = cluster_small(x, 5, polynomial(), 6)
    got = engines.fit(frame(spark, x), 5, engine=engine, g=g, loop=LoopSpec(max_iter=6, **loop), store=StoreSpec(**store), **options)
    assert got.labels.tolist() == want.tolist()
    falls = [h[2] for h in got.history]
    assert all(b <= a * (1 + 1e-6) + 1e-6 for a, b in zip(falls, falls[1:]))


def test_scores_are_centroid_distances(spark):
    x = data(20, 3)
    lifted = baselines.quadratic_lift(x, polynomial(2.0, 0.5))
    assert np.allclose(lifted @ lifted.T, (2 * x @ x.T + 0.5) ** 2)
    labels = np.arange(20) % 4
    centres = np.stack([lifted[labels == c].mean(axis=0) for c in range(4)])
    p = frame(spark, x)
    k = gram.entries(p, polynomial(2.0, 0.5))
    ell = sweep.round_robin(p, 4)
    e = sweep.cluster_means(k, ell)
    sq = sweep.sq_distances(sweep.scores(e, sweep.centroid_norms(sweep.own_cluster_mean(e, ell))), k.where("i = j"))
    for r in sq.collect():
        assert abs(r.sq - ((lifted[r.i] - centres[r.cl]) ** 2).sum()) < 1e-9


def test_membership_invariants(spark):
    labels = sweep.round_robin(frame(spark, data()), 5)
    t = sweep.triplets(labels)
    assert t.count() == 53 and t.select("idx").distinct().count() == 53
    assert all(abs(r.s - 1) < 1e-12 for r in t.groupBy("cl").agg(F.sum("w").alias("s")).collect())


MEASURED = {  # n = 52, d = 4, k = 5, two sweeps on a grid of 2 x 2
    "panel_1d": {("kernel", "points"): 4 * 52 * 4},
    "regrid_h1d": {("kernel", "points"): 2 * 2 * 52 * 4, ("kernel", "regrid"): 52 * 52},
    "tile_2d": {("kernel", "points"): 2 * 2 * 52 * 4, ("sweep", "pieces"): 2 * 2 * 52 * 5, ("sweep", "minimum_pairs"): 2 * (2 * (52 + 52 // 2) + 4 * 5)},
    "mixed_15d": {("kernel", "points"): 2 * 2 * 52 * 4, ("sweep", "pieces"): 2 * 2 * 52 * 5},
}


@pytest.mark.parametrize("engine", list(MEASURED))
@pytest.mark.parametrize("barrier", [False, True])
def test_traffic_read_from_the_plans(spark, engine, barrier):
    """Words that passed the exchanges of the executed plans: a stray shuffle of K, 2,704 words, would show."""
    got = engines.fit(frame(spark, data(52)), 5, engine=engine, g=2, loop=LoopSpec(max_iter=2, fixed=True, barrier=barrier))
    want = MEASURED[engine] | {("sweep", "labels"): 2 * 4 * 52, ("sweep", "norms_sizes"): 2 * 2 * 4 * 5}
    assert {(s, i): w for s, i, w, _ in got.traffic} == want


@pytest.mark.parametrize("engine", ["mixed_15d", "tile_2d", "panel_1d"])
@pytest.mark.parametrize("symmetric", [False, True])
def test_tiles_are_made_where_they_stay(spark, engine, symmetric):
    """The product is the last step before the cache: no exchange carries K."""
    run = engines.make(engine, frame(spark, data()), 5, polynomial(), GridSpec(53, 2), LoopSpec(), StoreSpec(symmetric=symmetric), 4)
    run.prepare()
    plan = run.held[0]._jdf.queryExecution().executedPlan().toString()
    cached = plan[plan.index("InMemoryRelation") :]
    assert "MapInArrow" in cached and "Exchange" not in cached[: cached.index("MapInArrow")]
    assert run.held[0].rdd.getNumPartitions() == gram.tile_count(GridSpec(53, 2), StoreSpec(symmetric=symmetric and engine != "panel_1d"))
    run.close()


def test_barrier_and_two_passes_agree(spark):
    x = frame(spark, data())
    for engine in ("panel_1d", "tile_2d", "mixed_15d", "fused"):
        one, two = (engines.fit(x, 5, engine=engine, loop=LoopSpec(max_iter=4, barrier=b)) for b in (True, False))
        assert one.labels.tolist() == two.labels.tolist() and one.history[-1][2] == two.history[-1][2]


def test_strips_bound_the_cells(monkeypatch):
    assert [k.shape for *_, k in gram.products(_placed_batches(), polynomial(), StoreSpec(), 3)] == [(3, 4), (1, 4)]
    monkeypatch.setattr(gram, "STRIP_BYTES", 8 * 4 * 2)
    assert [k.shape for *_, k in gram.products(_placed_batches(), polynomial(), StoreSpec())] == [(2, 4), (2, 4)]


def _placed_batches():
    import pyarrow as pa

    for side in (0, 1):
        values = [(0, pa.int32()), (side, pa.int32()), (0, pa.int32()), (0, pa.int64()), (4, pa.int32())]
        yield pa.RecordBatch.from_arrays([*[pa.array([v], t) for v, t in values], gram.cell(data(4))], ["rank", "side", "blk", "lo", "cnt", "data"])


def test_resume_from_labels(spark, tmp_path):
    x = frame(spark, data())
    keep = {"fixed": True, "checkpoint": str(tmp_path / "labels"), "checkpoint_every": 2}
    engines.fit(x, 5, loop=LoopSpec(max_iter=4, **keep))
    (tmp_path / "labels" / "sweep=6").mkdir()  # never finished: no _SUCCESS
    again = engines.fit(x, 5, loop=LoopSpec(max_iter=5, resume=True, **keep))
    assert [h[0] for h in again.history] == [5]
    assert again.labels.tolist() == engines.fit(x, 5, loop=LoopSpec(max_iter=5, fixed=True)).labels.tolist()


def test_piece_owners():
    grid = GridSpec(4, 2)
    assert [grid.wide(i) for i in range(2)] == [(0, 2), (2, 4)]
    assert [[grid.owner(j, piece) for piece in range(2)] for j in range(2)] == [[0, 1], [2, 3]]
    assert grid.rank(1, 0) == 1 and grid.row_blocks(1) == [2, 3]
    with pytest.raises(ValueError):
        GridSpec.of_workers(10, 5)


def test_sweep_has_one_shuffle(spark):
    run = engines.make("mixed_15d", frame(spark, data()), 5, polynomial(), GridSpec(53, 2), LoopSpec(), StoreSpec(), 4)
    run.prepare()
    labels = (np.arange(53) % 5).astype(np.int32)
    source, to_e = run.means(labels, np.bincount(labels))
    plan = source._jdf.queryExecution().executedPlan().toString()
    assert plan.split("InMemoryTableScan")[0].count("Exchange") == 1
    run.close()


def test_cost_table(spark):
    par = spark.createDataFrame([(1_536_000, 784, 64, 256)], "n long, d long, k long, p long")
    rows = {r.algo: r for r in costs.table(par).collect()}
    assert rows["1d"].kernel_words == 256 * 1_536_000 * 784 and rows["1d"].sweep_words == 1_536_000
    assert rows["1.5d"].kernel_words == 75_264_000 and rows["1.5d"].sweep_words == 6_240_000
    assert rows["h1d"].kernel_words == 9.216e9 + 75_264_000 and rows["2d"].sweep_words == 7_776_000
    assert costs.crossover(spark, [16]).first().workers == 289
    fits = {r.algo: r.feasible for r in costs.feasible(par, 80e9, workspace=1.1).collect()}
    assert fits == {"1d": True, "h1d": False, "2d": True, "1.5d": True}


def test_policies(spark):
    x = np.repeat(data(6), 3, axis=0)
    p = frame(spark, x)
    start = np.array([0, 0, 0, 1, 1, 1] * 3)
    with pytest.raises(ValueError, match="empty"):
        engines.fit(p, 4, loop=LoopSpec(empty="error"), init=start)
    assert set(engines.fit(p, 4, loop=LoopSpec(max_iter=1), init=start).labels) <= {0, 1}
    assert len(set(engines.fit(p, 4, loop=LoopSpec(max_iter=1, empty="reseed"), init=start).labels)) == 4
    assert engines.reseed(np.array([0, 0, 0]), np.array([1.0, 5.0, 5.0]), 2).tolist() == [0, 1, 0]


@pytest.mark.parametrize("rows", [[(0, [1.0]), (1, [float("nan")])], [(0, [1.0]), (1, [1.0, 2.0])], [(0, None), (1, [1.0])], [(0, [1.0]), (0, [2.0])], [(0, [float("inf")])], []])
def test_bad_points_raise(spark, rows):
    p = spark.createDataFrame(rows, "idx long, x array<double>")
    with pytest.raises(ValueError):
        engines.fit(p, 1)


def test_bounds_of_k(spark):
    p = frame(spark, data(3))
    for k in (0, 4):
        with pytest.raises(ValueError, match="k must"):
            engines.fit(p, k)
    assert engines.fit(p, 1).labels.tolist() == [0, 0, 0]
    assert engines.fit(frame(spark, data(1)), 1).labels.tolist() == [0]


def test_baselines(spark):
    x = data(40)
    p = frame(spark, x)
    assert baselines.lloyd(p, 4).labels.tolist() == engines.fit(p, 4, linear()).labels.tolist()
    assert baselines.lift(p, 4).labels.tolist() == engines.fit(p, 4).labels.tolist()
    whole = baselines.landmark(p, 4, m=40)
    assert (whole.labels == engines.fit(p, 4).labels).mean() == 1
    with pytest.raises(ValueError):
        baselines.lift(p, 4, rbf(1.0))


def test_kernel_forms_agree(spark):
    x = data(9)
    p = frame(spark, x)
    nn = (x * x).sum(axis=1)
    for spec in (linear(), polynomial(0.5, 2.0, 3), rbf(0.7), cosine(), KernelSpec("sigmoid", 0.3, 0.1)):
        block = spec.block(x @ x.T, nn, nn)
        assert all(abs(r.v - block[r.i, r.j]) < 1e-12 for r in gram.entries(p, spec).collect())


def test_planner():
    assert planner.choose(10**9, 64, 10, 4, linear()).engine == "lloyd"
    assert planner.choose(10**9, 64, 10, 4, polynomial()).engine == "lift"
    assert planner.choose(10**5, 64, 10, 4, rbf()).engine == "mixed_15d"
    assert planner.choose(2 * 10**7, 100, 16, 100, rbf()).engine == "fused"  # refuses no number of points
    with pytest.raises(ValueError):
        planner.choose(10**11, 64, 10, 4, rbf())
    assert not planner.choose(10**11, 64, 10, 4, rbf(), allow_approx=True).exact


def test_kernel_beats_lines_on_lobes(spark, sf_dir):
    p = points.lobes(spark, sf_dir)

    def score(kernel):
        return metrics.ari(metrics.contingency(engines.fit(p, 2, kernel).labels_df(), p)).first().ari

    assert score(polynomial()) > 0.9 > 0.3 > score(linear())


def test_model_round_trip(spark, tmp_path):
    x = data(60)
    p = frame(spark, x[:50])
    fitted, result = model.fit(p, 4, engine="mixed_15d")
    same = {r.idx: r.cl for r in fitted.assign(p).collect()}
    assert result.history[-1][1] == 0 and [same[i] for i in range(50)] == result.labels.tolist()
    fitted.save(str(tmp_path / "m"))
    again = model.KernelClusterModel.load(spark, str(tmp_path / "m"))
    q = frame(spark, x[50:])
    assert again.assign(q).collect() == fitted.assign(q).collect()


def test_scoring_by_blocks_equals_scoring_by_copies(spark, monkeypatch):
    p, q = frame(spark, data(40)), frame(spark, data(25, seed=2))
    fitted, result = model.fit(p, 4, rbf(0.5), "mixed_15d", LoopSpec(max_iter=3))
    assert result.final
    want = {r.idx: (r.cl, round(r.sq_distance, 9)) for r in fitted.assign(q).collect()}
    fitted.copy_bytes = 0
    monkeypatch.setattr(model, "QUERY_BLOCK", 7)
    assert {r.idx: (r.cl, round(r.sq_distance, 9)) for r in fitted.assign(q).collect()} == want
    with pytest.raises(ValueError, match="k means"):
        fitted.scorer("idx")


@pytest.mark.parametrize("engine", ["lloyd", "lift", "landmark"])
def test_models_of_means(spark, tmp_path, engine):
    p = frame(spark, data(40))
    fitted, result = model.fit(p, 4, polynomial(), engine)
    fitted.save(str(tmp_path / engine))
    again = model.MeansModel.load(spark, str(tmp_path / engine)).assign(p)
    assert [r.cl for r in sorted(again.collect())] == result.labels.tolist()


@pytest.mark.parametrize("empty", ["skip", "origin", "reseed"])
def test_means_without_kept_labels(spark, monkeypatch, empty):
    """Labels made anew in every scan, sums over more tasks than one: as the kernel engines."""
    monkeypatch.setattr(baselines, "FANIN", 1)
    p = frame(spark, data()).repartition(3)
    loop = LoopSpec(max_iter=5, empty=empty)
    one, other = baselines.lift(p, 9, loop=loop), engines.fit(p, 9, loop=loop)
    assert one.labels.tolist() == other.labels.tolist()
    assert [h[1] for h in one.history] == [h[1] for h in other.history]
    assert np.allclose([h[2] for h in one.history], [h[2] for h in other.history])


def test_one_task_window_refuses_what_does_not_fit(spark):
    with pytest.raises(ValueError, match="fused"):
        engines.fit(frame(spark, data()), 5, engine="window", limit=100)


def test_shared_folder_is_asked_for_on_a_cluster():
    from types import SimpleNamespace

    from kernmill.sources import store

    cluster = SimpleNamespace(conf=SimpleNamespace(get=lambda *a: None), sparkContext=SimpleNamespace(master="spark://host:7077"))
    with pytest.raises(ValueError, match="share"):
        store.shared_dir(cluster)


def test_blocks_round_trip(spark):
    x = data(10)
    got = {r.idx: r.x for r in from_blocks(to_blocks(frame(spark, x), 3)).collect()}
    assert all(got[i] == x[i].tolist() for i in range(10))


def test_dense_index_over_ranges(spark):
    df = spark.range(100).select((F.col("id") * 7 % 101).alias("v"))
    rows = points.dense_index(df, ["v"], partitions=5).orderBy("v").collect()
    assert [r.idx for r in rows] == list(range(100))


def test_sql_functions(spark):
    register(spark)
    frame(spark, data(12)).createOrReplaceTempView("pts")
    got = spark.sql("SELECT * FROM kernel_clusters(TABLE(pts) WITH SINGLE PARTITION, 3, 'poly', 1.0D, 1.0D, 2)").collect()
    assert [r.cl for r in sorted(got)] == cluster_small(data(12), 3, polynomial()).tolist()
    assert spark.sql("SELECT kernel_value(array(1.0D, 2.0D), array(3.0D, 4.0D), 'poly', 1.0D, 1.0D, 2) AS v").first().v == 144
    assert np.allclose(spark.sql("SELECT vec_sum(x) AS s FROM pts").first().s, data(12).sum(axis=0))


def test_start_by_seeds(spark):
    got = engines.plusplus(frame(spark, data(30)), 5, polynomial(), 30, 2)
    assert len(set(got.tolist())) == 5
