"""Registered queries: each a callable of (spark, sf_dir)."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import experiments, sqlapi
from ..functions import metrics, points
from ..functions.kernels import KernelSpec, cosine, dot, linear, polynomial, rbf, sigmoid
from ..operators import baselines, engines, gram, model, sweep
from ..plans import costs
from ..plans.layout import GridSpec, LoopSpec, StoreSpec, to_blocks
from ..sources.store import materialize, shared_dir, table
from ..streaming import streams
from .oracles import GRID, RUNS, SETS

POLY = polynomial()


def r6(c: Column | str) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, 6) + F.lit(0.0)


def _entries(spark, sf_dir, kernel: KernelSpec = POLY) -> DataFrame:
    return gram.entries(points.emb(spark, sf_dir), kernel)


def _start(spark, sf_dir, k: int = 10) -> tuple[DataFrame, DataFrame]:
    p = points.emb(spark, sf_dir)
    return gram.entries(p, POLY), sweep.round_robin(p, k)


def fit_labels(source, k: int, kernel: KernelSpec = POLY, engine: str = "mixed_15d", max_iter: int | None = 100, loop: dict | None = None, store: dict | None = None, **options):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        got = engines.fit(source(spark, sf_dir), k, kernel, engine, loop=LoopSpec(max_iter=max_iter, **(loop or {})), store=StoreSpec(**(store or {})), **options)
        return got.labels_df()

    return run


def whole_fit(source, k: int, loop: LoopSpec):
    """Labels of every row of the table by the exact lift, which never holds K."""
    return lambda spark, sf_dir: baselines.lift(source(spark, sf_dir), k, loop=loop).labels_df()


def emb_fit(engine: str = "mixed_15d", max_iter: int = 17, **options):
    return fit_labels(points.emb, 10, engine=engine, max_iter=max_iter, **options)


# --- kernel stage -------------------------------------------------------------


def gram_values(kernel: KernelSpec):
    return lambda spark, sf_dir: _entries(spark, sf_dir, kernel).select("i", "j", r6("v").alias("v"))


def gram_tiles_checksum(spark, sf_dir):
    p = points.emb(spark, sf_dir)
    grid, store = GridSpec(p.count(), 2), StoreSpec()

    def totals(batches):
        import pyarrow as pa

        for _, bi, bj, _, _, k in gram.products(batches, POLY, store):
            yield pa.RecordBatch.from_arrays([pa.array([bi], pa.int32()), pa.array([bj], pa.int32()), pa.array([k.size], pa.int64()), pa.array([float(k.sum())])], ["bi", "bj", "cells", "total"])

    strips = gram.placed(to_blocks(p, grid.step * grid.g), grid, store).mapInArrow(totals, "bi int, bj int, cells long, total double")
    return strips.groupBy("bi", "bj").agg(F.sum("cells").alias("cells"), r6(F.sum("total")).alias("total"))


def gram_symmetric_half(spark, sf_dir):
    """Row sums of K from the half build."""
    import numpy as np
    import pyarrow as pa

    p = points.emb(spark, sf_dir)
    grid, store = GridSpec(p.count(), 2), StoreSpec(symmetric=True)

    def sums(batches):
        for _, bi, bj, lo_i, lo_j, k in gram.products(batches, POLY, store):
            for lo, part in [(lo_i, k.sum(axis=1))] + ([(lo_j, k.sum(axis=0))] if bi != bj else []):
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(lo, lo + len(part))), pa.array(part)], ["i", "s"])

    at = gram.placed(to_blocks(p, grid.step * grid.g), grid, store)
    return at.mapInArrow(sums, "i long, s double").groupBy("i").agg(r6(F.sum("s")).alias("row_sum"))


def _diagonal(spark, sf_dir):
    nn = dot(F.col("x"), F.col("x"))
    return points.emb(spark, sf_dir).select(F.col("idx").alias("i"), nn.alias("nn")).select("i", POLY.column(F.col("nn"), F.col("nn"), F.col("nn")).alias("v"))


# --- one sweep ----------------------------------------------------------------


def sweep_step(name: str):
    def run(spark, sf_dir):
        k, labels = _start(spark, sf_dir)
        e = sweep.cluster_means(k, labels, transposed=name == "means_transposed")
        if name.startswith("means"):
            return e.select("i", "cl", r6("e").alias("e"))
        z = sweep.own_cluster_mean(e, labels)
        if name == "mask":
            return z.select("i", "cl", r6("z").alias("z"))
        c = sweep.centroid_norms(z)
        if name == "cnorm":
            return c.select("cl", r6("c").alias("c"))
        d = sweep.scores(e, c)
        if name == "scores":
            return d.select("i", "cl", r6("dist").alias("dist"))
        if name == "sqdist":
            return sweep.sq_distances(d, k.where("i = j")).select("i", "cl", r6("sq").alias("sq"))
        if name == "margin":
            by = Window.partitionBy("i").orderBy("dist", "cl")
            return d.select("i", "cl", (F.lead("dist").over(by) - F.col("dist")).alias("m"), F.row_number().over(by).alias("n")).where("n = 1").select("i", "cl", r6("m").alias("margin"))
        return sweep.nearest(d)

    return run


def sweep_objective(spark, sf_dir):
    k, labels = _start(spark, sf_dir)
    return sweep.objective(k, labels).select(r6("objective").alias("objective"))


def sizes_with_empties(spark, sf_dir):
    return sweep.sizes(baselines.lift(points.line4(spark, sf_dir), 64, loop=LoopSpec(max_iter=1)).labels_df(), 64)


def history(column: str):
    def run(spark, sf_dir):
        got = engines.fit(points.emb(spark, sf_dir), 10, loop=LoopSpec(max_iter=17, fixed=True)).history_df()
        return got.select("sweep", r6(column).alias(column) if column == "objective" else column)

    return run


def window_disk(spark, sf_dir):
    import uuid

    got = engines.fit(points.emb(spark, sf_dir), 10, engine="window", loop=LoopSpec(max_iter=17), height=150, distributed=True, on_disk=f"{shared_dir(spark)}/tiles-{uuid.uuid4().hex}")
    return got.labels_df()


# --- points -------------------------------------------------------------------


def spread(source, digits: int = 6):
    return lambda spark, sf_dir: source(spark, sf_dir).select("idx", F.posexplode("x").alias("pos", "v")).select("idx", (F.col("pos") + 1).alias("pos"), (F.round("v", digits) + F.lit(0.0)).alias("v"))


def docbag_points(spark, sf_dir):
    return points.docbag(spark, sf_dir).select("idx", F.posexplode("x").alias("pos", "v"), "truth").where("v > 0").select("idx", "pos", r6("v").alias("v"), "truth")


# --- scoring and measures -----------------------------------------------------


def assign_holdout(spark, sf_dir):
    rows = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    train = points.dense_index(rows.where("vec_id % 5 <> 0"), ["vec_id"]).select("idx", "x")
    fitted, _ = model.fit(train, 10, POLY, "mixed_15d", LoopSpec(max_iter=12))
    return fitted.assign(rows.where("vec_id % 5 = 0"), "vec_id").select("vec_id", "cl")


def _emb_model(spark, sf_dir, sweeps: int = 17):
    p = points.emb(spark, sf_dir)
    return model.fit(p, 10, POLY, "mixed_15d", LoopSpec(max_iter=sweeps))[0]


def nearest_members_topk(spark, sf_dir):
    return _emb_model(spark, sf_dir).members(3).select("cl", "rank", "idx", r6("sq_distance").alias("sq_distance"))


def _grid(spark, sf_dir=None):
    return spark.createDataFrame(GRID, "n long, d long, k long, p long")


def _event_sets(spark, sf_dir):
    """A set of points for each type of event, one dimension a user, at two k and three numbers of workers."""
    sets = table(spark, sf_dir, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.count_distinct("user_id").alias("d"))
    return sets.select("n", "d", F.explode(F.array(F.lit(16), F.lit(64)).cast("array<long>")).alias("k")).select("*", F.explode(F.array(F.lit(4), F.lit(64), F.lit(256)).cast("array<long>")).alias("p"))


def _event_counts(spark, sf_dir, name: str):
    """The different numbers of events that users have."""
    return table(spark, sf_dir, "events").groupBy("user_id").agg(F.count("*").alias(name)).select(name).distinct()


def cost_table(spark, sf_dir):
    got = costs.table(_event_sets(spark, sf_dir))
    return got.select("algo", "n", "d", "k", "p", *[F.round(c, 3).alias(c) for c in got.columns[5:]])


def grid_product_table(spark, sf_dir):
    got = costs.grid_product_square(_event_sets(spark, sf_dir))
    return got.select("n", "p", F.round("bound_words", 3).alias("bound_words"), F.round("grid_words", 3).alias("grid_words"), F.round("ratio", 9).alias("ratio"))


def traffic_mixed(spark, sf_dir):
    got = engines.fit(points.emb(spark, sf_dir), 10, g=2, loop=LoopSpec(max_iter=3, fixed=True))
    return got.traffic_df().select("stage", "item", "words")


def traffic_all(spark, sf_dir):
    rows = []
    for e in ("panel_1d", "regrid_h1d", "tile_2d", "mixed_15d"):
        options = {"relay": True} if e == "regrid_h1d" else {}  # its re-layout of K is what is measured
        got = engines.fit(points.emb(spark, sf_dir), 10, engine=e, g=2, loop=LoopSpec(max_iter=1, fixed=True), **options)
        rows += [(e, item, words) for _, item, words, _ in got.traffic]
    return spark.createDataFrame(rows, "engine string, item string, words long")


def balance(layout: str):
    def run(spark, sf_dir):
        p = points.emb(spark, sf_dir)
        labels = sweep.round_robin(p, 10)
        if layout == "2d":
            labels = engines.fit(p, 10, loop=LoopSpec(max_iter=1)).labels_df()
        return metrics.balance(labels, 10, 2, p.count(), layout).withColumn("ratio", F.round("ratio", 6))

    return run


def _runs(spark):
    return spark.createDataFrame(RUNS, "dataset string, k long, algo string, g long, stage string, seconds double")


def geo_mean_runs(spark, sf_dir):
    """Each event as a run: its type as the algorithm, 1 + value as the seconds."""
    runs = table(spark, sf_dir, "events").select(F.col("event_type").alias("algo"), (1 + F.col("value")).alias("seconds"))
    return metrics.geometric_mean(runs, "seconds", "algo").withColumn("geo_mean", F.round("geo_mean", 6))


def _user_totals(spark, sf_dir):
    """Points of one dimension: what a user's events add up to."""
    return points.userfeat(spark, sf_dir).select("idx", "key", F.slice("x", points.USER.index("total") + 1, 1).alias("x"))


def quality(source, k, kernel, sweeps, measure):
    def run(spark, sf_dir):
        p = source(spark, sf_dir)
        t = metrics.contingency(engines.fit(p, k, kernel, loop=LoopSpec(max_iter=sweeps)).labels_df(), p)
        if measure == "contingency":
            return t
        return getattr(metrics, measure)(t).select(r6(measure).alias(measure))

    return run


def agreement_engines(spark, sf_dir):
    p = points.emb(spark, sf_dir)
    one, other = (engines.fit(p, 10, engine=e, g=g).labels_df() for e, g in (("mixed_15d", 3), ("panel_1d", 2)))
    return metrics.agreement(one, other)


# --- utilities ----------------------------------------------------------------


def dense_index_lineitem(spark, sf_dir):
    rows = table(spark, sf_dir, "lineitem").select(*points.LINE_KEY)
    return points.dense_index(rows, points.LINE_KEY, partitions=8).select("idx", *points.LINE_KEY[:4])


def scaled(how):
    def run(spark, sf_dir):
        rows = how(table(spark, sf_dir, "lineitem").select("l_orderkey", *points.LINE4), points.LINE4)
        return rows.select("l_orderkey", *[r6(c).alias(c) for c in points.LINE4])

    return run


def onehot_flags(spark, sf_dir):
    flags = points.one_hot("l_returnflag", ["A", "N", "R"])
    return table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", *[f.alias(f"flag_{v}") for f, v in zip(flags, "anr")])


def sampled(spark, sf_dir):
    return points.sample_n(table(spark, sf_dir, "embeddings").select("vec_id"), 100, ["vec_id"], 3)


def anti_unsampled(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select("vec_id").join(sampled(spark, sf_dir), "vec_id", "left_anti")


def semi_changed(spark, sf_dir):
    k, before = _start(spark, sf_dir)
    after = sweep.sweep(k, before, 10)
    moved = after.join(before.withColumnRenamed("cl", "was"), "idx").where("cl <> was")
    return points.emb(spark, sf_dir).join(moved, "idx", "left_semi").select(F.col("key").alias("vec_id"))


def setops_labels(spark, sf_dir):
    k, before = _start(spark, sf_dir)
    return sweep.sweep(k, before, 10).exceptAll(before)


def asof_label_events(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    versions = e.where("event_type = 'signup'").select("user_id", F.col("ts").alias("since"), F.col("event_id").alias("version"))
    return model.latest_before(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), versions, "user_id", "ts", "since", "version").select("event_id", "version")


def interval_events(spark, sf_dir):
    spans = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("span"), (F.col("o_orderkey") * 7 % 9000).alias("lo"), (F.col("o_orderkey") * 7 % 9000 + 3).alias("hi"))
    return model.within(table(spark, sf_dir, "events").select("event_id"), spans, "event_id", "lo", "hi", 64).select("event_id", "span")


# --- streams ------------------------------------------------------------------


def _event_stream(spark, sf_dir):
    """All events as two files, given one at a time."""
    rows = table(spark, sf_dir, "events")
    path = materialize(rows.repartitionByRange(2, "ts")).inputFiles()[0].rsplit("/", 1)[0]
    return streams.source(spark, path)


def stream_windows(kind: str):
    def run(spark, sf_dir):
        got = streams.run_available(streams.windowed(_event_stream(spark, sf_dir), kind, "30 days"), "complete")
        by = "user_id" if kind == "session" else "event_type"
        return got.select(F.col("start").cast("timestamp_ntz").alias("start"), by, "n", F.round("total", 4).alias("total"))

    return run


def stream_dedup(spark, sf_dir):
    rows = table(spark, sf_dir, "events")
    path = materialize(rows.union(rows.where("event_id % 7 = 0")).repartitionByRange(2, "ts")).inputFiles()[0].rsplit("/", 1)[0]
    return streams.run_available(streams.without_repeats(streams.source(spark, path), "30 days").select("event_id", "user_id"))


def stream_assign(spark, sf_dir):
    """The stream's scoring is the last of 17 sweeps: a model of 16 gives each point its label of the 17th, settled or not."""
    fitted = _emb_model(spark, sf_dir, 16)
    path = materialize(points.emb(spark, sf_dir).select("idx", "x").repartition(2)).inputFiles()[0].rsplit("/", 1)[0]
    stream = streams.source(spark, path, "idx long, x array<double>")
    return streams.run_available(streams.score(stream, fitted)).select("idx", "cl")


def landmark_k10(spark, sf_dir):
    return baselines.landmark(points.emb(spark, sf_dir), 10, m=100).labels_df()


def spectral_rings(spark, sf_dir):
    p = points.rings(spark, sf_dir)
    return metrics.ari(metrics.contingency(baselines.spectral(p, 2, rbf(4.0)).labels_df(), p))


def plusplus_k10(spark, sf_dir):
    return engines.fit(points.emb(spark, sf_dir), 10, init="plusplus", seed=3).labels_df()


def docbag_wide_fit(spark, sf_dir):
    return engines.fit(points.docbag(spark, sf_dir, 10_000), 4, loop=LoopSpec(max_iter=7)).labels_df()


def window_heights(spark, sf_dir):
    """Labels per block height of the recomputing window: all alike."""
    p = points.emb(spark, sf_dir)
    out = None
    for b in (64, 128, 256, 512, 1024, 2048):
        part = engines.fit(p, 10, engine="window", loop=LoopSpec(max_iter=5), height=b).labels_df().withColumn("height", F.lit(b))
        out = part if out is None else out.union(part)
    return out


def _sets(spark, sf_dir):
    """Point sets of n points drawn by md5 order."""
    return {
        "vision": lambda n: points.sampled(points.emb(spark, sf_dir), n),
        "physics": lambda n: points.sampled(points.wide28(spark, sf_dir), n),
        "education": lambda n: points.sampled(points.docbag(spark, sf_dir), n),
    }


def scaling_runs(name: str, weak: bool):
    """Seconds and words of every engine, k in 16, 32, 64, grids of 1, 4 and 16 workers, on up to 500 points a grid side (strong: 2,000)."""

    def rows(spark, sf_dir) -> DataFrame:
        table_name, _, cap = SETS[name]
        held = table(spark, sf_dir, table_name).count()
        how = experiments.weak if weak else experiments.strong
        return how(spark, {name: _sets(spark, sf_dir)[name]}, min(cap, held // 4) if weak else min(4 * cap, held), sweeps=2)

    return rows


def scaling_words(name: str, weak: bool):
    def run(spark, sf_dir):
        got = scaling_runs(name, weak)(spark, sf_dir).where("stage <> 'update'")
        return got.select("dataset", "k", "algo", "g", "n", F.when(F.col("stage") == "kernel", "kernel").otherwise("sweep").alias("stage"), "words")

    return run


def stage_breakdown(spark, sf_dir):
    """Seconds and words of K, means and update at k = 64 on four workers, for every set."""
    out = None
    for name, (table_name, _, cap) in SETS.items():
        n = min(4 * cap, table(spark, sf_dir, table_name).count())
        part = experiments.strong(spark, {name: _sets(spark, sf_dir)[name]}, n, ks=(64,), grids=(2,), sweeps=2)
        out = part if out is None else out.unionByName(part)
    return out


def _wide_bags(spark, sf_dir):
    return points.docbag(spark, sf_dir, 10_000, drawn=1000).select("idx", "key", "x")


def window_comparison(spark, sf_dir):
    """Labels of the recomputing window against the mixed layout, on the widest set: all alike."""
    p = materialize(_wide_bags(spark, sf_dir))
    n, loop = p.count(), LoopSpec(max_iter=3, fixed=True)
    want = engines.fit(p, 16, loop=loop).labels
    settings = [("mixed_15d", "mixed_15d", {}), *[(f"window_{b}", "window", {"height": b}) for b in (256, 512, 1024)], ("fused", "fused", {})]
    rows = [("education", name, n, float((engines.fit(p, 16, engine=e, loop=loop, **o).labels == want).mean())) for name, e, o in settings]
    return spark.createDataFrame(rows, "dataset string, algo string, n long, agreement double")


def window_seconds(spark, sf_dir):
    """Seconds of both on the widest set, all documents, by stage."""
    return experiments.against_window(spark, "education", points.docbag(spark, sf_dir, 10_000), 16, sweeps=3)


def stationary_table(spark, sf_dir):
    """Words of a sweep by the operand that stays, and of K held c-fold by a cube layout."""
    got = _grid(spark)
    kinds = [costs.stationary(kind).alias(f"still_{kind.lower()}") for kind in "KVE"]
    got = got.select("n", "d", "k", "p", *kinds, costs.cube_3d(4).alias("cube_words"))
    return got.select("n", "d", "k", "p", *[F.round(c, 3).alias(c) for c in got.columns[4:]])


def largest_n(spark, sf_dir):
    """Points whose K fits 80 GB a worker, for as many workers as a user has events, and how much that exceeds 80,000."""
    fits = costs.largest(80e9 * F.col("p"))
    return _event_counts(spark, sf_dir, "p").withColumn("n", fits).withColumn("growth", F.round(F.col("n") / 80_000, 6))


def cluster_ranks(spark, sf_dir):
    """Clusters of each point by nearness, in every kind of rank."""
    k, labels = _start(spark, sf_dir)
    e = sweep.cluster_means(k, labels)
    d = sweep.scores(e, sweep.centroid_norms(sweep.own_cluster_mean(e, labels))).select("i", "cl", F.round("dist", 3).alias("dist"))
    near, tied = Window.partitionBy("i").orderBy("dist", "cl"), Window.partitionBy("i").orderBy("dist")
    return d.select("i", "cl", F.rank().over(tied).alias("r"), F.dense_rank().over(tied).alias("dense"), F.round(F.percent_rank().over(tied), 6).alias("share"), F.ntile(3).over(near).alias("third"))


def history_decrease(spark, sf_dir):
    got = engines.fit(points.emb(spark, sf_dir), 10, loop=LoopSpec(max_iter=6, fixed=True)).history_df()
    return got.select("sweep", r6(F.lag("objective").over(Window.orderBy("sweep")) - F.col("objective")).alias("decrease"))


def top_clusters_lateral(spark, sf_dir):
    """The two nearest clusters of each point, through a lateral subquery; it returns what it sorts by, else Spark ranks its rows without the order."""
    k, labels = _start(spark, sf_dir)
    e = sweep.cluster_means(k, labels)
    sweep.scores(e, sweep.centroid_norms(sweep.own_cluster_mean(e, labels))).createOrReplaceTempView("kernmill_scores")
    labels.createOrReplaceTempView("kernmill_labels")
    return spark.sql("SELECT l.idx, t.cl FROM kernmill_labels l, LATERAL (SELECT s.cl, s.dist FROM kernmill_scores s WHERE s.i = l.idx ORDER BY s.dist, s.cl LIMIT 2) t")


def contingency_pivot(spark, sf_dir):
    p = points.lobes(spark, sf_dir)
    t = metrics.contingency(engines.fit(p, 2, loop=LoopSpec(max_iter=3)).labels_df(), p)
    return t.groupBy("cl").pivot("truth", [0, 1]).agg(F.sum("cnt")).select("cl", F.coalesce("0", F.lit(0)).alias("t0"), F.coalesce("1", F.lit(0)).alias("t1"))


def stream_pairs(spark, sf_dir):
    """Each sign-up with the purchases of its user within an hour after it."""
    e = _event_stream(spark, sf_dir)
    got = streams.paired(e.where("event_type = 'signup'"), e.where("event_type = 'purchase'"), "user_id", "1 hour", "60 days")
    return streams.run_available(got).select("a_id", "b_id")


def stream_drift(spark, sf_dir):
    """Hourly share of values over 100 per remainder of the user, as a drift monitor would see them."""
    e = _event_stream(spark, sf_dir).select("ts", (F.col("user_id") % 3).cast("int").alias("cl"), F.col("value").alias("sq_distance"))
    got = streams.run_available(streams.drift(e, 100.0, "60 days"), "complete")
    return got.select(F.col("start").cast("timestamp_ntz").alias("start"), "cl", "n", F.round("mean_sq", 6).alias("mean_sq"), F.round("far_share", 6).alias("far_share"))


def fit_given(spark, sf_dir):
    """Labels from given ones: runs of three neighbours start together."""
    p = points.emb(spark, sf_dir)
    given = p.select("idx", (F.floor(F.col("idx") / 3) % 10).cast("int").alias("cl"))
    return engines.fit(p, 10, loop=LoopSpec(max_iter=8), init=given).labels_df()


def replicating_table(spark, sf_dir):
    """Words of layouts that copy the dense operand four times."""
    copied, moved = costs.replicating(4)
    return _grid(spark).select("n", "d", "k", "p", F.round(copied, 3).alias("copied_words"), F.round(moved, 3).alias("sweep_words"))


def collective_table(spark, sf_dir):
    """Sweep costs of the 2d layout by how the labels of a grid column are brought together, logarithms kept."""
    named = [c for how in ("allgather", "rounds") for c in zip((f"{how}_messages", f"{how}_words"), costs.distance_stage("2d", True, how))]
    return _event_sets(spark, sf_dir).select("n", "d", "k", "p", *[F.round(c, 3).alias(name) for name, c in named])


def cost_table_logs(spark, sf_dir):
    got = costs.table(_event_sets(spark, sf_dir), with_logs=True)
    return got.select("algo", "n", "d", "k", "p", *[F.round(c, 3).alias(c) for c in ("kernel_messages", "kernel_words", "sweep_messages", "sweep_words")])


def cost_table_function(spark, sf_dir):
    """The same costs through the SQL table function."""
    sqlapi.register(spark)
    _event_sets(spark, sf_dir).createOrReplaceTempView("kernmill_grid")
    words = ("kernel_messages", "kernel_words", "sweep_messages", "sweep_words")
    return spark.sql(f"SELECT t.algo, g.n, g.d, g.k, g.p, {', '.join(f'round(t.{c}, 3) AS {c}' for c in words)} FROM kernmill_grid g, LATERAL cost_table(g.n, g.d, g.k, g.p) t")


def sampled_features(spark, sf_dir):
    return spread(lambda s, d: points.sample_features(points.emb(s, d), 8, 64, 5))(spark, sf_dir)


def projected(spark, sf_dir):
    return spread(lambda s, d: points.project(points.emb(s, d), 4, 64, 5))(spark, sf_dir)


def means_by_tile(spark, sf_dir):
    k, labels = _start(spark, sf_dir)
    return sweep.cluster_means_by_tile(k, labels, labels.count()).select("i", "cl", r6("e").alias("e"))


def inner_pairs(spark, sf_dir):
    return sweep.inner_pair_means(*_start(spark, sf_dir)).select("cl", r6("c").alias("c"))


def unmoved_labels(spark, sf_dir):
    k, before = _start(spark, sf_dir)
    return sweep.sweep(k, before, 10).intersect(before)


def rolling_events(spark, sf_dir):
    """Per event of a user: value over its last five events, and events within the hour up to it."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "value", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    last5 = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, Window.currentRow)
    hour = Window.partitionBy("user_id").orderBy("at").rangeBetween(-3_600_000_000, Window.currentRow)
    return e.select("event_id", F.round(F.sum("value").over(last5), 4).alias("last5"), F.count("*").over(hour).alias("in_hour"))


def report_rollup(spark, sf_dir):
    """Seconds by dataset, then algorithm, then all, where more than one row was added up."""
    return _runs(spark).rollup("dataset", "algo").agg(F.sum("seconds").alias("seconds"), F.count("*").alias("rows"), F.grouping_id().cast("int").alias("level")).where("rows > 1")


def run_statistics(spark, sf_dir):
    by = [F.round(f, 6).alias(name) for name, f in (("spread", F.stddev_pop("seconds")), ("with_workers", F.corr("g", "seconds")))]
    return _runs(spark).groupBy("algo").agg(F.percentile_approx("seconds", 0.5, 10_000).alias("middle"), *by, F.sum(F.when(F.col("g") == 4, F.col("seconds"))).alias("on_four"))


def stream_late(spark, sf_dir):
    """Hourly counts where the newer half of the time comes first, and a watermark of two hours drops the older half."""
    rows, at = table(spark, sf_dir, "events"), F.unix_micros(F.col("ts").cast("timestamp"))
    middle = rows.select(at.alias("m")).agg(F.expr("(min(m) + max(m)) div 2").alias("m")).first().m
    path = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    for half, files in ((at >= middle, 8), (at < middle, 4)):  # two batches before the late one: a watermark drops rows from the second batch after it on
        rows.where(half).repartition(files).write.mode("append").parquet(path)
    got = streams.run_available(streams.windowed(streams.source(spark, path, files_per_trigger=4), "tumbling", "2 hours"))
    return got.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


def stream_dimension(spark, sf_dir):
    """Each event of the stream with a static dimension of its user."""
    users = table(spark, sf_dir, "events").groupBy("user_id").agg(F.count("*").alias("events"))
    return streams.run_available(streams.with_dimension(_event_stream(spark, sf_dir).select("event_id", "user_id"), users, "user_id")).select("event_id", "events")


_runs_query = lambda f: lambda spark, sf_dir: f(_runs(spark))
KERNELS = (("linear", linear()), ("poly", POLY), ("rbf", rbf(0.5)), ("sigmoid", sigmoid(0.5, 0.1)), ("cosine", cosine()))
QUERIES = {
    **{f"gram_{name}": gram_values(spec) for name, spec in KERNELS},
    "gram_tiles_checksum": gram_tiles_checksum,
    "gram_symmetric_half": gram_symmetric_half,
    "kernel_diag": lambda s, d: _diagonal(s, d).select("i", r6("v").alias("v")),
    "kernel_trace": lambda s, d: _diagonal(s, d).agg(r6(F.sum("v")).alias("trace")),
    "init_round_robin": lambda s, d: sweep.round_robin(points.emb(s, d), 10),
    "sizes_initial": lambda s, d: sweep.sizes(sweep.round_robin(points.emb(s, d), 10), 10),
    "membership_triplets": lambda s, d: sweep.triplets(sweep.round_robin(points.emb(s, d), 10)),
    "sizes_with_empties": sizes_with_empties,
    **{f"sweep_{n}": sweep_step(n) for n in ("means", "means_transposed", "mask", "cnorm", "scores", "sqdist", "labels")},
    "sweep_objective": sweep_objective,
    "fit_entries_k10": emb_fit("entries"),
    "fit_panel_1d_k10": emb_fit("panel_1d"),
    "fit_regrid_h1d_k10": emb_fit("regrid_h1d"),
    "fit_tile_2d_k10": emb_fit("tile_2d"),
    "fit_mixed_15d_k10": emb_fit("mixed_15d"),
    "fit_window_k10": emb_fit("window", height=128),
    "fit_window_disk_k10": window_disk,
    "fit_fused_k10": emb_fit("window", height=128, distributed=True),
    "fit_local_k10": emb_fit("local"),
    "fit_mixed_rowsplit_k10": emb_fit(loop={"split": "clusters"}),
    "fit_mixed_row_join_k10": emb_fit(loop={"copy_v": "row_join"}),
    "fit_mixed_diagonal_k10": emb_fit(loop={"copy_v": "diagonal"}),
    "fit_mixed_symmetric_k10": emb_fit(store={"symmetric": True}, g=3),
    "fit_mixed_sparse_v_k10": emb_fit(loop={"v": "sparse"}),
    "fit_mixed_f32acc64_k10": emb_fit(store={"dtype": "f32acc64"}),
    "fit_mixed_k16": fit_labels(points.emb, 16, max_iter=10),
    "fit_mixed_k32": fit_labels(points.emb, 32, max_iter=12),
    "fit_mixed_k64": fit_labels(points.emb, 64, max_iter=4),
    "history_changed": history("changed"),
    "history_objective": history("objective"),
    "empty_skip": whole_fit(points.line4, 64, LoopSpec(max_iter=12, empty="skip")),
    "empty_origin": whole_fit(points.line4, 64, LoopSpec(max_iter=12, empty="origin")),
    "empty_reseed": whole_fit(points.line4, 64, LoopSpec(max_iter=12, empty="reseed")),
    "tie_break_mini": fit_labels(points.mini, 2, linear(), max_iter=3),
    "mini_poly": fit_labels(_user_totals, 2, max_iter=3),
    "mini_scores": lambda s, d: (lambda k, l: sweep.scores(e := sweep.cluster_means(k, l), sweep.centroid_norms(sweep.own_cluster_mean(e, l))))(gram.entries(points.mini(s), POLY), sweep.round_robin(points.mini(s), 2)).select("i", "cl", r6("dist").alias("dist")),
    **{f"{f.__name__}_points": spread(f) for f in (points.userfeat, points.part2, points.lobes, points.rings)},
    **{f"{f.__name__}_points": spread(f, 4) for f in (points.line4, points.wide28, points.eventday)},
    "docbag_points": docbag_points,
    "docvocab_counts": points.docvocab,
    "line4_fit_k16": whole_fit(points.line4, 16, LoopSpec(max_iter=15)),
    "wide28_fit_k16": whole_fit(points.wide28, 16, LoopSpec(max_iter=19)),
    "docbag_fit_k4": fit_labels(points.docbag, 4, max_iter=9),
    "docbag_wide_fit_k4": docbag_wide_fit,
    "userfeat_fit_k4": fit_labels(points.userfeat, 4, max_iter=14),
    "eventday_fit_k4": whole_fit(points.eventday, 4, LoopSpec(max_iter=12)),
    "lobes_linear": fit_labels(points.lobes, 2, linear(), max_iter=None),
    "lobes_poly": fit_labels(points.lobes, 2, max_iter=3),
    "rings_poly": fit_labels(points.rings, 2, max_iter=None),
    "part2_fit": fit_labels(points.part2, 16, max_iter=23),
    "lloyd_k10": lambda s, d: baselines.lloyd(points.emb(s, d), 10, LoopSpec(max_iter=12)).labels_df(),
    "lift_poly2_k10": lambda s, d: baselines.lift(points.emb(s, d), 10, loop=LoopSpec(max_iter=17)).labels_df(),
    "landmark_k10": landmark_k10,
    "spectral_rings_ari": spectral_rings,
    "plusplus_k10": plusplus_k10,
    "window_heights": window_heights,
    **{f"weak_scaling_{name}": scaling_words(name, True) for name in SETS},
    **{f"strong_scaling_{name}": scaling_words(name, False) for name in SETS},
    "weak_efficiency": lambda s, d: experiments.weak_report(scaling_runs("vision", True)(s, d)),
    "strong_speedup": lambda s, d: experiments.strong_report(scaling_runs("vision", False)(s, d)),
    "window_seconds": window_seconds,
    "stage_breakdown": stage_breakdown,
    "window_comparison": window_comparison,
    "assign_holdout": assign_holdout,
    "nearest_members_topk": nearest_members_topk,
    "second_best_margin": sweep_step("margin"),
    "cost_table": cost_table,
    "cost_crossover": lambda s, d: costs.crossover_of(_event_counts(s, d, "k")),
    "memory_table": lambda s, d: costs.memory_table(_event_sets(s, d)).withColumn("memory_bytes", F.round("memory_bytes", 0)),
    "feasible_table": lambda s, d: costs.feasible(_event_sets(s, d), 80e9).drop("memory_bytes"),
    "weak_plan": lambda s, d: costs.weak_plan(s),
    "traffic_mixed": traffic_mixed,
    "traffic_all": traffic_all,
    "balance_1d": balance("1d"),
    "balance_2d": balance("2d"),
    "flops_table": lambda s, d: costs.flops(_event_sets(s, d)),
    "grid_product_table": grid_product_table,
    "geo_mean_runs": geo_mean_runs,
    "weak_efficiency_fixed": _runs_query(metrics.weak_efficiency),
    "strong_speedup_fixed": _runs_query(metrics.strong_speedup),
    "speedup_fixed": _runs_query(lambda r: metrics.speedup(r, "mixed", "panel")),
    "report_cube": _runs_query(metrics.report),
    "contingency_lobes": quality(points.lobes, 2, POLY, 3, "contingency"),
    "ari_lobes": quality(points.lobes, 2, POLY, 3, "ari"),
    "ari_lobes_linear": quality(points.lobes, 2, linear(), 2, "ari"),
    "nmi_docbag": quality(points.docbag, 4, POLY, 9, "nmi"),
    "purity_docbag": quality(points.docbag, 4, POLY, 9, "purity"),
    "agreement_engines": agreement_engines,
    "dense_index_lineitem": dense_index_lineitem,
    "standardize_line4": scaled(points.standardize),
    "minmax_line4": scaled(points.minmax),
    "onehot_flags": onehot_flags,
    "sample_n": sampled,
    "semi_changed": semi_changed,
    "anti_unsampled": anti_unsampled,
    "setops_labels": setops_labels,
    "asof_label_events": asof_label_events,
    "interval_events": interval_events,
    "stream_assign": stream_assign,
    "stream_tumbling": stream_windows("tumbling"),
    "stream_sliding": stream_windows("sliding"),
    "stream_session": lambda s, d: stream_windows("session")(s, d),
    "stream_dedup": stream_dedup,
    "stream_pairs": stream_pairs,
    "stream_drift": stream_drift,
    "stationary_table": stationary_table,
    "largest_n": largest_n,
    "cluster_ranks": cluster_ranks,
    "history_decrease": history_decrease,
    "fit_given_k10": fit_given,
    "replicating_table": replicating_table,
    "collective_table": collective_table,
    "cost_table_logs": cost_table_logs,
    "cost_table_function": cost_table_function,
    "sampled_features": sampled_features,
    "projected_emb": projected,
    "means_by_tile": means_by_tile,
    "inner_pairs": inner_pairs,
    "unmoved_labels": unmoved_labels,
    "rolling_events": rolling_events,
    "report_rollup": report_rollup,
    "run_statistics": run_statistics,
    "stream_late": stream_late,
    "stream_dimension": stream_dimension,
    "top_clusters_lateral": top_clusters_lateral,
    "contingency_pivot": contingency_pivot,
}
