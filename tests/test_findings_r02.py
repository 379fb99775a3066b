"""Findings of the second review: lateral order, scoring of an unsettled fit."""

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq

from kernmill.functions import points
from kernmill.functions.kernels import polynomial
from kernmill.sqlapi import cluster_small
from kernmill.workloads import tables

from .test_kernel_kmeans import data


def test_lateral_ranks_by_distance(spark, sf_dir):
    plan = tables.top_clusters_lateral(spark, sf_dir)._jdf.queryExecution().optimizedPlan().toString()
    (ranked,) = [line for line in plan.splitlines() if "Window [row_number" in line and "windowspecdefinition(i#" in line]
    assert "dist#" in ranked[ranked.index("windowspecdefinition") :]


def test_stream_gives_the_labels_of_the_last_sweep(spark, tmp_path):
    """Points that have not settled after 17 sweeps."""
    x = data(600, 3, 0).astype("f4")
    want = [cluster_small(x.astype(float), 10, polynomial(), sweeps).tolist() for sweeps in (17, 18)]
    assert want[0] != want[1]
    pq.write_table(pa.table({"vec_id": np.arange(len(x)), "embedding": pa.array(list(x), pa.list_(pa.float32()))}), tmp_path / "embeddings.parquet")
    got = {r.idx: r.cl for r in tables.stream_assign(spark, str(tmp_path)).collect()}
    assert [got[i] for i in range(len(x))] == want[0]


def test_cost_queries_read_a_table(spark, sf_dir):
    for name in ("collective_table", "cost_crossover", "cost_table", "cost_table_function", "cost_table_logs", "feasible_table", "flops_table", "geo_mean_runs", "grid_product_table", "largest_n", "memory_table"):
        assert any(f.endswith("/events.parquet") for f in tables.QUERIES[name](spark, sf_dir).inputFiles()), name


def test_documents_are_drawn_before_their_vectors(spark, sf_dir):
    """Vectors of 10,000 words for the drawn documents alone: as many as ``sampled`` draws, and the same."""
    want = {r.key: (r.idx, r.x) for r in points.sampled(points.docbag(spark, sf_dir, 50), 20).collect()}
    got = points.docbag(spark, sf_dir, 50, drawn=20)
    assert {r.key: (r.idx, r.x) for r in got.collect()} == want and len(want) == 20
    files = [f for f in got.inputFiles() if "/table-" in f]
    assert files and spark.read.parquet(*files).count() == 20
