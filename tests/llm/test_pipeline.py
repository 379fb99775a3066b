"""The pipeline against brute force, stage by stage, and the SQL of the operators that have one."""

import re
from collections import defaultdict

import duckdb
import pytest

import corpus_pipeline
from kernmill.llm import queries
from tests.llm.test_operators import base_spans, contaminated, grouped


def plain(v):
    return repr(v) if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_equals_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for t in ("documents", "embeddings", "pages", "benchmark", "labels", "conversations"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    got, want = queries.QUERIES[name](spark, sf_dir), con.sql(queries.ORACLES[name])
    cols = sorted(got.columns)
    assert sorted(want.columns) == cols
    at = [want.columns.index(c) for c in cols]
    assert sorted(tuple(plain(r[c]) for c in cols) for r in got.collect()) == sorted(tuple(plain(r[i]) for i in at) for r in want.fetchall())


def test_stages(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    before = {r.doc_id: r.text for r in docs.collect()}
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf_dir}/labels.parquet").collect()}
    steps = dict(corpus_pipeline.STAGES)

    good = corpus_pipeline.stage(steps["quality"](spark, docs, sf_dir))
    assert good.columns == docs.columns
    kept = {r.doc_id: r.text for r in good.collect()}
    known = [i for i in before if i in labels]
    assert sum((i in kept) == labels[i] for i in known) >= 0.9 * len(known)

    once = corpus_pipeline.stage(steps["near_dedup"](spark, good, sf_dir))
    ids = sorted(kept)
    roots = grouped([kept[i] for i in ids], 5, 80)[1]
    assert sorted(r.doc_id for r in once.collect()) == sorted({ids[r] for r in roots})

    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect()]
    apart = corpus_pipeline.stage(steps["decontamination"](spark, once, sf_dir))
    mine = {r.doc_id: r.text for r in once.collect()}
    hits = dict(zip(mine, contaminated(list(mine.values()), items)))
    assert {r.doc_id for r in apart.collect()} == {i for i in mine if not hits[i][1]}

    clean = corpus_pipeline.stage(steps["secrets"](spark, apart, sf_dir))
    left = {r.doc_id: r.text for r in clean.collect()}
    assert set(left) == {r.doc_id for r in apart.collect()} and clean.columns == docs.columns
    for i, t in left.items():
        assert not base_spans(t)
        if not base_spans(mine[i]) and not re.search("[A-Za-z0-9+/_-]{32}", mine[i]):
            assert t == mine[i]

    pieces = defaultdict(int)
    for r in steps["packing"](spark, clean, sf_dir).collect():
        pieces[r.doc_id] += r.length
        total = r.doc_tokens
        assert pieces[r.doc_id] <= total
    assert set(pieces) == set(left)
