"""Pairs of blocks of one family of near copies are dealt out one by one."""

import re

import pytest

from kernmill.llm import common, near_dedup


@pytest.mark.parametrize("bound", [near_dedup.BROADCAST_ROWS, 0])
def test_no_exchange_by_family_alone(spark, monkeypatch, bound):
    monkeypatch.setattr(near_dedup, "BLOCK", 8)
    monkeypatch.setattr(near_dedup, "BROADCAST_ROWS", bound)
    words = [f"w{i}" for i in range(60)]
    texts = [(i, " ".join([*words[:i], f"x{i}", *words[i + 1 :]])) for i in range(40)] + [(40, "alone in its own family " * 3), (41, "alone in its own family " * 3 + "now")]
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    reps = spark.createDataFrame([(i, 58 if i < 40 else 10) for i, _ in texts], "rep long, n_shingles long")
    family = spark.createDataFrame([(i, 0 if i < 40 else 40) for i, _ in texts], "node long, component long")
    pairs = near_dedup.block_pairs(docs, reps, family, 3)
    rows = pairs.drop("members").collect()
    blocks = {r.block for r in rows if r.family == 0}
    assert blocks == set(range(5)) and all(r.lo == r.hi == 0 for r in rows if r.family == 40)
    assert {(r.lo, r.hi) for r in rows if r.family == 0} == {(a, b) for a in range(5) for b in range(a, 5)}
    assert all(r.block in (r.lo, r.hi) for r in rows) and len(rows) == 40 * 5 + 2
    links = pairs.groupBy("family", "lo", "hi").applyInPandas(near_dedup._linked(85), "a long, b long")
    plan = links._jdf.queryExecution().executedPlan().toString()
    dealt = re.findall(r"hashpartitioning\(([^)]*)\)", plan)
    assert any(d.startswith("family") and "lo#" in d and "hi#" in d for d in dealt), plan
    assert not any(re.match(r"(family|component)#\d+L?, \d+$", d) for d in dealt), plan


def test_left_salted_join_keeps_rows_without_a_match(spark):
    rows = spark.createDataFrame([(k, i) for k in (1, 2, None) for i in range(20)], "k long, i long")
    once = spark.createDataFrame([(1, "a")], "k long, v string")
    got = common.salted_join(rows, once, "k", "i", how="left").collect()
    assert len(got) == 60 and sum(r.v == "a" for r in got) == 20
