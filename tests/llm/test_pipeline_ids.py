"""The pipeline's last stage holds the corpus as token ids."""

import zlib
from collections import defaultdict

import numpy as np

import corpus_pipeline
from kernmill.llm.token_codec import Codec, default_vocabulary


def test_packed_rows_hold_the_ids(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(40)
    texts = {r.doc_id: r.text for r in docs.collect()}
    got = defaultdict(dict)
    for r in dict(corpus_pipeline.STAGES)["packing"](spark, docs, sf_dir).collect():
        assert zlib.crc32(r.ids) == r.ids_crc32
        got[r.doc_id][r.start] = np.frombuffer(r.ids, "<u4").tolist()
    want = {i: c.tolist() + [2] for i, c in zip(texts, Codec(default_vocabulary()).encode(list(texts.values())))}
    assert {i: sum((parts[s] for s in sorted(parts)), []) for i, parts in got.items()} == want
