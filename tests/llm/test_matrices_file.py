"""A written file of matrices, read again, with positions that restart at each segment."""

import numpy as np

from kernmill.llm import token_binary
from tests.llm.test_operators import TEXTS, docs


def test_written_matrices_have_positions(spark, tmp_path):
    token_binary.write_matrices(docs(spark, TEXTS), str(tmp_path / "m"), window=256)
    rows = spark.read.parquet(str(tmp_path / "m")).collect()
    assert rows and max(r.n_segments for r in rows) > 1
    for r in rows:
        want = [p for a, b in zip(r.cu_seqlens, r.cu_seqlens[1:]) for p in range(b - a)]
        assert np.frombuffer(r.positions, "<u2").tolist() == want + [0] * (256 - r.n_tokens)
        assert len(np.frombuffer(r.input_ids, "<u2")) == 256
