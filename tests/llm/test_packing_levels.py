"""Levels against the rule written out: the move that keeps the sum of squared counts smallest, ties to the lowest fill."""

import numpy as np

from kernmill.llm.sequence_packing import Levels


def test_places_by_the_least_sum_of_squares():
    draw, levels, counts = np.random.Generator(np.random.PCG64(4)), Levels(64), np.zeros(65, int)
    for i in range(3000):
        n = int(min(64, draw.integers(1, 65) if i % 3 else draw.integers(1, 9)))
        costs = {}
        for fill in range(65 - n):
            after = counts.copy()
            if fill and not counts[fill]:
                continue
            after[fill] -= fill > 0
            after[fill + n] += fill + n < 64
            costs[fill] = int((after**2).sum())
        want = min(costs, key=lambda f: (costs[f], f))
        counts[want] -= want > 0
        counts[want + n] += want + n < 64
        done = levels.place((i, 0, np.zeros(n, np.uint16), n))
        assert (done is not None) == (want + n == 64)
        assert levels.count.tolist() == counts.tolist() and levels.open == counts.sum()
