"""Numbers of groups that are tried side by side."""

import numpy as np
import pytest
from test_one_task import blocks_graph

from blockfinder.operators import baselines, graph


def in_order(n, a, b, objective, numbers):
    best, score = np.zeros(n, "i8"), 0.0
    deg = np.bincount(np.r_[a, b], minlength=n).astype("f8")
    for k in numbers:
        labels = baselines.messages(n, a, b, deg, k, objective, 0.3, 8, 0)
        now = (labels[a] == labels[b]).mean() - ((np.bincount(labels, deg, k) / deg.sum()) ** 2).sum()
        if now > score + 1e-3:
            best, score = labels, now
        elif k >= 2 * (best.max() + 1):
            break
    return best


@pytest.mark.parametrize("objective", ["modularity", "sbm"])
def test_numbers_of_groups_side_by_side_give_what_they_give_in_order(spark, monkeypatch, objective):
    n = 150
    a, b = blocks_graph(n, 3, 1500)
    order = np.lexsort((b, a))
    g = graph.build(spark.createDataFrame([(int(x), int(y)) for x, y in zip(a, b, strict=True)], "a long, b long"), spark.range(n))
    monkeypatch.setattr(baselines, "AT_ONCE", 4)
    found = baselines.belief_propagation(g, objective, max_iter=8).toPandas().set_index("id")["block"].sort_index().to_numpy()
    plain = in_order(n, a[order], b[order], objective, baselines.scan(n))
    least = {k: np.flatnonzero(plain == k).min() for k in np.unique(plain)}
    assert found.tolist() == [least[k] for k in plain]


def test_numbers_that_are_needed_go_side_by_side_while_there_is_room():
    grid = list(baselines.scan(100))
    assert baselines.side_by_side(grid, 2, 100) == [2, 3, 4, 6, 8, 11]
    assert baselines.side_by_side(grid[6:], 22, 100) == [15, 20, 26]
    assert baselines.side_by_side(grid[6:], 22, baselines.MESSAGE_BYTES // 4 // 35) == [15, 20]
    assert baselines.side_by_side(grid[6:], 22, 10**12) == [15]
