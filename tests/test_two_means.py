"""Two-means gives the same planes whether a set goes to one task or is summed up where it lies."""

import numpy as np
import pytest

from blockfinder.operators import bisect


@pytest.mark.parametrize("how", [{}, {"init": "far"}, {"init": "kmeans++", "n_init": 3, "seed": 4}, {"max_iter": 2}])
def test_planes_do_not_depend_on_where_a_set_is_held(spark, how):
    rng = np.random.default_rng(3)
    z = rng.normal(0, 1.0, (3_000, 4)).astype("f4")  # one cloud: steps go on for long, and a sample starts elsewhere
    path = np.where(np.arange(3_000) % 3 == 0, "a", "b")
    path[2_990:] = "c"
    z[2_990:] = 1
    assign = spark.createDataFrame([(p, k, row.tolist()) for k, (p, row) in enumerate(zip(path.tolist(), z, strict=True))], "path string, id long, v array<float>").repartition(7)
    sizes = {p: int((path == p).sum()) for p in ("a", "b", "c")}
    spread = bisect.two_means(assign, sizes, rows=5, **how)
    mixed = bisect.two_means(assign, sizes, rows=1_500, **how)
    for p in sizes:
        own = np.flatnonzero(path == p)
        w, b = bisect.fit(z[own], own, rows=10_000, **how)
        assert bisect.fit(z[own], own, rows=5, **how)[0].tolist() == w.tolist()
        for planes in (spread, mixed):
            assert planes[p][0] == pytest.approx(w) and planes[p][1] == pytest.approx(b)
            assert ((z[own].astype("f8") @ planes[p][0] > planes[p][1]) == (z[own].astype("f8") @ w > b)).all()


def test_steps_go_on_until_no_side_changes(spark):
    z = np.random.default_rng(8).normal(0, 1.0, (3_000, 4)).astype("f4")
    w, b = bisect.fit(z, np.arange(3_000), rows=100)
    side = z.astype("f8") @ w > b
    again = bisect.plane(np.stack([z[~side].astype("f8").mean(axis=0), z[side].astype("f8").mean(axis=0)]))
    assert ((z.astype("f8") @ again[0] > again[1]) == side).all()
