"""Rounds of merges leave nothing behind."""

from pathlib import Path

from test_one_task import blocks_graph

from blockfinder.operators import baselines, graph


def test_rounds_leave_no_tables_behind(spark, monkeypatch):
    a, b = blocks_graph(60, 3, 400)
    g = graph.build(spark.createDataFrame([(int(x), int(y)) for x, y in zip(a, b, strict=True)], "a long, b long"))
    monkeypatch.setattr(baselines, "ONE_TASK_EDGES", len(a) // 2)
    shared = Path(spark.sparkContext.getCheckpointDir().removeprefix("file:"))
    before = set(shared.iterdir())
    found = baselines.greedy_modularity(g)
    assert found.count() == 60
    kept = [x for x in shared.iterdir() if x not in before]
    assert len(kept) <= 5  # the start, the result, and what the last task gave
