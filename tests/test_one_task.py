"""Methods in one task: what they touch grows with the arcs."""

import tracemalloc

import numpy as np

from blockfinder.operators import baselines


def blocks_graph(n, k, m, seed=0):
    rng = np.random.default_rng(seed)
    a = rng.integers(0, n, m)
    b = np.where(rng.random(m) < 0.8, rng.integers(0, n // k, m) * k + a % k, rng.integers(0, n, m))
    cell = np.unique(np.minimum(a, b) * n + np.maximum(a, b))
    return tuple(x[cell // n != cell % n] for x in (cell // n, cell % n))


def plain_rounds(n, r, s, vol, total):
    """The same merges from a dense table."""
    table, vol, labels = np.zeros((n, n)), vol.copy(), np.arange(n)
    np.add.at(table, (r, s), 1)
    while True:
        gain = table / total - np.outer(vol, vol) / total**2
        gain[(table == 0) | np.eye(n, dtype=bool)] = -1
        best = []
        for x in range(n):
            most = np.flatnonzero((gain[x] == gain[x].max()) & (gain[x] > 0))
            best.append(max(most, key=lambda y: (min(x, y) * 31 + max(x, y), y)) if len(most) else -1)
        pairs = [(x, best[x]) for x in range(n) if best[x] >= 0 and best[best[x]] == x and best[x] < x]
        if not pairs:
            return labels
        for x, y in pairs:
            table[y] += table[x]
            table[:, y] += table[:, x]
            table[x], table[:, x] = 0, 0
            vol[y] += vol[x]
            vol[x] = 0
            labels[labels == x] = y


def test_rounds_touch_what_merges(monkeypatch):
    n = 150
    a, b = blocks_graph(n, 5, 900)
    r, s = np.r_[a, b], np.r_[b, a]
    vol = np.bincount(r, minlength=n).astype("f8")
    assert (baselines.rounds_in_memory(n, r, s, np.ones(len(r)), vol, float(len(r))) == plain_rounds(n, r, s, vol, float(len(r)))).all()
    n = 4000
    a, b = blocks_graph(n, 10, 60_000)
    r, s = np.r_[a, b], np.r_[b, a]
    seen, unique = [], np.unique
    monkeypatch.setattr(np, "unique", lambda x, **how: (seen.append(len(x)), unique(x, **how))[1])
    baselines.rounds_in_memory(n, r, s, np.ones(len(r)), np.bincount(r, minlength=n).astype("f8"), float(len(r)))
    assert len(seen) > 10 and sum(seen) < 8 * len(r)


def test_rounds_of_few_merges_leave_the_cells_alone(monkeypatch):
    for seed in range(8):
        n = 40 + 15 * seed
        a, b = blocks_graph(n, 1 + seed % 4, 3 * n, seed)
        r, s = np.r_[a, b], np.r_[b, a]
        vol = np.bincount(r, minlength=n).astype("f8")
        assert (baselines.rounds_in_memory(n, r, s, np.ones(len(r)), vol, float(len(r))) == plain_rounds(n, r, s, vol, float(len(r)))).all()
    n = 4000
    a, b = blocks_graph(n, 10, 60_000)
    r, s = np.r_[a, b], np.r_[b, a]
    vol = np.bincount(r, minlength=n).astype("f8")
    seen, divmod_ = [], np.divmod
    monkeypatch.setattr(np, "divmod", lambda x, y: (seen.append(len(x)), divmod_(x, y))[1])
    baselines.rounds_in_memory(n, r, s, np.ones(len(r)), vol, float(len(r)))
    assert sum(seen) < 25 * len(r)


def test_sweeps_hold_no_table_of_nodes_and_blocks():
    n, k = 20_000, 400
    a, b = blocks_graph(n, 20, 100_000)
    start, near = baselines.csr(n, a, b)
    tracemalloc.start()
    out = baselines.chain(np.arange(n) % k, k, start, near, a, b, np.random.default_rng(0), 3.0, 2)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(out) == n and most < 40 << 20  # a table would take 64 MB


def test_a_graph_of_the_stated_edges_is_merged_in_one_task(spark, monkeypatch):
    from blockfinder.operators import graph

    a, b = blocks_graph(300, 3, 3000)
    g = graph.build(spark.createDataFrame([(int(x), int(y)) for x, y in zip(a, b, strict=True)], "a long, b long"))
    monkeypatch.setattr(baselines, "ONE_TASK_EDGES", g.m)
    settled, settle = [], baselines.settle
    monkeypatch.setattr(baselines, "settle", lambda df: (settled.append(df), settle(df))[1])
    found = baselines.greedy_modularity(g)
    assert len(settled) == 3 and found.count() == g.n  # nothing but the start


def plain_best(n, a, b):
    """The best merge at each step, from a dense table."""
    table, total, labels = np.zeros((n, n)), 2.0 * len(a), np.arange(n)
    np.add.at(table, (np.r_[a, b], np.r_[b, a]), 1)
    vol = table.sum(axis=1)
    while True:
        gain = table / total - np.outer(vol, vol) / total**2
        gain[(table == 0) | ~np.triu(np.ones((n, n), bool), 1)] = -1
        i, j = divmod(int(gain.argmax()), n)
        if gain[i, j] <= 0:
            return labels
        table[i] += table[j]
        table[:, i] += table[:, j]
        table[j], table[:, j] = 0, 0
        vol[i] += vol[j]
        vol[j] = 0
        labels[labels == j] = i


def test_best_merges_ask_few_rows(monkeypatch):
    a, b = blocks_graph(150, 5, 900)
    assert (baselines.merge_best(150, a, b) == plain_best(150, a, b)).all()
    n = 2000
    a, b = blocks_graph(n, 8, 40_000)
    pushed, push = [], baselines.heapq.heappush
    monkeypatch.setattr(baselines.heapq, "heappush", lambda heap, x: (pushed.append(1), push(heap, x))[1])
    baselines.merge_best(n, a, b)
    assert len(pushed) < 4 * n


def plain_messages(n, a, b, k, objective, sweeps, seed=0, damping=0.3):
    """The same sweeps, message by message."""
    m, deg = len(a), np.bincount(np.r_[a, b], minlength=n).astype("f8")
    src, dst, excess = np.r_[a, b], np.r_[b, a], max(1.5, (deg**2).mean() / deg.mean() - 1)
    beta = np.log(k / (np.sqrt(excess) - 1) + 1)
    table, belief = np.ones((k, k)) + np.eye(k) * (np.exp(beta) - 1), np.full((n, k), 1 / k)
    psi = baselines.uniform_block(seed + k, np.arange(2 * m), k)
    psi /= psi.sum(axis=1, keepdims=True)
    for sweep in range(sweeps):
        pull, field = np.log(psi @ table), deg @ belief
        whole = -deg[:, None] * (beta * field if objective == "modularity" else field @ table / table.mean()) / deg.sum()
        np.add.at(whole, dst, pull)
        belief = np.exp(whole - whole.max(axis=1, keepdims=True))
        belief /= belief.sum(axis=1, keepdims=True)
        own = whole[src] - np.roll(pull, m, axis=0)
        new = np.exp(own - own.max(axis=1, keepdims=True))
        psi = damping * psi + (1 - damping) * new / new.sum(axis=1, keepdims=True)
        if objective == "sbm" and sweep % 10 == 9:
            joint, vol = belief[a].T @ belief[b], deg @ belief
            learned = (joint + joint.T) * deg.sum() / np.maximum(np.outer(vol, vol), 1e-9)
            table = 0.5 * table + 0.5 * np.maximum(learned / learned.mean(), 1e-3)
    return belief.argmax(axis=1)


def test_messages_fill_one_table(monkeypatch):
    monkeypatch.setattr(baselines, "TURN", 700)
    n, k = 200, 5
    a, b = blocks_graph(n, 4, 1500)
    deg = np.bincount(np.r_[a, b], minlength=n + 1).astype("f8")  # the last node has no edge
    for objective in ("modularity", "sbm"):
        found = baselines.messages(n + 1, a, b, deg, k, objective, 0.3, 12, 0)
        assert (found == plain_messages(n + 1, a, b, k, objective, 12)).mean() > 0.99  # sums in single precision
    monkeypatch.undo()
    n, k = 5000, 16
    a, b = blocks_graph(n, 8, 100_000)
    tracemalloc.start()
    baselines.messages(n, a, b, np.bincount(np.r_[a, b], minlength=n).astype("f8"), k, "modularity", 0.3, 2, 0)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 3 * 2 * len(a) * k * 4


def test_a_sample_of_a_larger_graph_is_inferred(spark, monkeypatch):
    from blockfinder.operators import graph

    n = 600
    a, b = blocks_graph(n, 3, 6000)
    g = graph.build(spark.createDataFrame([(int(x), int(y)) for x, y in zip(a, b, strict=True)], "a long, b long"), spark.range(n + 2))
    found = baselines.sbm_mcmc(g, sample_fraction=0.5).toPandas().set_index("id")["block"].sort_index()
    assert found.nunique() < 50 and found[n] == n and found[n + 1] == n + 1  # nothing to follow
    drawn = {r["id"] for r in baselines.sampled(g, 0, 0.5).collect()}
    assert drawn == set(np.flatnonzero(baselines.uniform_block(0, np.arange(n + 2), 1)[:, 0] < 0.5).tolist())
    # In a task or distributed: the same labels are followed alike.
    start = np.where(np.isin(np.arange(n + 2), list(drawn)), np.arange(n + 2) % 7, -1)
    start[:7] = np.arange(7)
    after = baselines.follow(start.copy(), n + 2, a, b)
    rows = [(int(i), int(start[i])) for i in np.flatnonzero(start >= 0)]
    other = baselines.followed(g, spark.createDataFrame(rows, "id long, block long")).toPandas().set_index("id")["block"].sort_index()
    assert (other.to_numpy() == after).all()
    monkeypatch.setattr(baselines, "ONE_TASK_EDGES", 4000)  # fewer than the graph has, which was refused
    monkeypatch.setattr(baselines, "infer", lambda n, *rest: np.arange(n) % 7)
    assert baselines.sbm_mcmc(g, sample_fraction=0.5).count() == n + 2


def test_a_method_runs_once(spark, tmp_path):
    from blockfinder.operators import graph

    g = graph.build(spark.createDataFrame([(1, 2), (3, 4)], "a long, b long"))
    log = str(tmp_path / "runs")

    def method(n, a, b):
        with open(log, "a") as out:
            out.write("run\n")
        return np.arange(n) // 2

    found = baselines.in_one_task(g, method)
    assert found.count() == 4 and len(found.collect()) == 4
    with open(log) as lines:
        assert len(lines.readlines()) == 1
