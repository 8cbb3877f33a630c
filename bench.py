"""Headline queries on one machine: prints one JSON line.

BENCH_SF_DIR: the tables (default sf0.1). BENCH_CPUS: threads. BENCH_LIMIT_S: nothing starts after so many seconds, and
what then still runs is cancelled at twice that.
"""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
LIMIT_S = float(os.environ.get("BENCH_LIMIT_S", "600"))


def main() -> None:
    from pyspark.sql import SparkSession

    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    from blockfinder.operators import metrics
    from blockfinder.plans.experiments import limited
    from blockfinder.plans.pipeline import partition
    from blockfinder.queries import QUERIES, load_all
    from blockfinder.queries.tables import planted

    load_all()
    took, results = {}, {}
    began = time.perf_counter()

    def timed(name: str, run):
        """The result of ``run``, whose seconds are kept; what has no time left or runs out of it says so."""
        spent = time.perf_counter() - began
        if spent > LIMIT_S:
            results[name] = {"status": "not started"}
            return None
        status, out, seconds = limited(spark, run, max(60.0, 2 * LIMIT_S - spent))
        if status == "ok":
            took[name] = round(seconds, 3)
            return out
        results[name] = {"status": status, "seconds": round(seconds, 1)}
        return None

    def blocks(name: str, table: str, key: str, block: str | None, kinds=("cut", "mod"), seed: int = 0) -> None:
        if time.perf_counter() - began > LIMIT_S:
            results.update({f"{name}_{kind}": {"status": "not started"} for kind in kinds})
            return
        made = time.perf_counter()
        params, g = planted(spark, SF, table, key, block, mean_degree=40.0, seed=seed)
        made = time.perf_counter() - made
        for kind in kinds:
            r = timed(f"{name}_{kind}", lambda kind=kind: partition(g, kind, seed=seed))
            if r is not None:
                s = {k: round(v, 4) for k, v in metrics.scores(params.nodes, r.blocks).items()}
                results[f"{name}_{kind}"] = {"status": "ok"} | s | {k: round(v, 3) for k, v in r.timings.items()} | {"n": g.n, "m": g.m, "generated_s": round(made, 1)}

    def write(name: str):
        return QUERIES[name](spark, SF).write.format("noop").mode("overwrite").save()

    blocks("customer_nation", "customer", "c_custkey", "c_nationkey")
    blocks("part_brand", "part", "p_partkey", "p_brand")
    for name in ("edges_part_coorder", "degrees_part", "weights_cut", "modularity_by_brand", "op_window_rank", "op_join_interval"):
        timed(name, lambda name=name: write(name))
    blocks("events", "events", "event_id", None, ("cut",))
    blocks("orders", "orders", "o_orderkey", None, ("cut",), 1)
    blocks("events_again", "events", "event_id", None, ("mod",), 1)
    blocks("orders_again", "orders", "o_orderkey", None, ("mod",))
    print(json.dumps({"metric": "headline queries", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": SF.rsplit("sf", 1)[-1], "results": results}))


if __name__ == "__main__":
    main()
