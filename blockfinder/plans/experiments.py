"""Runs of several methods on several graphs: status, quality, time, shares, and what a plan moves."""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, metrics
from ..operators.graph import Graph
from .pipeline import partition

TABLE = "workload string, seed int, method string, status string, n long, m long, k_true long, k_found long, acc double, ari double, f1 double, recall double, precision double, feat_s double, emb_s double, select_s double, total_s double"

#: The two variants and the five methods they are compared with.
METHODS: dict[str, Callable[[Graph], object]] = {
    "cut": lambda g: partition(g, "cut"),
    "mod": lambda g: partition(g, "mod"),
    "markov chain": lambda g: baselines.sbm_mcmc(g),
    "greedy modularity": lambda g: baselines.greedy_modularity(g, "exact"),
    "spectral modularity": lambda g: baselines.spectral_modularity(g),
    "parallel inference": lambda g: baselines.sbm_parallel(g),
    "belief propagation": lambda g: baselines.belief_propagation(g),
}


def limited(spark: SparkSession, run: Callable[[], object], limit_s: float) -> tuple[str, object, float]:
    """(status, result, seconds) of ``run``: ``ok``, ``OOT`` if its jobs were cancelled at the limit, ``OOM``, or ``failed``.

    The limit reaches whatever runs as jobs of this thread; what the driver does by itself ends first.
    """
    context, group, late = spark.sparkContext, f"limited-{uuid.uuid4().hex}", threading.Event()

    def stop():
        late.set()
        context.cancelJobGroup(group)

    context.setJobGroup(group, "a run with a limit", interruptOnCancel=True)
    timer = threading.Timer(limit_s, stop)
    timer.start()
    began = time.perf_counter()
    try:
        out = run()
        took = time.perf_counter() - began
        return ("OOT", None, limit_s) if late.is_set() else ("ok", out, took)
    except Exception as problem:
        text = f"{type(problem).__name__} {problem}"
        status = "OOT" if late.is_set() else "OOM" if "OutOfMemory" in text or "MemoryError" in text else "failed"
        return status, None, limit_s if late.is_set() else time.perf_counter() - began
    finally:
        timer.cancel()
        context.setLocalProperty("spark.jobGroup.id", None)
        context.setLocalProperty("spark.job.interruptOnCancel", None)


def quality_table(spark: SparkSession, graphs: Iterable[tuple[str, int, DataFrame, Graph]], methods: dict[str, Callable[[Graph], object]] = METHODS, limit_s: float = 600.0) -> DataFrame:
    """A row for each graph (workload, seed, truth, graph) and method. Runs without a result have null measures."""
    rows = []
    for workload, seed, truth, g in graphs:
        k_true = truth.select("block").distinct().count()
        for name, method in methods.items():

            def run(method=method, g=g):
                out = method(g)
                blocks = getattr(out, "blocks", out)
                blocks.count()
                return out, blocks

            status, out, took = limited(spark, run, limit_s)
            if status != "ok":
                rows.append((workload, seed, name, status, g.n, g.m, k_true, None, *[None] * 8, float(took)))
                continue
            result, blocks = out
            s = metrics.scores(truth, blocks)
            stages = getattr(result, "timings", {})
            rows.append((workload, seed, name, status, g.n, g.m, k_true, s["k_found"], *[float(s[c]) for c in ("acc", "ari", "f1", "recall", "precision")], *[stages.get(c) for c in ("features", "embedding", "selection")], float(took)))
    return spark.createDataFrame(rows, TABLE)


def summarise(table: DataFrame) -> DataFrame:
    """Means over the seeds of each workload and method, with the number of runs that ended."""
    means = [F.avg(c).alias(c) for c in ("acc", "ari", "f1", "recall", "precision", "feat_s", "emb_s", "select_s", "total_s", "k_found")]
    return table.groupBy("workload", "n", "method").agg(F.count(F.lit(1)).alias("runs"), F.sum((F.col("status") == "ok").cast("long")).alias("ended"), *means)


def stage_shares(table: DataFrame) -> DataFrame:
    """The share of each stage of the time of runs that have stages."""
    whole = F.col("feat_s") + F.col("emb_s") + F.col("select_s")
    return table.where("status = 'ok' and select_s is not null").select("workload", "seed", "method", "n", "feat_s", "emb_s", "select_s", *[(F.col(c) / whole).alias(s) for c, s in (("feat_s", "feat_share"), ("emb_s", "emb_share"), ("select_s", "select_share"))])


def compare(table: DataFrame, base: str) -> DataFrame:
    """How many times longer ``base`` takes than each method, by workload; where base has no result, at least that."""
    rows = summarise(table)
    other = rows.where(F.col("method") == base).select("workload", F.col("total_s").alias("base_s"), (F.col("ended") < F.col("runs")).alias("at_least"))
    return rows.where(F.col("method") != base).join(F.broadcast(other), "workload").select("workload", "method", (F.col("base_s") / F.col("total_s")).alias("speed_up"), "at_least")


def plan_cost(spark: SparkSession, run: Callable[[], object]) -> dict[str, float]:
    """Jobs, stages, tasks, rows and bytes that ``run`` reads, shuffles and spills, from the status of its stages."""
    context, group = spark.sparkContext, f"cost-{uuid.uuid4().hex}"
    context.setJobGroup(group, "a run whose cost is counted")
    began = time.perf_counter()
    try:
        run()
    finally:
        context.setLocalProperty("spark.jobGroup.id", None)
    took = time.perf_counter() - began
    tracker, store = context.statusTracker(), context._jsc.sc().statusStore()
    jobs = tracker.getJobIdsForGroup(group)
    stages = {s for j in jobs if tracker.getJobInfo(j) for s in tracker.getJobInfo(j).stageIds}
    out = {"jobs": len(jobs), "stages": 0, "tasks": 0, "seconds": took, "rows_read": 0, "bytes_read": 0, "shuffle_rows": 0, "shuffle_bytes": 0, "spill_bytes": 0}
    for s in stages:
        try:
            x = store.lastStageAttempt(s)
        except Exception:  # a stage that was skipped has no attempt
            continue
        if x.status().toString() != "COMPLETE":
            continue
        out["stages"] += 1
        out["tasks"] += x.numTasks()
        for name, value in (("rows_read", x.inputRecords()), ("bytes_read", x.inputBytes()), ("shuffle_rows", x.shuffleWriteRecords()), ("shuffle_bytes", x.shuffleWriteBytes()), ("spill_bytes", x.diskBytesSpilled())):
            out[name] += value
    return out
