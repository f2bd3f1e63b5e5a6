"""The experiments: run-time grids, phases, group counts, tree nodes, edge samples, memory, case study, data sets."""

from __future__ import annotations

import resource
import time
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession

from bipercolate import graph, maxbiclique, measures, overlap, partial
from bipercolate.communities import METHODS, detect
from bipercolate.graph import encode
from bipercolate.sources.sinks import consume
from bipercolate.sources.workloads import ALPHAS, BETAS, DEFAULT_ALPHA, DEFAULT_BETA, GRAPHS

METRICS = "graph string, alpha int, beta int, method string, metric string, value double, status string"


def timed(run: Callable[[], DataFrame]) -> float:
    began = time.time()
    consume(run())
    return time.time() - began


def within_budget(spark: SparkSession, run: Callable[[], DataFrame], budget_s: float) -> tuple[float, str]:
    """Seconds and "ok", or the budget and "timeout": jobs of a run beyond its budget are cancelled."""
    import threading

    context, tag = spark.sparkContext, f"budget-{time.time_ns()}"
    context.addJobTag(tag)
    late = threading.Event()

    def stop() -> None:
        late.set()
        context.cancelJobsWithTag(tag)

    timer = threading.Timer(budget_s, stop)
    timer.start()
    try:
        return timed(run), "ok"
    except Exception:
        if late.is_set():
            return budget_s, "timeout"
        raise
    finally:
        timer.cancel()
        context.removeJobTag(tag)


def grid(spark: SparkSession, sf_dir: str, graphs: Iterable[str], sizes: Iterable[tuple[int, int]], methods: Iterable[str] = METHODS, budget_s: float = 600) -> DataFrame:
    """Run time of each method, graph and (alpha, beta), from the encoded graph on."""
    rows = []
    for g in graphs:
        e = encode(GRAPHS[g](spark, sf_dir))
        for a, b in sizes:
            for m in methods:
                s, status = within_budget(spark, lambda e=e, a=a, b=b, m=m: detect(e, a, b, m).labels, budget_s)
                rows.append((g, a, b, m, "seconds", s, status))
    return spark.createDataFrame(rows, METRICS)


def phases(spark: SparkSession, sf_dir: str, graphs: Iterable[str], sizes: Iterable[tuple[int, int]]) -> DataFrame:
    """Enumeration alone, and what either kind of partial groups adds to it."""
    rows = []
    for g in graphs:
        e = encode(GRAPHS[g](spark, sf_dir))
        for a, b in sizes:
            began = time.time()
            found = maxbiclique.enumerate_bicliques(e.edges, a, b, qualified_only=True)
            rows.append((g, a, b, "enumeration", "seconds", time.time() - began, "ok"))
            rows.append((g, a, b, "prefix_groups", "seconds", timed(lambda: partial.by_prefix(found.bicliques, a, b)), "ok"))
            rows.append((g, a, b, "seed_groups", "seconds", timed(lambda: partial.by_seed(found.bicliques, found.seeds, a, b)), "ok"))
    return spark.createDataFrame(rows, METRICS)


def group_counts(spark: SparkSession, sf_dir: str, graphs: Iterable[str], sizes: Iterable[tuple[int, int]]) -> DataFrame:
    rows = []
    for g in graphs:
        e = encode(GRAPHS[g](spark, sf_dir))
        for a, b in sizes:
            rows += [(g, a, b, "", k, float(n), "ok") for k, n in measures.counts(e, a, b).items()]
    return spark.createDataFrame(rows, METRICS)


def tree_nodes(spark: SparkSession, sf_dir: str, graphs: Iterable[str], sizes: Iterable[tuple[int, int]]) -> DataFrame:
    rows = []
    for g in graphs:
        e = encode(GRAPHS[g](spark, sf_dir))
        for a, b in sizes:
            found = maxbiclique.enumerate_bicliques(e.edges, a, b, qualified_only=True)
            for m in ("listing", "listing_pruned", "listing_seeded"):
                rows += [(g, a, b, m, k, float(n), "ok") for k, n in measures.nodes(e, a, b, m, found).items()]
    return spark.createDataFrame(rows, METRICS)


def scale(spark: SparkSession, sf_dir: str, graphs: Iterable[str], alpha: int, beta: int, method: str = "listing_seeded", percents: Iterable[int] = (20, 40, 60, 80, 100)) -> DataFrame:
    """Run time on nested samples of the edges."""
    rows = []
    for g in graphs:
        edges = encode(GRAPHS[g](spark, sf_dir), "id").edges
        for p in percents:
            rows.append((g, alpha, beta, method, f"seconds at {p} %", timed(lambda p=p, edges=edges: detect(graph.sample(edges, p), alpha, beta, method).labels), "ok"))
    return spark.createDataFrame(rows, METRICS)


def _executor_metrics(spark: SparkSession) -> list[dict]:
    """Per executor: peak memory, and shuffled bytes so far, from Spark's status store (kept also without a web page)."""
    store = spark.sparkContext._jsc.sc().statusStore()
    rows, every = [], store.executorList(True)
    for k in range(every.size()):
        one = every.apply(k)
        peak = one.peakMemoryMetrics()
        names = ("JVMHeapMemory", "JVMOffHeapMemory", "OnHeapExecutionMemory", "OffHeapExecutionMemory", "ProcessTreePythonRSSMemory")
        peaks = {n: peak.get().getMetricValue(n) if peak.isDefined() else 0 for n in names}
        rows.append({"written": one.totalShuffleWrite(), "read": one.totalShuffleRead(), **peaks})
    return rows


def _spilled(spark: SparkSession) -> int:
    """Bytes that all stages so far spilled to disk."""
    context = spark.sparkContext
    none = context._gateway.new_array(context._jvm.double, 0)
    stages = context._jsc.sc().statusStore().stageList(context._jvm.java.util.ArrayList(), False, False, none, context._jvm.java.util.ArrayList())
    return sum(stages.apply(k).diskBytesSpilled() for k in range(stages.size()))


def memory(spark: SparkSession, sf_dir: str, graphs: Iterable[str], alpha: int, beta: int, methods: Iterable[str] = METHODS) -> DataFrame:
    """Per method: the highest memory of any executor so far (MB; peaks never fall, so methods run in the order of their need), and bytes shuffled and spilled by the run."""
    rows = []
    for g in graphs:
        for m in methods:
            before, spilled = _executor_metrics(spark), _spilled(spark)
            consume(detect(GRAPHS[g](spark, sf_dir), alpha, beta, m).labels)
            after = _executor_metrics(spark)
            total = lambda rows, name: sum(r[name] for r in rows) / 1e6
            found = {
                "peak_heap_mb": max(r["JVMHeapMemory"] for r in after) / 1e6, "peak_execution_mb": max(r["OnHeapExecutionMemory"] for r in after) / 1e6,
                "peak_python_mb": max(r["ProcessTreePythonRSSMemory"] for r in after) / 1e6, "shuffle_mb": total(after, "written") - total(before, "written"),
                "spill_mb": (_spilled(spark) - spilled) / 1e6, "driver_python_mb": resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1e3,
            }
            rows += [(g, alpha, beta, m, k, float(v), "ok") for k, v in found.items()]
    return spark.createDataFrame(rows, METRICS)


def data_sets(spark: SparkSession, sf_dir: str, graphs: Iterable[str], alpha: int = 2, beta: int = 2) -> DataFrame:
    """Vertices, edges, mean degrees, maximal bicliques, overlap edges."""
    rows = []
    for g in graphs:
        e = encode(GRAPHS[g](spark, sf_dir))
        for k, n in graph.stats(e.edges).first().asDict().items():
            rows.append((g, alpha, beta, "", k, float(n), "ok"))
        found = maxbiclique.enumerate_bicliques(e.edges).bicliques
        rows.append((g, alpha, beta, "", "maximal_bicliques", float(found.count()), "ok"))
        rows.append((g, alpha, beta, "", "overlap_edges", float(overlap.edges(found, alpha, beta).count()), "ok"))
    return spark.createDataFrame(rows, METRICS)


def speed_ups(times: DataFrame, base: str = "overlap") -> DataFrame:
    """Ratio of the base method's time to each method's, where both ended."""
    ok = times.filter("metric = 'seconds' and status = 'ok'").select("graph", "alpha", "beta", "method", "value")
    ref = ok.filter(ok.method == base).select("graph", "alpha", "beta", ok.value.alias("base"))
    return ok.join(ref, ["graph", "alpha", "beta"]).selectExpr("graph", "alpha", "beta", "method", "base / value AS speed_up")


def report(spark: SparkSession, sf_dir: str, budget_s: float = 120) -> dict[str, DataFrame]:
    """All experiments on graphs small enough for one machine: run times and speed-ups, phases, group counts, tree nodes, samples, memory, data sets."""
    every = [(a, b) for a in ALPHAS for b in BETAS]
    few = ["user_day", "nation_brand"]
    times = grid(spark, sf_dir, ["nation_brand"], [(DEFAULT_ALPHA, DEFAULT_BETA), (2, 2), (8, 8)], budget_s=budget_s).union(grid(spark, sf_dir, ["user_day"], [(2, 2), (3, 3)], budget_s=budget_s))
    return {
        "run_times": times, "speed_ups": speed_ups(times), "phases": phases(spark, sf_dir, few, [(2, 2), (3, 3)]),
        "group_counts": group_counts(spark, sf_dir, ["nation_brand"], every).union(group_counts(spark, sf_dir, ["user_day", "cust_brand"], [(2, 2), (3, 3)])),
        "tree_nodes": tree_nodes(spark, sf_dir, few, [(2, 2), (3, 3)]), "edge_samples": scale(spark, sf_dir, ["user_day"], 3, 3),
        "memory": memory(spark, sf_dir, ["user_day"], 3, 3), "data_sets": data_sets(spark, sf_dir, ["nation_brand", "user_day", "page_link"]),
    }
