"""Cost measures: time to the k-th answer, delays, memory, sizes, scaling, outcomes, Spark's own costs."""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from statistics import mean, median

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import anyk, equireduce, stacked
from ..plans import predicates as P
from ..plans.query import Query


def timed(run: Callable[[], DataFrame], repeats: int = 5, warm: int = 1, limit_s: float = 7200) -> dict:
    """Median seconds of several runs after warm ones; what ended it, if it did not end well."""
    seconds = []
    for n in range(warm + repeats):
        began = time.perf_counter()
        try:
            rows = run().count()
        except Exception as why:  # the outcome is the measurement
            return {"outcome": type(why).__name__, "seconds": None, "rows": None}
        took = time.perf_counter() - began
        if took > limit_s:
            return {"outcome": "over the limit", "seconds": took, "rows": rows}
        if n >= warm:
            seconds.append(took)
    return {"outcome": "done", "seconds": median(seconds), "rows": rows}


def time_to_k(query: Query, ks: list[int], methods: dict[str, Callable[[Query, int], DataFrame]], spark: SparkSession, repeats: int = 1) -> DataFrame:
    """(method, k, seconds, rows, outcome): TT(k), everything from the start of the query included."""
    rows = []
    for name, run in methods.items():
        for k in ks:
            got = timed(lambda run=run, k=k: run(query, k), repeats, 0)
            rows.append((name, k, got["seconds"], got["rows"], got["outcome"]))
    return spark.createDataFrame(rows, "method string, k long, seconds double, rows long, outcome string")


def delays(query: Query, ks: int, variants: list[str], spark: SparkSession, window: int = 1000, method: str = "auto") -> DataFrame:
    """(variant, window, answers, delay, first): mean seconds between answers in windows of so many, and the time of the first one.

    The walk alone is timed; the passes before it are the same for all variants.
    """
    g = stacked.stack(query, method)
    made = stacked.instance(g, ks)
    rows = []
    for variant in variants:
        stamps: list[float] = [time.perf_counter()]
        for n, _ in enumerate(anyk.enumerate_answers(made, variant, stamps), 1):
            if n >= ks:
                break
        gaps = [b - a for a, b in zip(stamps, stamps[1:], strict=False)]
        rows += [(variant, i // window, len(gaps[i : i + window]), mean(gaps[i : i + window]), gaps[0]) for i in range(0, len(gaps), window)]
    return spark.createDataFrame(rows, "variant string, window long, answers long, delay double, first double")


def memory(query: Query, ks: list[int], variants: list[str], spark: SparkSession, method: str = "auto") -> DataFrame:
    """(variant, k, listed, candidates): MEM(k), what an enumerator holds after k answers; equal in every run."""
    g = stacked.stack(query, method)
    made, rows = stacked.instance(g, max(ks)), []
    for variant in variants:
        for k in ks:
            cost = anyk.Cost()
            for n, _ in enumerate(anyk.enumerate_answers(made, variant, cost=cost), 1):
                if n >= k:
                    break
            rows.append((variant, k, cost.listed, cost.candidates))
    return spark.createDataFrame(rows, "variant string, k long, listed long, candidates long")


def connector_sizes(s: DataFrame, t: DataFrame, where: P.Condition, methods: list[str]) -> DataFrame:
    """(method, nodes, edges, depth, dup_factor) of the connectors of one edge."""
    out = None
    for m in methods:
        graph = equireduce.connector(s, t, where, m)
        one = graph.size().select(F.lit(m).alias("method"), "nodes", "edges", F.lit(graph.depth).alias("depth"), F.lit(graph.dup_factor).alias("dup_factor"))
        out = one if out is None else out.unionByName(one)
    return out


def spark_costs(spark: SparkSession, runs: dict[str, Callable[[], DataFrame]]) -> DataFrame:
    """(run, seconds, stages, tasks, read_mb, shuffled_mb, spilled_mb, task_seconds): what Spark's own store says of each run."""
    store, context, rows = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext, []
    for name, run in runs.items():
        group = f"costs-{name}-{time.time_ns()}"
        context.setJobGroup(group, name)
        began = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        took = time.perf_counter() - began
        context.setJobGroup("", "")
        context._jsc.sc().listenerBus().waitUntilEmpty()
        ids = {s for job in context.statusTracker().getJobIdsForGroup(group) for s in context.statusTracker().getJobInfo(job).stageIds}
        totals = [0, 0, 0, 0, 0, 0]
        for stage in ids:
            info = context.statusTracker().getStageInfo(stage)
            if info is None or not info.numCompletedTasks:
                continue  # skipped: its files were there already
            data = store.lastStageAttempt(stage)
            for i, x in enumerate((1, data.numCompleteTasks(), data.inputBytes(), data.shuffleWriteBytes(), data.diskBytesSpilled(), data.executorRunTime())):
                totals[i] += x
        rows.append((name, took, totals[0], totals[1], totals[2] / 1e6, totals[3] / 1e6, totals[4] / 1e6, totals[5] / 1e3))
    return spark.createDataFrame(rows, "run string, seconds double, stages long, tasks long, read_mb double, shuffled_mb double, spilled_mb double, task_seconds double")


def scaling_exponent(sizes: list[int], seconds: list[float]) -> float:
    """Slope of log time over log size by least squares; about 1 for quasi-linear methods."""
    x, y = [math.log(n) for n in sizes], [math.log(s) for s in seconds]
    mx, my = mean(x), mean(y)
    return sum((a - mx) * (b - my) for a, b in zip(x, y, strict=True)) / sum((a - mx) ** 2 for a in x)


def growth(spark: SparkSession, points: dict[str, list[tuple[int, Callable[[], DataFrame]]]]) -> DataFrame:
    """(series, points, exponent): how the time of each series grows with its sizes."""
    rows = []
    for name, series in points.items():
        seconds = [timed(run, 1, 1)["seconds"] for _, run in series]
        done = [(n, s) for (n, _), s in zip(series, seconds, strict=True) if s]
        rows.append((name, len(done), scaling_exponent([n for n, _ in done], [s for _, s in done]) if len({n for n, _ in done}) > 1 else None))
    return spark.createDataFrame(rows, "series string, points long, exponent double")


def bounds(n: int, k: int, p: int, depth: int, edges: int) -> dict[str, float]:
    """The published cost terms for given sizes, without constants."""
    log = math.log2(max(2, n))
    return {
        "floor": n + k,
        "acyclic": n * log**p + k * math.log2(max(2, k)),
        "memory": n * log ** (p - 1) * math.log2(max(2, log)) + k,
        "connector": edges + k * math.log2(max(2, k)) + k * depth,
        "direct": n * n + k * math.log2(max(2, k)),
        "binary": n * log + k * math.log2(max(2, k)),
        "chain": n * log + k * n,
    }
