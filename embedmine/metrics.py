"""Measures: counts of a run, times, ratios of an ablation, sizes, memory."""

from __future__ import annotations

import inspect
import time
from collections.abc import Callable
from statistics import median

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .plans.model import MiningResult


def funnel(spark: SparkSession, result: MiningResult) -> DataFrame:
    """step, candidates (of a run with ``refused``, else null), canonical, processed, kept."""
    rows = [(r["step"], r.get("candidates"), r["canonical"], r["processed"], r.get("kept", 0)) for r in result.funnel]
    return spark.createDataFrame(rows, "step int, candidates long, canonical long, processed long, kept long")


def level_counts(spark: SparkSession, result: MiningResult) -> DataFrame:
    """size, n: interesting subgraphs of each size."""
    return spark.createDataFrame([(r["step"], r["processed"]) for r in result.funnel if r["processed"]], "size int, n long")


def timed(run: Callable[[], DataFrame], repeats: int = 3) -> float:
    """Median seconds of a run to the last row, start-up apart (one run before warms up)."""
    seconds = []
    for _ in range(repeats + 1):
        began = time.time()
        run().write.format("noop").mode("overwrite").save()
        seconds.append(time.time() - began)
    return median(seconds[1:])


def ablate(with_it: Callable[[], DataFrame], without: Callable[[], DataFrame], repeats: int = 1) -> dict[str, float]:
    """Seconds with and without an optimisation, and the slowdown factor."""
    a, b = timed(with_it, repeats), timed(without, repeats)
    return {"with": a, "without": b, "slowdown": b / a}


def speedup(spark: SparkSession, times: dict[int, float], reference: int) -> DataFrame:
    """workers, seconds, speedup against ``reference`` workers, ideal."""
    return spark.createDataFrame([(w, t, times[reference] / t, w / reference) for w, t in sorted(times.items())], "workers int, seconds double, speedup double, ideal double")


def parquet_bytes(df: DataFrame) -> int:
    """Bytes of the files that a written table is read from."""
    spark = df.sparkSession
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    total = 0
    for f in df.inputFiles():
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f)
        total += p.getFileSystem(conf).getFileStatus(p).getLen()
    return total


def peak_memory_mb(spark: SparkSession) -> dict[str, float]:
    """Peak heap of each executor (the driver's own where it runs the tasks), as the session has recorded it so far."""
    out = {}
    listed = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    for i in range(listed.size()):
        one = listed.apply(i)
        peak = one.peakMemoryMetrics()
        heap = peak.get().getMetricValue("JVMHeapMemory") if peak.isDefined() else 0
        if not heap:  # nothing recorded yet: what the pools of this process have held
            pools = spark.sparkContext._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans()
            heap = sum(p.getPeakUsage().getUsed() for p in pools if p.getType().toString() == "Heap memory")
        out[one.id()] = round(heap / 1e6, 1)
    return out


def lines_of_code(*functions: Callable) -> int:
    """Lines of an application's own functions without blank lines and docstrings."""
    total = 0
    for f in functions:
        source = [x for x in inspect.getsource(f).splitlines() if x.strip()]
        total += len(source) - len((f.__doc__ or "").strip().splitlines())
    return total


def messages(spark: SparkSession, runs: dict[str, list[int]]) -> DataFrame:
    """paradigm, messages: rows that passed between steps or owners, summed over a run."""
    return spark.createDataFrame([(name, sum(n)) for name, n in runs.items()], "paradigm string, messages long")


def hot_spots(df: DataFrame, key: str) -> DataFrame:
    """n_keys, most, mean, share of the key with the most rows."""
    n = df.groupBy(key).agg(F.count(F.lit(1)).alias("n"))
    return n.agg(F.count(F.lit(1)).alias("n_keys"), F.max("n").alias("most"), F.round(F.avg("n"), 6).alias("mean"), F.round(F.max("n") / F.sum("n"), 6).alias("share"))


def phase_shares(result: MiningResult) -> dict[str, float]:
    """Share of a run's seconds by what the engine does apart: growing (read, generate, canonicality, filter, write),
    aggregation by pattern with the aggregation filter, and the path store (write, decode)."""
    total = sum(r.get("seconds", 0) for r in result.funnel) or 1.0
    grow = sum(r.get("seconds_grow", 0) for r in result.funnel)
    by_pattern = sum(r.get("seconds_aggregate", 0) for r in result.funnel)
    return {"grow": round(grow / total, 4), "aggregate": round(by_pattern / total, 4), "store": round(max(0.0, 1 - (grow + by_pattern) / total), 4)}


def phase_breakdown(g, size: int) -> dict[str, float]:
    """Share of seconds of a vertex-mode step that grows to ``size``: read, generate, canonicality and
    grouping, pattern aggregation, write. Plans of growing length are timed and their times subtracted."""
    from .apps.motifs import embeddings
    from .functions.canonical import words
    from .operators import aggregate, expand
    from .plans.scratch import written

    level = written(embeddings(g, size - 1), "level")
    k = size - 1
    near = g.shared(g.adjacency.select("vid", "nbr"))
    read = timed(lambda: level, 1)
    generate = timed(lambda: level.withColumn("vid", F.explode(F.array(*words(k)))).join(near, "vid"), 1)
    grown = lambda: expand.grown_vertices(expand.vertex_candidates(level, g, k).where("ok"), k)
    check = timed(grown, 1)
    pattern = timed(lambda: aggregate.by_quick(grown().drop("touch", "ok"), {"n": F.count(F.lit(1))}), 1)
    began = time.time()
    written(grown(), "level")
    write = time.time() - began
    parts = {"read": read, "generate": max(0.0, generate - read), "canonicality": max(0.0, check - generate), "pattern": max(0.0, pattern - check), "write": max(0.0, write - check)}
    total = sum(parts.values()) or 1.0
    return {name: round(x / total, 4) for name, x in parts.items()}
