"""Cliques: enumeration, maximal and frequent ones."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.canonical import words
from ..plans.model import MiningApp
from ..plans.scratch import spread, written
from ..sources.graph import PropertyGraph


def app(max_size: int) -> MiningApp:
    """Cliques as a filter-process application: prune by the newest vertex, no aggregation by pattern."""
    return MiningApp("cliques", filter=lambda e: e.is_clique & F.lit(e.size <= max_size), output=lambda e: [F.lit(e.size).alias("k"), F.array_join(e.array(), "-").alias("members")], termination=lambda e: F.lit(e.size >= max_size))


def forward(g: PropertyGraph) -> DataFrame:
    """vid, ahead: each vertex's larger neighbours. After a relabelling by degree no list exceeds the root of twice the edges."""
    return g.adjacency.where("nbr > vid").groupBy("vid").agg(F.collect_list("nbr").alias("ahead"))


def open_cliques(g: PropertyGraph, max_size: int) -> Iterator[tuple[int, DataFrame]]:
    """(k, cliques of k vertices with ``open``, the larger vertices that touch all of them) for k below ``max_size``.

    A clique's canonical order is the rising one: each open vertex is an
    extension, and the child's list is the intersection with that vertex's own list.
    """
    if max_size < 2:
        return
    ahead = written(spread(forward(g), "vid"), "forward")
    now = ahead.select(F.col("vid").alias("w0"), F.col("ahead").alias("open"))
    yield 1, now
    for k in range(1, max_size - 1):
        grown = now.select(*words(k), "open", F.explode("open").alias(f"w{k}"))
        joined = grown.join(g.shared(ahead.withColumnRenamed("vid", f"w{k}")), f"w{k}")
        now = joined.select(*words(k + 1), F.array_intersect("open", "ahead").alias("open")).where(F.size("open") > 0)
        now = written(spread(now, *words(k + 1)), f"cliques-{k + 1}")
        yield k + 1, now


def find_cliques(g: PropertyGraph, max_size: int = 5) -> dict[int, DataFrame]:
    """Cliques by size, w0 < w1 < ..."""
    out = {1: g.vertices.select(F.col("vid").alias("w0"))}
    for k, f in open_cliques(g, max_size):
        out[k + 1] = f.select(*words(k), F.explode("open").alias(f"w{k}"))
    return out


def clique_counts(g: PropertyGraph, max_size: int = 5) -> DataFrame:
    """k, n; the largest size is the sum of its parents' lists, never enumerated."""
    used = g.edges.select(F.explode(F.array("src", "dst")).alias("w0")).distinct()
    out = used.agg(F.count(F.lit(1)).alias("n")).select(F.lit(1).alias("k"), "n")
    for k, f in open_cliques(g, max_size):
        out = out.unionByName(f.agg(F.coalesce(F.sum(F.size("open")), F.lit(0)).cast("long").alias("n")).select(F.lit(k + 1).alias("k"), "n"))
    return out.where("n > 0")


def maximal_cliques(g: PropertyGraph, max_size: int) -> DataFrame:
    """k, members: cliques up to ``max_size`` in no other clique of the graph. Those of the largest size are tested too."""
    out = None
    adjacency = g.shared(g.adjacency.select("vid", "nbr"))
    for k, f in find_cliques(g, max_size).items():
        key = f.select(F.array_join(F.array(*words(k)), "-").alias("members"), F.array(*words(k)).alias("w"))
        met = key.select("members", F.explode("w").alias("vid")).join(adjacency, "vid").groupBy("members", "nbr").agg(F.count(F.lit(1)).alias("n"))
        larger = met.where(F.col("n") == k).select("members").distinct()
        row = key.join(larger, "members", "left_anti").select(F.lit(k).alias("k"), "members")
        out = row if out is None else out.unionByName(row)
    return out


def frequent_cliques(g: PropertyGraph, support: int, max_size: int) -> DataFrame:
    """k, lbls, support: cliques by label multiset. Members of equal label are one orbit, so the
    support is the least number of distinct vertices over the labels."""
    labels = g.shared(g.vertices.select("vid", F.coalesce("vlabel_text", F.lit("")).alias("t")))
    out = None
    for k, f in find_cliques(g, max_size).items():
        if k == 1:
            continue
        rows = f.select(F.array_join(F.array(*words(k)), "-").alias("members"), F.explode(F.array(*words(k))).alias("vid")).join(labels, "vid")
        named = rows.groupBy("members").agg(F.array_join(F.array_sort(F.collect_list("t")), "|").alias("lbls"))
        sizes = rows.join(named, "members").groupBy("lbls", "t").agg(F.countDistinct("vid").alias("size"))
        row = sizes.groupBy("lbls").agg(F.min("size").alias("support")).where(F.col("support") >= support).select(F.lit(k).alias("k"), "lbls", "support")
        out = row if out is None else out.unionByName(row)
    return out
