"""Helpers around a graph: degrees, triangles, clustering, components, k-core, rank iteration."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import written
from ..sources.graph import PropertyGraph


def degrees(g: PropertyGraph) -> DataFrame:
    return g.degrees.select("vid", F.col("d").alias("value"))


def degree_histogram(g: PropertyGraph) -> DataFrame:
    return degrees(g).groupBy(F.col("value").alias("vid")).agg(F.count(F.lit(1)).alias("value"))


def triangles(g: PropertyGraph) -> DataFrame:
    """vid, value: triangles at each vertex with an edge."""
    if not g.small:
        return g.triples.select("vid", F.col("tri").alias("value"))
    e = g.edges.select("src", "dst")
    t = e.select(F.col("src").alias("x"), F.col("dst").alias("y")).join(g.shared(e.select(F.col("src").alias("y"), F.col("dst").alias("z"))), "y").join(g.shared(e.select(F.col("src").alias("x"), F.col("dst").alias("z"))), ["x", "z"], "left_semi")
    n = t.select(F.explode(F.array("x", "y", "z")).alias("vid")).groupBy("vid").agg(F.count(F.lit(1)).alias("t"))
    return degrees(g).select("vid").join(n, "vid", "left").select("vid", F.coalesce("t", F.lit(0)).alias("value"))


def clustering(g: PropertyGraph) -> DataFrame:
    """vid, value: closed over possible pairs of neighbours (0 below two neighbours)."""
    d = degrees(g).withColumnRenamed("value", "d")
    ratio = F.when(F.col("d") > 1, 2 * F.col("value") / (F.col("d") * (F.col("d") - 1))).otherwise(0.0)
    return triangles(g).join(d, "vid").select("vid", F.round(ratio, 6).alias("value"))


def components(g: PropertyGraph) -> DataFrame:
    """vid, value: the smallest vertex reachable, by contraction of stars; rounds grow with the logarithm of the size."""
    now = written(g.edges.select(F.col("dst").alias("a"), F.col("src").alias("b")), "stars")
    seen = None
    while True:
        mark = tuple(now.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("a", "b"))).first())
        if mark == seen or not mark[0]:
            break
        seen = mark
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        floor = large.groupBy("a").agg(F.min("b").alias("m"))
        tied = large.join(floor, "a").where("b <> m").select(F.greatest("b", "m").alias("a"), F.least("b", "m").alias("b"))
        now = written(tied.unionByName(floor.select("a", F.col("m").alias("b"))).distinct(), "stars")
    return now.select(F.col("a").alias("vid"), F.col("b").alias("value")).unionByName(now.select(F.col("b").alias("vid"), F.col("b").alias("value")).distinct())


def k_core(g: PropertyGraph, k: int) -> DataFrame:
    """vid, value: vertices of the k-core with their degree inside it."""
    now = written(g.adjacency.select("vid", "nbr"), "core")
    size = None
    while True:
        n = now.count()
        if n == size or not n:
            return now.groupBy("vid").agg(F.count(F.lit(1)).alias("value"))
        size = n
        keep = now.groupBy("vid").agg(F.count(F.lit(1)).alias("d")).where(F.col("d") >= k).select("vid")
        now = written(now.join(keep, "vid", "left_semi").join(keep.withColumnRenamed("vid", "nbr"), "nbr", "left_semi").select("vid", "nbr"), "core")


def page_rank(g: PropertyGraph, rounds: int = 5, damping: float = 0.85) -> DataFrame:
    """vid, value: the vertex-centric iteration of the contrast class, a fixed number of rounds."""
    d = written(degrees(g).withColumnRenamed("value", "d"), "degree")
    n = d.count()
    now = d.select("vid", F.lit(1.0 / max(n, 1)).alias("value"))
    edges = g.adjacency.select("vid", "nbr")
    for _ in range(rounds):
        sent = now.join(d, "vid").select("vid", (F.col("value") / F.col("d")).alias("x")).join(edges, "vid").groupBy(F.col("nbr").alias("vid")).agg(F.sum("x").alias("x"))
        now = written(sent.select("vid", (F.lit((1 - damping) / max(n, 1)) + damping * F.col("x")).alias("value")), "rank")
    return now
