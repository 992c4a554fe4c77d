"""Frequent subgraph mining by minimum-image support, as an application of the engine."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import aggregate, expand
from ..operators.aggregate import PATTERN
from ..plans.engine import explore
from ..plans.model import Domains, MiningApp
from ..sources.graph import PropertyGraph


@dataclass
class FrequentSubgraphs:
    """patterns: size, canon, PATTERN, support; embeddings by size: edge-mode rows; funnel: counts by size."""

    patterns: DataFrame | None = None
    embeddings: dict[int, DataFrame] = field(default_factory=dict)
    funnel: list[dict] = field(default_factory=list)


def app(support: int, max_edges: int | None = None, max_vertices: int | None = None, labels: str = "vertex") -> MiningApp:
    """Maps each embedding's vertices to its pattern, unites them place by place, keeps the embeddings
    of patterns whose every place has ``support`` vertices, and outputs those."""
    return MiningApp(
        "frequent subgraphs",
        mode="edge",
        labels=labels,
        filter=lambda e: F.lit(True) if max_vertices is None else e.n_vertices <= max_vertices,
        maps=(Domains("support", support),),
        aggregation_filter=lambda e, read: read("support") >= support,
        aggregation_output=lambda e, read: [*e.words, read("support").alias("support")],
        termination=None if max_edges is None else lambda e: F.lit(e.size >= max_edges),
        max_size=max_edges,
    )


def frequent_subgraphs(g: PropertyGraph, support: int, max_edges: int | None = None, max_vertices: int | None = None, labels: str = "vertex", store: str = "list") -> FrequentSubgraphs:
    """All patterns whose every vertex has at least ``support`` distinct images, and their embeddings.

    Size counts edges; ``max_vertices`` is a second bound. Without ``max_edges`` it goes on
    until no pattern is frequent. The last size is tested as well and then not expanded. Where
    nothing is frequent any more, the sizes up to ``max_edges`` have empty tables.
    """
    r = explore(g, app(support, max_edges, max_vertices, labels), store)
    out = FrequentSubgraphs(funnel=r.funnel)
    for k in sorted(k for k, _ in r.aggregates):
        found = r.aggregates[k, "support"].where(F.col("support") >= support)
        row = found.select(F.lit(k).alias("size"), "canon", *PATTERN, "support")
        out.patterns = row if out.patterns is None else out.patterns.unionByName(row)
        out.embeddings[k] = r.levels[k]
    if out.patterns is None:
        out.patterns = g.edges.sparkSession.createDataFrame([], "size int, canon string, k int, n_edges int, degs string, lbls string, support long")
    empty = expand.seed_edges(g, labels).where(F.lit(False))
    for size in range(1, (max_edges or 0) + 1):
        if size not in out.embeddings:
            out.embeddings[size] = empty
        empty = expand.edge_candidates(empty, g, size, labels).drop("ok")
    return out


def by_canon(f: DataFrame) -> DataFrame:
    """canon, n: embeddings of each pattern of a level."""
    return aggregate.count_by_pattern(f, None).select("canon", "n")


def support_sweep(g: PropertyGraph, thresholds: list[int], max_edges: int, labels: str = "vertex") -> DataFrame:
    """theta, n_frequent, n_kept: mined once at the smallest threshold; a pattern's support does not depend on it."""
    mined = frequent_subgraphs(g, min(thresholds), max_edges, labels=labels)
    counts = None
    for k, f in mined.embeddings.items():
        row = by_canon(f)
        counts = row if counts is None else counts.unionByName(row)
    table = mined.patterns.join(counts, "canon").select("support", "n")
    spark = table.sparkSession
    return spark.createDataFrame([(t,) for t in thresholds], "theta int").join(table, F.col("support") >= F.col("theta"), "left").groupBy("theta").agg(F.count("support").alias("n_frequent"), F.coalesce(F.sum("n"), F.lit(0)).alias("n_kept"))
