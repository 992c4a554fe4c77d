"""Motif counting: the frequency of every connected vertex-induced pattern."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.canonical import words
from ..functions import patterns
from ..operators import aggregate, balance, expand, triples
from ..plans.model import PATTERN, Emit, MiningApp
from ..plans.scratch import written
from ..sources.graph import PropertyGraph


def app(max_size: int, labelled: bool = False, termination: bool = True) -> MiningApp:
    """Motifs as a filter-process application. Without the termination filter the engine generates one size more and refuses it."""
    return MiningApp(
        "motifs",
        labelled=labelled,
        filter=lambda e: F.lit(e.size <= max_size),
        map_outputs=(Emit("n", PATTERN, lambda e: F.lit(1)),),
        termination=(lambda e: F.lit(e.size >= max_size)) if termination else None,
        counted=True,
    )


def embeddings(g: PropertyGraph, size: int, labelled: bool = False, seeds: DataFrame | None = None) -> DataFrame:
    """Canonical embeddings of ``size`` vertices: w0.., code (, labels). The last level is not written."""
    now = expand.seed_vertices(g, labelled) if seeds is None else seeds
    for k in range(1, size):
        now = expand.grown_vertices(expand.vertex_candidates(now, g, k).where("ok"), k).drop("touch", "ok")
        if k + 1 < size and k > 1:
            now = written(now, f"level-{k + 1}")
    return now


def count_motifs(g: PropertyGraph, max_size: int = 4, sizes: str = "exact", labelled: bool = False, two_level: bool = True, waves: int = 1) -> DataFrame:
    """canon, k, n_edges, degs, lbls, n of each motif of ``max_size`` vertices, or of 3 to ``max_size`` ("upto",
    in one run that counts every level as it passes).

    The last level is grouped by quick code as it is generated and never
    stored. ``waves`` mines ranges of first vertices one after another, which
    bounds the state between steps.
    """
    if sizes == "upto":
        return _upto(g, max_size, labelled, two_level, waves)
    parts = []
    # On a large graph the last of three levels is counted by first word and quick code, not generated.
    counted = triples.by_first(g.triples) if max_size == 3 and two_level and not labelled and not g.small else None
    for low, high in balance.seed_waves(g, waves):
        if counted is not None:
            parts.append(written(counted.where(in_wave(low, high)).groupBy("code").agg(F.sum("n").alias("n")), "quick"))
            continue
        seeds = expand.seed_vertices(g, labelled)
        seeds = seeds if waves < 2 else seeds.where(in_wave(low, high))
        last = embeddings(g, max_size, labelled, seeds)
        if not two_level:
            parts.append(aggregate.count_one_level(last, max_size))
            continue
        parts.append(written(aggregate.by_quick(last, {"n": F.count(F.lit(1))}), "quick"))
    if not two_level:
        whole = parts[0]
        for p in parts[1:]:
            whole = whole.unionByName(p)
        return whole.groupBy("canon", *aggregate.PATTERN).agg(F.sum("n").alias("n"))
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.unionByName(p)
    return aggregate.by_pattern(whole, max_size, {"n": F.sum("n")})


def in_wave(low: int, high: int) -> Column:
    return (F.col("w0") >= low) & ((F.col("w0") < high) | F.lit(high == balance.ALL[1]))


def _upto(g: PropertyGraph, max_size: int, labelled: bool, two_level: bool, waves: int) -> DataFrame:
    """Motifs of 3 to ``max_size`` vertices: every level is made once, grouped, and grown further."""
    parts: DataFrame | None = None
    for low, high in balance.seed_waves(g, waves):
        seeds = expand.seed_vertices(g, labelled)
        now = seeds if waves < 2 else seeds.where(in_wave(low, high))
        for k in range(2, max_size + 1):
            now = expand.grown_vertices(expand.vertex_candidates(now, g, k - 1).where("ok"), k - 1).drop("touch", "ok")
            now = written(now, f"level-{k}") if 2 < k < max_size else now
            if k < 3:
                continue
            part = aggregate.count_by_pattern(now, k) if two_level else aggregate.count_one_level(now, k)
            part = written(part, "counts")
            parts = part if parts is None else parts.unionByName(part)
    if parts is None:
        return aggregate.count_by_pattern(expand.seed_vertices(g, labelled).where(F.lit(False)), 1)
    return parts.groupBy("canon", *aggregate.PATTERN).agg(F.sum("n").alias("n"))


def count_by_graph(g: PropertyGraph, size: int, graph_of) -> DataFrame:
    """graph, n_edges, n for a collection of graphs in one: ``graph_of`` gives the graph of a vertex column.
    Components never mix, so the first word names the graph."""
    f = embeddings(g, size)
    return f.groupBy(graph_of(F.col("w0")).alias("graph"), F.bit_count("code").cast("int").alias("n_edges")).agg(F.count(F.lit(1)).alias("n"))


def graph_support(g: PropertyGraph, size: int, graph_of, labelled: bool = False) -> DataFrame:
    """canon, PATTERN, support for a collection: in how many graphs a motif occurs. Another anti-monotone
    measure than images: a graph that lacks a pattern lacks its extensions."""
    f = embeddings(g, size, labelled)
    keys = ["code", "labels"] if labelled else ["code"]
    held = written(f.select(*keys, graph_of(F.col("w0")).alias("graph")).distinct(), "held")
    forms = patterns.canonicalize(held, size)
    once = held.join(forms, keys).select("canon", *aggregate.PATTERN, "graph").distinct()
    return once.groupBy("canon", *aggregate.PATTERN).agg(F.count(F.lit(1)).alias("support"))


def aggregation_stats(g: PropertyGraph, size: int, labelled: bool = False) -> DataFrame:
    """k, n_embeddings, n_quick, n_canonical, reduction: the work that two levels save."""
    if size == 3 and not labelled and not g.small:
        quick = written(triples.by_first(g.triples).groupBy("code").agg(F.sum("n").alias("n")), "quick")
    else:
        quick = written(aggregate.by_quick(embeddings(g, size, labelled), {"n": F.count(F.lit(1))}), "quick")
    forms = aggregate.by_pattern(quick, size, {"n": F.sum("n")}).agg(F.count(F.lit(1)).alias("n_canonical"))
    row = quick.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_embeddings"), F.count(F.lit(1)).alias("n_quick"))
    return row.crossJoin(forms).select(F.lit(size).alias("k"), "n_embeddings", "n_quick", "n_canonical", F.round(F.col("n_embeddings") / F.greatest(F.col("n_quick"), F.lit(1)), 6).alias("reduction"))


