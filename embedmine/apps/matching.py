"""Matching of one given pattern, and dense subgraphs."""

from __future__ import annotations

from itertools import permutations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import patterns
from ..functions.canonical import every, words
from ..operators import triples, wedges
from ..plans.scratch import spread
from ..sources.graph import PropertyGraph
from .motifs import embeddings

SQUARE = {frozenset(e) for e in ((0, 1), (1, 2), (2, 3), (0, 3))}


def order_predicates(n: int, edges: list[tuple[int, int]], labels: list[int]) -> list[tuple[int, int]]:
    """Pairs (i, j): requiring image(i) < image(j) leaves one of each class of symmetric mappings."""
    pattern = (tuple(labels), tuple((min(a, b), max(a, b), 0) for a, b in edges))
    out, fixed = [], list(labels)
    while True:
        orbit = patterns.canonical(tuple(fixed), pattern[1])[2]
        groups: dict[int, list[int]] = {}
        for v, o in enumerate(orbit):
            groups.setdefault(o, []).append(v)
        group = next((sorted(m) for m in groups.values() if len(m) > 1), None)
        if group is None:
            return out
        out += [(group[0], v) for v in group[1:]]
        fixed[group[0]] = max(fixed) + 1


def match_pattern(g: PropertyGraph, edges: list[tuple[int, int]], labels: list[str | None] | None = None, induced: bool = False, unique: bool = True, max_label_cost: int = 0) -> DataFrame:
    """v1, v2, ...: images of the pattern's vertices 0, 1, ...

    Vertices are joined in an order that keeps the pattern connected; later
    edges are semi-joins; unlabelled triangles and squares of a large graph come from its packed lists. ``unique`` gives one mapping of each symmetric class,
    else all. ``labels``: required label texts (None: any); up to
    ``max_label_cost`` of them may differ (inexact matching by label cost).
    """
    n = max(max(e) for e in edges) + 1
    kinds = labels or [None] * n
    if not g.small and n == 3 and len({frozenset(e) for e in edges}) == 3 and kinds == [None] * 3:
        orders = ("xyz",) if unique else tuple(map("".join, permutations("xyz")))
        return triples.listed(g.lists, g.n_edges, orders).toDF("v1", "v2", "v3")
    if not g.small and n == 4 and unique and {frozenset(e) for e in edges} == SQUARE and kinds == [None] * 4:
        return wedges.squares(g.lists, g.n_edges, induced)
    numbers = {t: i + 1 for i, t in enumerate(sorted({x for x in kinds if x is not None}))}
    broken = order_predicates(n, edges, [numbers.get(t, 0) for t in kinds]) if unique else []
    order = [0]
    while len(order) < n:
        order.append(next(v for v in range(n) if v not in order and any({v, u} in [set(e) for e in edges] for u in order)))
    pairs = g.adjacency.select("vid", "nbr")
    names = g.vertices.select("vid", "vlabel_text")
    now = None
    seen: list[int] = []
    for v in order:
        col = f"x{v}"
        if now is None:
            now = spread(g.adjacency.select(F.col("vid").alias(col)).distinct(), col)
        else:
            near = [u for u in seen if {u, v} in [set(e) for e in edges]]
            now = now.join(g.shared(pairs.select(F.col("vid").alias(f"x{near[0]}"), F.col("nbr").alias(col))), f"x{near[0]}")
            now = now.where(every([F.col(col) != F.col(f"x{u}") for u in seen]))
            bounds = [F.col(f"x{i}") < F.col(f"x{j}") for i, j in broken if {i, j} <= {*seen, v} and v in (i, j)]
            now = now.where(every(bounds)) if bounds else now
            for u in near[1:]:
                now = now.join(g.shared(pairs.select(F.col("vid").alias(f"x{u}"), F.col("nbr").alias(col))), [f"x{u}", col], "left_semi")
            if induced:
                for u in [u for u in seen if u not in near]:
                    now = now.join(g.shared(pairs.select(F.col("vid").alias(f"x{u}"), F.col("nbr").alias(col))), [f"x{u}", col], "left_anti")
        if kinds[v] is not None:
            now = now.join(g.shared(names.select(F.col("vid").alias(col), F.col("vlabel_text").alias(f"t{v}"))), col)
            wrong = (~F.col(f"t{v}").eqNullSafe(F.lit(kinds[v]))).cast("int")
            now = now.withColumn("cost", (F.col("cost") if "cost" in now.columns else F.lit(0)) + wrong).drop(f"t{v}").where(F.col("cost") <= max_label_cost)
        seen.append(v)
    return now.select(*[F.col(f"x{v}").alias(f"v{v + 1}") for v in range(n)])


def dense_subgraphs(g: PropertyGraph, min_density: float, size: int) -> DataFrame:
    """Connected sets of ``size`` vertices with at least that share of the possible edges. Density is
    not anti-monotone, so it is tested on output only."""
    f = embeddings(g, size)
    least = min_density * size * (size - 1) / 2 - 1e-9
    return f.where(F.bit_count("code") >= least).select(*words(size), F.bit_count("code").cast("int").alias("n_edges"))
