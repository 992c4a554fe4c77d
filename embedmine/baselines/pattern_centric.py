"""The pattern-centric paradigm: only patterns are kept; their embeddings are matched anew in every round."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import patterns
from ..functions.canonical import every
from ..plans.scratch import written
from ..sources.graph import PropertyGraph

Pattern = tuple[tuple[int, ...], tuple[tuple[int, int, int], ...]]


def mappings(g: PropertyGraph, group: list[Pattern], among: Callable[[Column], Column] | None = None) -> DataFrame:
    """pid and all mappings x0, x1, ... of patterns that differ in their labels only: a join for each edge.

    ``pid`` is the place in ``group``; the patterns' labels travel with the rows,
    so that one plan serves them all. ``among``: a test of the first vertex's place in a
    fixed shuffle of all, 0 to 999.
    """
    edges = group[0][1]
    n = len(group[0][0])
    wanted = g.edges.sparkSession.createDataFrame([(i, *p[0]) for i, p in enumerate(group)], "pid int, " + ", ".join(f"l{v} int" for v in range(n)))
    side = g.adjacency.select("vid", "nbr", "vlabel", "nlabel")
    rest = list(edges)
    a, b, _ = rest.pop(0)
    first = side.select(F.col("vid").alias(f"x{a}"), F.col("nbr").alias(f"x{b}"), F.col("vlabel").alias(f"l{a}"), F.col("nlabel").alias(f"l{b}"))
    if among is not None:
        first = first.where(among(F.pmod(F.xxhash64(f"x{a}"), F.lit(1000))))
    now = first.join(F.broadcast(wanted), [f"l{a}", f"l{b}"])  # patterns come from the driver, a few thousand at most
    seen = [a, b]
    while rest:
        a, b, _ = edge = next(e for e in rest if e[0] in seen or e[1] in seen)
        rest.remove(edge)
        if a in seen and b in seen:
            now = now.join(g.shared(side.select(F.col("vid").alias(f"x{a}"), F.col("nbr").alias(f"x{b}"))), [f"x{a}", f"x{b}"], "left_semi")
            continue
        a, b = (a, b) if a in seen else (b, a)
        step = side.select(F.col("vid").alias(f"x{a}"), F.col("nbr").alias(f"x{b}"), F.col("nlabel").alias(f"l{b}"))
        now = now.join(g.shared(step), [f"x{a}", f"l{b}"]).where(every([F.col(f"x{b}") != F.col(f"x{u}") for u in seen]))
        seen.append(b)
    return now.select("pid", *[f"x{v}" for v in range(n)])


def by_shape(group: list[Pattern]) -> list[list[Pattern]]:
    shapes: dict[tuple, list[Pattern]] = {}
    for p in group:
        shapes.setdefault(p[1], []).append(p)
    return list(shapes.values())


def supports(g: PropertyGraph, group: list[Pattern]) -> dict[Pattern, int]:
    """Support of each pattern: a plan for each shape, one row a pattern to the driver."""
    out = dict.fromkeys(group, 0)
    for same in by_shape(group):
        n = len(same[0][0])
        images = mappings(g, same).select("pid", F.explode(F.array(*[F.struct(F.lit(v).alias("v"), F.col(f"x{v}").alias("x")) for v in range(n)])).alias("i")).select("pid", "i.v", "i.x").distinct()
        least = images.groupBy("pid", "v").agg(F.count(F.lit(1)).alias("n")).groupBy("pid").agg(F.min("n").alias("n"))
        for r in least.collect():  # one row a pattern
            out[same[r["pid"]]] = r["n"]
    return out


#: Bounds of the slices of first vertices that early stopping matches one after another (shares of all).
SLICES = (0.0, 0.1, 0.3, 1.0)


def reaching(g: PropertyGraph, group: list[Pattern], threshold: int) -> dict[Pattern, int]:
    """``threshold`` for each pattern of which every vertex has so many images, 0 for the others.

    Matching stops early: it begins with a slice of the first vertices, and only patterns that
    have not reached the threshold yet are matched on the next, larger slice.
    """
    out = dict.fromkeys(group, 0)
    for same in by_shape(group):
        n, left, before = len(same[0][0]), list(same), None
        for low, high in zip(SLICES[:-1], SLICES[1:]):
            found = mappings(g, left, lambda x, low=low, high=high: x.between(int(low * 1000), int(high * 1000) - 1))
            names = g.edges.sparkSession.createDataFrame([(i, same.index(p)) for i, p in enumerate(left)], "pid int, of int")
            found = found.join(F.broadcast(names), "pid")
            images = found.select("of", F.explode(F.array(*[F.struct(F.lit(v).alias("v"), F.col(f"x{v}").alias("x")) for v in range(n)])).alias("i")).select("of", "i.v", "i.x").distinct()
            images = written(images if before is None else images.unionByName(before).distinct(), "images")
            sizes = images.groupBy("of", "v").agg(F.count(F.lit(1)).alias("n")).groupBy("of").agg(F.min("n").alias("n"), F.count(F.lit(1)).alias("places"))
            for r in sizes.where((F.col("n") >= threshold) & (F.col("places") == n)).collect():
                out[same[r["of"]]] = threshold
            left, before = [p for p in same if not out[p]], images
            if not left:
                break
    return out


def extensions(p: Pattern, pairs: set[tuple[int, int]]) -> set[tuple]:
    """Canonical forms of a pattern with one more edge: to a new vertex or between two of its own."""
    labels, edges = p
    out = set()
    orbit = patterns.canonical(*p)[2]
    done = set()
    for v, o in enumerate(orbit):
        if o in done:
            continue  # one representative of each orbit is enough for a new vertex
        done.add(o)
        for x, y in pairs:
            for here, there in {(x, y), (y, x)}:
                if labels[v] == here:
                    out.add(patterns.canonical((*labels, there), (*edges, (v, len(labels), 0)))[0])
    have = {(a, b) for a, b, _ in edges}
    for a in range(len(labels)):
        for b in range(a + 1, len(labels)):
            if (a, b) not in have and tuple(sorted((labels[a], labels[b]))) in pairs:
                out.add(patterns.canonical(labels, (*edges, (a, b, 0)))[0])
    return out


def frequent_patterns(g: PropertyGraph, threshold: int, max_edges: int, early_stop: bool = False) -> list[tuple[int, Pattern, int]]:
    """(size, pattern, support), patterns as the only state: a few thousand at most, on the driver as in a pattern miner."""
    rows = g.adjacency.where("vlabel <= nlabel").select("vlabel", "nlabel").distinct().collect()
    pairs = {(r[0], r[1]) for r in rows}
    now = {patterns.canonical(p, ((0, 1, 0),))[0] for p in pairs}
    out, frequent_pairs = [], set()
    for size in range(1, max_edges + 1):
        found = (reaching(g, sorted(now), threshold) if early_stop else supports(g, sorted(now))) if now else {}
        kept = [p for p in sorted(now) if found[p] >= threshold]
        out += [(size, p, found[p]) for p in kept]
        if size == 1:
            frequent_pairs = {tuple(sorted(p[0])) for p in kept}
        now = set().union(*(extensions(p, frequent_pairs) for p in kept)) if kept else set()
    return out


def frequent_table(g: PropertyGraph, threshold: int, max_edges: int, early_stop: bool = False) -> DataFrame:
    """size, canon, k, n_edges, degs, lbls, support."""
    rows = [(size, *patterns.described(*p)[:5], s) for size, p, s in frequent_patterns(g, threshold, max_edges, early_stop)]
    return g.edges.sparkSession.createDataFrame(rows, "size int, canon string, k int, n_edges int, degs string, lbls string, support long")


def embeddings_by_pattern(g: PropertyGraph, threshold: int, max_edges: int) -> DataFrame:
    """size, lbls, n_mappings: what each worker holds where a pattern is one worker's task.

    The mappings of every frequent pattern are dealt by pattern, so that a
    pattern's matching and support are one task's work, and counted there: popular
    patterns are hot spots, and no more tasks have work than there are patterns.
    """
    out = None
    found = frequent_patterns(g, threshold, max_edges)
    for size in range(1, max_edges + 1):
        for same in by_shape([p for s, p, _ in found if s == size]):
            names = g.edges.sparkSession.createDataFrame([(i, "|".join(map(str, sorted(p[0])))) for i, p in enumerate(same)], "pid int, lbls string")
            held = mappings(g, same).repartition("pid").groupBy("pid").agg(F.count(F.lit(1)).alias("n_mappings"))
            row = held.join(F.broadcast(names), "pid").select(F.lit(size).alias("size"), "lbls", "n_mappings")
            out = row if out is None else out.unionByName(row)
    return out if out is not None else g.edges.sparkSession.createDataFrame([], "size int, lbls string, n_mappings long")


def skew(loads: DataFrame, value: str) -> DataFrame:
    """n, most, mean, share: how much of all the largest part holds."""
    return loads.agg(F.count(F.lit(1)).alias("n"), F.max(value).alias("most"), F.avg(value).alias("mean"), F.sum(value).alias("__all")).withColumn("share", F.round(F.col("most") / F.col("__all"), 6)).drop("__all")


def mine_then_match(g: PropertyGraph, threshold: int, edges: int) -> DataFrame:
    """The centralized pair of a pattern miner and a matcher: embeddings (edge ids w0 < ...) of the frequent patterns of ``edges`` edges."""
    side = g.adjacency.select("vid", "nbr", "eid")
    out = None
    for same in by_shape([p for size, p, _ in frequent_patterns(g, threshold, edges) if size == edges]):
        found = mappings(g, same)
        for i, (a, b, _) in enumerate(same[0][1]):
            found = found.join(g.shared(side.select(F.col("vid").alias(f"x{a}"), F.col("nbr").alias(f"x{b}"), F.col("eid").alias(f"__e{i}"))), [f"x{a}", f"x{b}"])
        ids = F.array_sort(F.array(*[F.col(f"__e{i}") for i in range(edges)]))
        found = found.select(*[ids[i].alias(f"w{i}") for i in range(edges)])
        out = found if out is None else out.unionByName(found)
    empty = g.edges.where("false").select(*[F.col("eid").alias(f"w{i}") for i in range(edges)])
    return written(empty if out is None else out.distinct(), "matched")
