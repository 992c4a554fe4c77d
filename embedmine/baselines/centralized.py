"""Centralized methods on the same problems: motif census by closed formulas and by a tree of patterns, cliques by ordered joins,
coordinated de-duplication, and brute force for toys."""

from __future__ import annotations

from itertools import combinations, permutations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import patterns
from ..functions.canonical import every, words
from ..operators import expand, wedges
from ..plans.scratch import written
from ..sources.graph import PropertyGraph


def motif_census(g: PropertyGraph, k: int) -> DataFrame:
    """k, n_edges, degs, n for k = 3 or 4.

    Non-induced counts come from degrees, triangles on edges and common
    neighbours; subtracting the denser patterns gives the induced ones.
    """
    if k == 3 and not g.small:
        d = F.col("d")
        row = g.triples.agg(F.sum((d * (d - 1) / 2).cast("long")), F.sum("low")).first()
        return g.triples.sparkSession.createDataFrame([r for r in ((3, 2, "1-1-2", row[0] - 3 * row[1]), (3, 3, "2-2-2", row[1])) if r[3]], "k int, n_edges int, degs string, n long")
    spark = g.edges.sparkSession
    a = g.adjacency.select("vid", "nbr")
    degree = written(a.groupBy("vid").agg(F.count(F.lit(1)).alias("d")), "degree")
    e = g.edges.select("src", "dst")
    on = {x: degree.select(F.col("vid").alias(x), F.col("d").alias(f"d_{x}")) for x in ("src", "dst")}
    wedge = a.select(F.col("vid").alias("src"), F.col("nbr").alias("c")).join(e, "src").where("c <> dst")
    tri = wedge.join(g.shared(a.select(F.col("vid").alias("dst"), F.col("nbr").alias("c"))), ["dst", "c"], "left_semi").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("t"))
    sides = written(e.join(on["src"], "src").join(on["dst"], "dst").join(tri, ["src", "dst"], "left").withColumn("t", F.coalesce("t", F.lit(0))), "sides")
    d = F.col("d").cast("long")
    dr = degree.agg(F.coalesce(F.sum(d * (d - 1) / 2), F.lit(0)), F.coalesce(F.sum(d * (d - 1) * (d - 2) / 6), F.lit(0))).first()
    er = sides.agg(F.coalesce(F.sum("t"), F.lit(0)), F.coalesce(F.sum((F.col("d_src") - 1) * (F.col("d_dst") - 1)), F.lit(0)), F.coalesce(F.sum(F.col("t") * (F.col("t") - 1) / 2), F.lit(0)), F.coalesce(F.sum(F.col("t") * (F.col("d_src") + F.col("d_dst") - 4)), F.lit(0))).first()
    wedges, stars = int(dr[0]), int(dr[1])
    triangles, paths, diamonds = int(er[0]) // 3, int(er[1]) - int(er[0]), int(er[2])
    if k == 3:
        rows = [(3, 2, "1-1-2", wedges - 3 * triangles), (3, 3, "2-2-2", triangles)]
    else:
        # Twice the triangles at a vertex is the sum over its edges; each triangle is met at two edges of the vertex.
        paws = int(er[3]) // 2
        common = a.select(F.col("vid").alias("m"), F.col("nbr").alias("u")).join(a.select(F.col("vid").alias("m"), F.col("nbr").alias("v")), "m").where("u < v").groupBy("u", "v").agg(F.count(F.lit(1)).alias("c"))
        squares = int(common.agg(F.coalesce(F.sum(F.col("c") * (F.col("c") - 1) / 2), F.lit(0))).first()[0]) // 2
        full = clique_join(g, 4).count()
        diamond = diamonds - 6 * full
        square = squares - diamond - 3 * full
        paw = paws - 4 * diamond - 12 * full
        path = paths - 2 * paw - 4 * square - 6 * diamond - 12 * full
        star = stars - paw - 2 * diamond - 4 * full
        rows = [(4, 3, "1-1-2-2", path), (4, 3, "1-1-1-3", star), (4, 4, "1-2-2-3", paw), (4, 4, "2-2-2-2", square), (4, 5, "2-2-3-3", diamond), (4, 6, "3-3-3-3", full)]
    return spark.createDataFrame([r for r in rows if r[3]], "k int, n_edges int, degs string, n long")


def census_by_tree(g: PropertyGraph, k: int) -> DataFrame:
    """k, n_edges, degs, n of every connected pattern of ``k`` vertices, matched along a tree of patterns.

    Each pattern's vertices are ordered so that every prefix is connected and,
    where it can be, a prefix of a pattern that is in the tree already. A node of the
    tree is the table of induced mappings of its prefix, made once from its parent's by one join
    and tests, and shared by all patterns below. A pattern's count is its mappings over its symmetries.
    """
    links = g.adjacency.select("vid", "nbr")
    shapes: dict[int, set] = {1: {((0,), ())}}
    for n in range(2, k + 1):
        shapes[n] = {patterns.canonical((0,) * n, (*edges, *[(i, n - 1, 0) for i in more]))[0] for _, edges in shapes[n - 1] for size in range(1, n) for more in combinations(range(n - 1), size)}
    nodes: dict[tuple, DataFrame] = {((),): g.adjacency.select(F.col("vid").alias("x0")).distinct()}

    def table(path: tuple) -> DataFrame:
        """Mappings of a prefix, given for each vertex by the earlier ones that it touches."""
        if path not in nodes:
            near, i = path[-1], len(path) - 1
            now = table(path[:-1]).join(g.shared(links.select(F.col("vid").alias(f"x{near[0]}"), F.col("nbr").alias(f"x{i}"))), f"x{near[0]}")
            now = now.where(every([F.col(f"x{i}") != F.col(f"x{j}") for j in range(i)]))
            for j in range(i):
                if j != near[0]:
                    other = links.select(F.col("vid").alias(f"x{j}"), F.col("nbr").alias(f"x{i}"))
                    now = now.join(g.shared(other), [f"x{j}", f"x{i}"], "left_semi" if j in near else "left_anti")
            nodes[path] = written(now, "census") if i + 1 < k else now
        return nodes[path]

    rows = []
    for form in sorted(shapes[k]):
        near = {v: {b if a == v else a for a, b, _ in form[1] if v in (a, b)} for v in range(k)}
        paths = []
        for order in permutations(range(k)):
            path = tuple(tuple(i for i in range(j) if order[i] in near[order[j]]) for j in range(k))
            if all(path[1:]):
                paths.append(path)
        symmetries = paths.count(paths[0])
        best = max(set(paths), key=lambda p: (sum(p[: i + 1] in nodes for i in range(k)), p))
        found = table(best).count()
        if found:
            _, _, n_edges, degs, *_ = patterns.described(*form)
            rows.append((k, n_edges, degs, found // symmetries))
    return g.edges.sparkSession.createDataFrame(rows, "k int, n_edges int, degs string, n long")


def clique_join(g: PropertyGraph, k: int) -> DataFrame:
    """k-cliques by an ordered self-join of the edges: w0 < w1 < ..."""
    e = g.edges.select(F.col("src").alias("s"), F.col("dst").alias("t"))
    now = g.edges.select(F.col("src").alias("w0"), F.col("dst").alias("w1"))
    for i in range(2, k):
        now = now.join(g.shared(e.select(F.col("s").alias(f"w{i - 1}"), F.col("t").alias(f"w{i}"))), f"w{i - 1}")
        for j in range(i - 1):
            now = now.join(g.shared(e.select(F.col("s").alias(f"w{j}"), F.col("t").alias(f"w{i}"))), [f"w{j}", f"w{i}"], "left_semi")
    return now.select(*words(k))


def dedupe_global(g: PropertyGraph, size: int) -> DataFrame:
    """Connected sets by growth in every order and a global distinct on the sorted words: what the canonicality test avoids.
    Sets of three of a large graph are made distinct where their growths meet, at their centres."""
    if size == 3 and not g.small:
        return wedges.connected(g.lists, g.n_edges)
    now = expand.seed_vertices(g).select("w0")
    near = g.adjacency.select("vid", "nbr")
    for k in range(1, size):
        met = now.withColumn("vid", F.explode(F.array(*words(k)))).join(g.shared(near), "vid").where(every([F.col("nbr") != F.col(w) for w in words(k)]))
        ids = F.array_sort(F.array(*words(k), "nbr"))
        now = met.select(*[ids[i].alias(f"w{i}") for i in range(k + 1)]).distinct()
    return now


def brute_force(edges: list[tuple[int, int]], size: int) -> set[frozenset[int]]:
    """All connected vertex sets of a toy graph."""
    near: dict[int, set[int]] = {}
    for a, b in edges:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    out = set()
    for c in combinations(sorted(near), size):
        seen, todo = {c[0]}, [c[0]]
        while todo:
            for v in near[todo.pop()]:
                if v in c and v not in seen:
                    seen.add(v)
                    todo.append(v)
        if len(seen) == size:
            out.add(frozenset(c))
    return out
