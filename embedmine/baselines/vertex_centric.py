"""The vertex-centric paradigm: vertices own embeddings and send them to one another.

A new embedding is sent to each of its border vertices (members with a
neighbour outside), which extend it by their own neighbours. An extension that
several members touch is made by each of them; only the first toucher's copy
that passes the canonicality test stays.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.canonical import bit, every, extended_code, is_canonical, words
from ..operators import aggregate, expand, triples
from ..operators.aggregate import PATTERN
from ..plans.scratch import written
from ..sources.graph import PropertyGraph, measured


def messages(f: DataFrame, g: PropertyGraph, k: int) -> DataFrame:
    """A row for each embedding and border vertex: owner, bit, and the embedding. Dealt to the owners by a real shuffle."""
    members = F.array(*[F.struct(F.lit(i).alias("at"), F.col(w).alias("owner")) for i, w in enumerate(words(k))])
    sent = f.withColumn("m", F.explode(members)).select(*f.columns, "m.at", "m.owner")
    degree = g.adjacency.groupBy("vid").agg(F.count(F.lit(1)).alias("d")).select(F.col("vid").alias("owner"), "d")
    # A member is on the border unless all its neighbours are members: degree against edges inside.
    inside = F.lit(0)
    for i in range(k):
        own = F.lit(0)
        for j in range(1, k):
            at = j * (j - 1) // 2
            for p in range(j):
                if i in (j, p):
                    own = own + bit(F.col("code"), at + p).cast("int")
        inside = F.when(F.col("at") == i, own).otherwise(inside)
    return sent.join(g.shared(degree), "owner").where(F.col("d") > inside).drop("d").repartition("owner")


def explore(g: PropertyGraph, size: int) -> tuple[DataFrame, list[tuple[int, int]]]:
    """(canonical embeddings of ``size`` vertices, [(step, messages)])."""
    now = expand.seed_vertices(g)
    counts = []
    adjacency = g.adjacency.select(F.col("vid").alias("owner"), F.col("nbr").alias("ext"))
    pairs = g.adjacency.select("vid", "nbr")
    for k in range(1, size):
        sent = written(messages(now, g, k), f"messages-{k}")
        counts.append((k, sent.count()))
        made = sent.join(adjacency, "owner").where((F.col("ext") > F.col("w0")) & every([F.col("ext") != F.col(w) for w in words(k)]))
        # Each owner asks for the other members' edges to the extension.
        for i, w in enumerate(words(k)):
            other = pairs.select(F.col("vid").alias(w), F.col("nbr").alias("ext"), F.lit(1).alias(f"__t{i}"))
            made = made.join(g.shared(other), [w, "ext"], "left")
        touches = [F.col(f"__t{i}").isNotNull() for i in range(k)]
        first = every([~touches[i] | (F.col("at") <= i) for i in range(k)])
        made = made.where(first & is_canonical(k, touches, F.col("ext")))
        touch = F.lit(0).cast("long")
        for i in range(k):
            touch = touch + F.when(touches[i], F.lit(1 << i)).otherwise(0)
        now = written(made.select(*words(k), F.col("ext").alias(f"w{k}"), extended_code(F.col("code"), touch, k).alias("code")), f"owned-{k + 1}")
    return now, counts


def count_motifs(g: PropertyGraph, size: int) -> DataFrame:
    """canon, PATTERN, n. On a large graph the extensions of three vertices are counted by owner and quick code, not
    made: the owner of the first word of an edge makes those that touch it (codes 3 and 7), that of the second the others (5)."""
    if size == 3 and not g.small:
        quick = triples.by_first(g.triples).groupBy("code").agg(F.sum("n").alias("n"))
        return aggregate.by_pattern(written(quick, "quick"), size, {"n": F.sum("n")})
    return aggregate.count_by_pattern(explore(g, size)[0], size)


def message_counts(g: PropertyGraph, size: int) -> DataFrame:
    if size == 3 and not g.small:
        # A vertex is on the border of itself if it has an edge, of an edge if it has another one.
        row = g.degrees.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.when(F.col("d") > 1, F.col("d"))), F.lit(0))).first()
        return g.degrees.sparkSession.createDataFrame([(1, row[0]), (2, row[1])], "step int, messages long")
    return g.edges.sparkSession.createDataFrame(explore(g, size)[1], "step int, messages long")


def frequent_subgraphs(g: PropertyGraph, support: int, max_edges: int, depth_first: bool = True) -> tuple[DataFrame, int]:
    """(size, PATTERN, support of the frequent patterns; messages sent).

    Depth first, as owners hold embeddings of one pattern at a time: the
    embeddings of each frequent pattern are sent and grown by themselves to one
    edge more, and the results of a size are then joined to decide its supports.
    An embedding goes to its border vertices, those with an edge that it lacks.
    """
    now = expand.seed_edges(g, "vertex")
    degree = g.adjacency.groupBy("vid").agg(F.count(F.lit(1)).alias("d")).select(F.col("vid").alias("owner"), "d")
    at = expand.incident(g).withColumnRenamed("vid", "owner")
    sent = 0
    out = None
    for k in range(1, max_edges + 1):
        now = written(now, f"owned-{k}")
        forms = aggregate.forms_of(now, None)
        frequent = written(aggregate.supports(now, forms, support).where(F.col("support") >= support), "support")
        row = frequent.select(F.lit(k).alias("size"), "canon", *PATTERN, "support")
        out = row if out is None else out.unionByName(row)
        quick = forms.select("code", "labels", "canon").join(frequent.select("canon"), "canon", "left_semi")
        kept = written(now.join(measured(quick), ["code", "labels"]), f"kept-{k}")
        if k == max_edges or kept.isEmpty():
            break
        canons = [r["canon"] for r in frequent.select("canon").orderBy("canon").collect()] if depth_first else [None]
        grown = None
        for canon in canons:
            mine = (kept if canon is None else kept.where(F.col("canon") == canon)).drop("canon")
            inside = sum((F.when((F.col(f"a{i}") == F.col("owner")) | (F.col(f"b{i}") == F.col("owner")), 1).otherwise(0) for i in range(k)), F.lit(0))
            owned = mine.withColumn("owner", F.explode("vs")).join(g.shared(degree), "owner").where(F.col("d") > inside).drop("d")
            owned = written(owned.repartition("owner"), "messages")
            sent += owned.count()
            met = owned.join(at, "owner").where(F.col("eid") > F.col("w0"))
            met = met.where((F.col("owner") == F.col("src")) | ~F.array_contains("vs", F.col("src")))
            part = written(expand.grown_edges(met, k, "vertex").where("ok").drop("ok"), "grown")
            grown = part if grown is None else grown.unionByName(part)
        now = grown
    return out, sent
