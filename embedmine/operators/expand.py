"""One exploration step: seeds, extensions, canonicality.

Vertex mode: rows w0..w(k-1) (vertices in visiting order), code (quick code as a
long), and, if labelled, labels array<int>. Edge mode: w0..w(k-1) (edge ids),
a_i, b_i (endpoints of word i), vs (vertices by first visit), and the quick code in
two texts that grow with the row: code (for each word the numbers of its ends and
its label) and labels (of the visited vertices).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.canonical import bit, every, extended_code, is_canonical, later_words, some, words
from ..plans.scratch import spread
from ..sources.graph import PropertyGraph


def seed_vertices(g: PropertyGraph, labelled: bool = False) -> DataFrame:
    """All vertices as embeddings of size 1."""
    extra = [F.array("vlabel").alias("labels")] if labelled else []
    return g.vertices.select(F.col("vid").alias("w0"), F.lit(0).cast("long").alias("code"), *extra)


def vertex_candidates(f: DataFrame, g: PropertyGraph, k: int, refused: bool = False) -> DataFrame:
    """Extensions of every k-vertex embedding by a neighbour: columns of ``f``, ext, touch (bit i: it
    touches word i), ok. ``refused``: those that are not canonical as well (ok is false)."""
    return met_by_first(f, g, k) if g.small and not refused else met_by_all(f, g, k)


def met_by_all(f: DataFrame, g: PropertyGraph, k: int) -> DataFrame:
    """An extension is met once for each member that it touches. One grouping
    removes the repetitions, gathers ``touch``, and decides canonicality: every
    meeting must find no larger word after it. (A meeting that fails may not be
    dropped before the grouping: the others of the same extension would then
    pass.) Only tests of the extension itself go below the group. The members of
    one parent are exploded from one row, so that with a broadcast graph the map
    side already combines them.
    """
    labelled = "labels" in f.columns
    members = F.array(*[F.struct(F.lit(1 << i).cast("long").alias("bit"), F.col(w).alias("vid"), later_words(k, i).alias("later")) for i, w in enumerate(words(k))])
    near = g.adjacency.select("vid", F.col("nbr").alias("ext"), *(["nlabel"] if labelled else []))
    met = f.withColumn("m", F.explode(members)).select(*f.columns, F.col("m.bit").alias("bit"), F.col("m.vid").alias("vid"), F.col("m.later").alias("later"))
    met = met.join(g.shared(near), "vid").where((F.col("ext") > F.col("w0")) & every([F.col("ext") != F.col(w) for w in words(k)[1:]]))
    label = [F.first("nlabel").alias("nlabel")] if labelled else []
    return met.groupBy(*f.columns, "ext").agg(F.bit_or("bit").alias("touch"), F.min(F.col("ext") > F.col("later")).alias("ok"), *label)


def met_by_first(f: DataFrame, g: PropertyGraph, k: int) -> DataFrame:
    """The canonical extensions alone, where the graph may be broadcast: the parents are dealt evenly, and
    their many extensions never move.

    Only the meeting with the first member touched counts, and for that one the
    order is a test within the row: the extension exceeds every later word. What
    passes is looked up with the other members; a link to an earlier one means
    that this was not the first meeting.
    """
    labelled = "labels" in f.columns
    members = F.array(*[F.struct(F.lit(1 << i).cast("long").alias("bit"), F.col(w).alias("vid"), later_words(k, i).alias("later")) for i, w in enumerate(words(k))])
    near = g.adjacency.select("vid", F.col("nbr").alias("ext"), *(["nlabel"] if labelled else []))
    met = spread(f, *words(k)).withColumn("m", F.explode(members)).select(*f.columns, F.col("m.bit").alias("bit"), F.col("m.vid").alias("vid"), F.col("m.later").alias("later"))
    met = met.join(g.shared(near), "vid").where((F.col("ext") > F.col("w0")) & (F.col("ext") > F.col("later")) & every([F.col("ext") != F.col(w) for w in words(k)[1:]]))
    touch = F.col("bit")
    if k > 1:
        for i, w in enumerate(words(k)):
            table, same = g.linked(F.col(w), F.col("ext"), f"t{i}")
            met = met.join(table, same, "left").where((F.col("bit") <= 1 << i) | F.col(f"t{i}").isNull())
            touch = touch.bitwiseOR(F.when(F.col(f"t{i}").isNotNull(), F.lit(1 << i).cast("long")).otherwise(0))
    return met.select(*f.columns, "ext", touch.alias("touch"), F.lit(True).alias("ok"), *(["nlabel"] if labelled else []))


def grown_vertices(candidates: DataFrame, k: int) -> DataFrame:
    """Candidates as embeddings of k + 1 vertices; ``touch`` and ``ok`` stay for the filters."""
    extra = [F.concat("labels", F.array("nlabel")).alias("labels")] if "labels" in candidates.columns else []
    return candidates.select(*words(k), F.col("ext").alias(f"w{k}"), extended_code(F.col("code"), F.col("touch"), k).alias("code"), *extra, "touch", "ok")


def label_text(label: str, kind: str, labels: str) -> Column:
    """A label in a quick code; "0" if ``labels`` ("vertex", "edge" or "both") leaves its kind out."""
    return F.col(label).cast("string") if labels in (kind, "both") else F.lit("0")


def ends(g: PropertyGraph) -> DataFrame:
    """eid, src, dst, and the labels la, lb, el of both ends and the edge."""
    return g.adjacency.where("vid < nbr").select("eid", F.col("vid").alias("src"), F.col("nbr").alias("dst"), F.col("vlabel").alias("la"), F.col("nlabel").alias("lb"), F.col("elabel").alias("el"))


def seeded(e: DataFrame, labels: str = "both") -> DataFrame:
    """Rows of :func:`ends` as embeddings of one edge; further columns stay."""
    own = ("eid", "src", "dst", "la", "lb", "el")
    return e.select(
        *[c for c in e.columns if c not in own],
        F.col("eid").alias("w0"), F.col("src").alias("a0"), F.col("dst").alias("b0"), F.array("src", "dst").alias("vs"),
        F.concat(F.lit("0-1:"), label_text("el", "edge", labels)).alias("code"),
        F.concat_ws(",", label_text("la", "vertex", labels), label_text("lb", "vertex", labels)).alias("labels"),
    )


def seed_edges(g: PropertyGraph, labels: str = "both") -> DataFrame:
    """All edges as embeddings of size 1."""
    return seeded(ends(g), labels)


def edge_columns(k: int) -> list[str]:
    return words(k) + [f"{c}{i}" for c in "ab" for i in range(k)]


def grown_edges(met: DataFrame, k: int, labels: str = "both", keep: tuple[str, ...] = ()) -> DataFrame:
    """k-edge embeddings that meet an edge (columns of :func:`ends`), as embeddings of k + 1 edges with ``ok``:
    the edge is new, touches a word, and keeps the canonical order. All is decided within the row."""
    pa, pb = F.array_position("vs", F.col("src")), F.array_position("vs", F.col("dst"))
    met = met.withColumn("pa", pa).withColumn("pb", pb)
    size = F.size("vs")
    na, nb = (F.when(F.col(p) > 0, F.col(p).cast("int") - 1).otherwise(size) for p in ("pa", "pb"))
    fresh = lambda if_a, if_b, neither: F.when(F.col("pa") == 0, if_a).when(F.col("pb") == 0, if_b).otherwise(neither)
    touches = [some([F.col(x) == F.col(f"{c}{i}") for x in ("src", "dst") for c in "ab"]) for i in range(k)]
    known = every([F.col("eid") != F.col(w) for w in words(k)])
    return met.select(
        *keep,
        *words(k), F.col("eid").alias(f"w{k}"),
        *[f"a{i}" for i in range(k)], F.col("src").alias(f"a{k}"),
        *[f"b{i}" for i in range(k)], F.col("dst").alias(f"b{k}"),
        fresh(F.concat("vs", F.array("src")), F.concat("vs", F.array("dst")), F.col("vs")).alias("vs"),
        F.concat("code", F.lit(","), F.least(na, nb).cast("string"), F.lit("-"), F.greatest(na, nb).cast("string"), F.lit(":"), label_text("el", "edge", labels)).alias("code"),
        F.concat("labels", fresh(F.concat(F.lit(","), label_text("la", "vertex", labels)), F.concat(F.lit(","), label_text("lb", "vertex", labels)), F.lit(""))).alias("labels"),
        (known & some(touches) & is_canonical(k, touches, F.col("eid"))).alias("ok"),
    )


def incident(g: PropertyGraph) -> DataFrame:
    """vid, and the columns of :func:`ends` for each edge at it."""
    low = F.col("vid") < F.col("nbr")
    return g.adjacency.select(
        "vid", "eid", F.least("vid", "nbr").alias("src"), F.greatest("vid", "nbr").alias("dst"),
        F.when(low, F.col("vlabel")).otherwise(F.col("nlabel")).alias("la"), F.when(low, F.col("nlabel")).otherwise(F.col("vlabel")).alias("lb"), F.col("elabel").alias("el"),
    )


def edge_candidates(f: DataFrame, g: PropertyGraph, k: int, labels: str = "both") -> DataFrame:
    """Every extension of every k-edge embedding by an incident edge, with ``ok``; needs no grouping.

    An edge between two members would be met from both ends; it is taken from
    its smaller end only.
    """
    parents = spread(f, *words(k)) if g.small else f
    met = parents.withColumn("vid", F.explode("vs")).join(g.shared(incident(g)), "vid").where(F.col("eid") > F.col("w0"))
    met = met.where((F.col("vid") == F.col("src")) | ~F.array_contains("vs", F.col("src")))
    met = met.where(every([F.col("eid") != F.col(w) for w in words(k)]))
    return grown_edges(met, k, labels)


def touched(mask: Column, k: int) -> list[Column]:
    return [bit(mask, i) for i in range(k)]
