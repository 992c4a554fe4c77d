"""The layered path store: embeddings of one size as edges between consecutive positions.

Rows (canon, level, node, next): some embedding of the pattern has ``node`` at
position ``level`` and ``next`` after it. Nodes are words: vertices or edges.
Following the edges gives all stored embeddings and others besides, which
decoding rejects: repeated words, words that touch nothing, orders that are not
canonical, what the application's filters refuse, and, at full length, other
patterns than the store's.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import patterns
from ..functions.canonical import every, extended_code, is_canonical, words
from ..plans.model import EmbeddingView, MiningApp
from ..plans.scratch import spread, written
from ..sources.graph import PropertyGraph, measured
from . import balance
from .aggregate import code_keys
from .expand import ends, grown_edges, seeded, touched

#: Bytes of a store edge and of a word in a list.
EDGE_BYTES, WORD_BYTES = 20, 8
#: Store edges from which the paths are dealt by their cost between steps; below, a task's share is not worth its plan.
DEALT_EDGES = 100_000
Alpha = Callable[[DataFrame, int], DataFrame]


def vertex_mode(f: DataFrame) -> bool:
    return "vs" not in f.columns


def with_pattern(f: DataFrame, k: int) -> DataFrame:
    keys = code_keys(f)
    forms = written(patterns.canonicalize(f, k if vertex_mode(f) else None), "forms").select(*keys, "canon")
    return f.join(measured(forms), keys)


def build(f: DataFrame, k: int, per_pattern: bool = True) -> DataFrame:
    """Distinct store edges of the embeddings ``f`` of k words, of either mode: partial distinct where
    the rows are, one shuffle to merge. Flat rows: an entry's successors are never one array."""
    if k < 2:
        raise ValueError("a path store has two levels at least")
    held = with_pattern(f, k) if per_pattern else f.withColumn("canon", F.lit(""))
    steps = F.array(*[F.struct(F.lit(i).alias("level"), F.col(f"w{i}").alias("node"), F.col(f"w{i + 1}").alias("next")) for i in range(k - 1)])
    return held.select("canon", F.explode(steps).alias("s")).select("canon", "s.level", "s.node", "s.next").distinct()


def merge(stores: list[DataFrame]) -> DataFrame:
    """The union of stores built apart: one entry for each (canon, level, node, next)."""
    whole = stores[0]
    for s in stores[1:]:
        whole = whole.unionByName(s)
    return whole.distinct()


def share(store: DataFrame, limit_rows: int = 400_000) -> tuple[DataFrame, bool]:
    """The store for the level joins, and whether every worker gets all of it: broadcast where its measured size allows it, else shuffled."""
    small = store.count() <= limit_rows
    return (F.broadcast(store) if small else store), small


def decode(store: DataFrame, g: PropertyGraph, k: int, app: MiningApp | None = None, per_pattern: bool = True, parts: int | None = None, alpha: Alpha | None = None) -> DataFrame:
    """The embeddings of k words of a store: canon, the columns of their mode, and touch in vertex mode. No
    extension of a rejected prefix is looked at.

    The mode and the labels are those of ``app`` (vertex mode without labels if there is none).
    ``parts``: the paths are dealt to that many tasks in intervals of equal cost, and the
    result has their number as ``part``; with a store and a graph that may be broadcast, a
    task then decodes its own paths to the end. ``alpha``: the aggregation filter of a size.
    """
    edge_mode = app is not None and app.mode == "edge"
    labelled = app is not None and app.labelled and not edge_mode
    labels = app.labels if app is not None else "both"
    steps, small = share(store)

    if parts is None:
        now = spread(store.where("level = 0").select("canon", F.col("node").alias("w0")).distinct(), "canon", "w0")
        keep: tuple[str, ...] = ("canon",)
    else:
        now = balance.partition_paths(store, k, parts).select("canon", "part", "prefix", F.col("prefix")[0].alias("w0")).repartitionById(parts, F.col("part"))
        keep = ("canon", "part", "prefix")
    if edge_mode:
        lines = ends(g)
        now = seeded(now.join(g.shared(lines), F.col("w0") == F.col("eid")).drop("w0"), labels)
    elif labelled:
        named = g.vertices.select(F.col("vid").alias("w0"), F.array("vlabel").alias("labels"))
        now = now.join(measured(named), "w0").select(*keep, "w0", F.lit(0).cast("long").alias("code"), "labels")
    else:
        now = now.withColumn("code", F.lit(0).cast("long"))
    now = _filtered(now, app, 1, k, alpha)
    for i in range(1, k):
        step = steps.where(F.col("level") == i - 1).select("canon", F.col("node").alias(f"w{i - 1}"), F.col("next").alias("__word"))
        paths = now.join(F.broadcast(step) if small else step, ["canon", f"w{i - 1}"])
        paths = paths.where(every([F.col("__word") != F.col(w) for w in words(i)]) & (F.col("__word") > F.col("w0")))
        if parts is not None:  # the first words of a prefix are given
            paths = paths.where((F.size("prefix") <= i) | (F.col("__word") == F.col("prefix")[i]))
        if edge_mode:
            met = paths.join(g.shared(lines), F.col("__word") == F.col("eid"))
            now = grown_edges(met, i, labels, keep).where("ok").drop("ok")
        else:
            now = _grown(paths, g, i, keep, labelled)
        now = _filtered(now, app, i + 1, k, alpha)
        if i + 1 < k and not edge_mode:
            now = now.drop("touch")
    if per_pattern:
        keys = code_keys(now)
        now = written(now, f"paths-{k}")
        forms = patterns.canonicalize(now, None if edge_mode else k).select(*keys, F.col("canon").alias("__own"))
        now = now.join(forms, keys).where("__own = canon").drop("__own")
    return now.drop("prefix")


def _filtered(now: DataFrame, app: MiningApp | None, size: int, k: int, alpha: Alpha | None) -> DataFrame:
    """The prefixes that the application's filters let pass; none that was stopped before full length."""
    if app is None:
        return now
    view = EmbeddingView(size, app.mode, tuple(now.columns))
    now = now.where(app.filter(view)) if app.needs is None else now
    if app.termination is not None and size < k:
        now = now.where(~app.termination(view))
    return now if alpha is None else alpha(now, size)


def _grown(paths: DataFrame, g: PropertyGraph, i: int, keep: tuple[str, ...], labelled: bool) -> DataFrame:
    """Vertex-mode paths of i words and one word more that touches them and keeps the canonical order."""
    held = [*keep, *words(i), "code", *(["labels"] if labelled else []), "__word"]
    if g.small:
        touch = F.lit(0).cast("long")
        for j, w in enumerate(words(i)):
            table, same = g.linked(F.col(w), F.col("__word"), f"__t{j}")
            paths = paths.join(table, same, "left").select(*held, *[f"__t{n}" for n in range(j + 1)])
            touch = touch.bitwiseOR(F.when(F.col(f"__t{j}").isNotNull(), F.lit(1 << j).cast("long")).otherwise(0))
        found = paths.select(*held, touch.alias("touch")).where("touch <> 0")
    else:
        members = F.array(*[F.struct(F.lit(1 << j).cast("long").alias("bit"), F.col(w).alias("vid")) for j, w in enumerate(words(i))])
        met = paths.withColumn("m", F.explode(members)).select(*held, "m.bit", "m.vid").join(g.adjacency.select("vid", F.col("nbr").alias("__word")), ["vid", "__word"])
        found = met.groupBy(*held).agg(F.bit_or("bit").alias("touch"))
    found = found.where(is_canonical(i, touched(F.col("touch"), i), F.col("__word")))
    extra = []
    if labelled:
        found = found.join(measured(g.vertices.select(F.col("vid").alias("__word"), "vlabel")), "__word")
        extra = [F.concat("labels", F.array("vlabel")).alias("labels")]
    return found.select(*keep, *words(i), F.col("__word").alias(f"w{i}"), extended_code(F.col("code"), F.col("touch"), i).alias("code"), *extra, "touch")


def stored_and_decoded(level: DataFrame, g: PropertyGraph, k: int, app: MiningApp, store: str, alpha: Alpha | None = None) -> tuple[DataFrame, int]:
    """A level as the next step reads it from a path store, and the rows handed over (store edges, or
    embeddings); "auto" leaves it a list where that is smaller. The paths of a large store are dealt by cost to as many tasks as a shuffle has."""
    edges = written(build(level, k), f"paths-{k}")
    n, listed = edges.count(), level.count()
    if store == "auto" and n * EDGE_BYTES >= listed * k * WORD_BYTES:
        return level, listed
    parts = int(level.sparkSession.conf.get("spark.sql.shuffle.partitions")) if n >= DEALT_EDGES else None
    return written(decode(edges, g, k, app, parts=parts, alpha=alpha).select(level.columns), f"decoded-{k}"), n


def store_stats(store: DataFrame, g: PropertyGraph, k: int, app: MiningApp | None = None, per_pattern: bool = True) -> DataFrame:
    """One row: store_edges, paths (followed to the end without any test), embeddings, spurious (paths that are none)."""
    edges = store.agg(F.count(F.lit(1)).alias("store_edges"))
    paths = balance.path_costs(store, k).where("level = 0").agg(F.coalesce(F.sum("cost"), F.lit(0)).cast("long").alias("paths"))
    real = decode(store, g, k, app, per_pattern).agg(F.count(F.lit(1)).alias("embeddings"))
    return edges.crossJoin(paths).crossJoin(real).withColumn("spurious", F.col("paths") - F.col("embeddings"))


def sizes(f: DataFrame, store: DataFrame, k: int) -> DataFrame:
    """k, list_words, store_edges, list_bytes, store_bytes."""
    n = f.agg(F.count(F.lit(1)).alias("n"))
    e = store.agg(F.count(F.lit(1)).alias("store_edges"))
    return n.crossJoin(e).select(F.lit(k).alias("k"), (F.col("n") * k).alias("list_words"), "store_edges", (F.col("n") * k * WORD_BYTES).alias("list_bytes"), (F.col("store_edges") * EDGE_BYTES).alias("store_bytes"))


def prefix_tree_size(f: DataFrame, k: int) -> DataFrame:
    """level, n_prefixes: nodes of a prefix tree over the embeddings (its last level is all of them)."""
    out = None
    for i in range(k):
        row = f.select(*words(i + 1)).distinct().agg(F.count(F.lit(1)).alias("n_prefixes")).select(F.lit(i).alias("level"), "n_prefixes")
        out = row if out is None else out.unionByName(row)
    return out
