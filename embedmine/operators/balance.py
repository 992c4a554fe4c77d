"""Load balance over a path store: cost of each entry, intervals of paths, round robin."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.canonical import words
from ..plans.scratch import written
from ..sources.graph import PropertyGraph, dense_ids, running_sum

COST = "decimal(38,0)"
#: Bins of vertices between which waves are cut; bounds of all ids.
BINS, ALL = 2000, (-(1 << 63), (1 << 63) - 1)


def path_costs(store: DataFrame, k: int) -> DataFrame:
    """canon, level, node, cost: paths (canonical or not) that start at the entry; 1 in the last level."""
    below = store.where(F.col("level") == k - 2).select("canon", F.lit(k - 1).alias("level"), F.col("next").alias("node")).distinct().withColumn("cost", F.lit(1).cast(COST))
    out = below
    for level in range(k - 2, -1, -1):
        edges = store.where(F.col("level") == level).select("canon", "node", F.col("next").alias("__next"))
        costs = edges.join(below.select("canon", F.col("node").alias("__next"), "cost"), ["canon", "__next"]).groupBy("canon", "node").agg(F.sum("cost").cast(COST).alias("cost"))
        below = costs.select("canon", F.lit(level).alias("level"), "node", "cost")
        out = out.unionByName(below)
    return out


def partition_paths(store: DataFrame, k: int, parts: int) -> DataFrame:
    """canon, prefix, lo, hi, part: intervals of path ordinals, each in one part; parts differ by one path at most.

    Each pattern's store is divided apart. Entries of the first level lie in
    sequence; one that a bound cuts is replaced by its successors, level by
    level: at most parts - 1 entries a level and pattern go on. Sums over a level run
    range by range, so that no task sees all entries of a pattern.
    """
    costs = written(path_costs(store, k), "costs")
    total = costs.where("level = 0").groupBy("canon").agg(F.sum("cost").cast(COST).alias("total"))
    now = costs.where("level = 0").join(total, "canon").select("canon", "total", F.array().cast("array<bigint>").alias("prefix"), F.lit(0).cast(COST).alias("base"), "node", "cost")
    out = None
    for level in range(k):
        now = running_sum(now, ["canon", "prefix"], ["node"], "cost", "below", COST)
        now = now.withColumn("lo", (F.col("base") + F.col("below")).cast(COST)).withColumn("hi", (F.col("lo") + F.col("cost")).cast(COST))
        now = now.withColumn("part", F.expr(f"cast((lo * {parts}) div total as int)")).withColumn("last", F.expr(f"cast(((hi - 1) * {parts}) div total as int)"))
        now = written(now.withColumn("prefix", F.concat("prefix", F.array("node"))), "intervals")
        whole = now.where("part = last").select("canon", "prefix", "lo", "hi", "part")
        out = whole if out is None else out.unionByName(whole)
        if level == k - 1:
            break
        edges = store.where(F.col("level") == level).select("canon", "node", F.col("next").alias("__next"))
        children = now.where("part < last").select("canon", "total", "prefix", F.col("lo").alias("base"), "node").join(edges, ["canon", "node"]).drop("node")
        now = children.join(costs.where(F.col("level") == level + 1).select("canon", F.col("node").alias("__next"), "cost"), ["canon", "__next"]).withColumnRenamed("__next", "node")
        now = now.select("canon", "total", "prefix", "base", "node", "cost")
    return out


def partition_loads(n: DataFrame, parts: int) -> DataFrame:
    """part, n: the paths that :func:`partition_paths` gives to each part of a store, by the number of all (n, a row for
    each store). Its intervals hold every ordinal once, and an ordinal o lies in part o * parts div n."""
    each = n.select(F.col("n").cast(COST).alias("n"), F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"))
    begin = lambda p: F.expr(f"({p} * n + {parts - 1}) div {parts}")
    return each.select("part", (begin("(part + 1)") - begin("part")).cast("long").alias("n")).where("n > 0")


def round_robin(f: DataFrame, k: int, parts: int, block: int = 1) -> DataFrame:
    """Embeddings with their part: blocks of ``block`` in word order, dealt in turn."""
    return dense_ids(f, words(k), "ordinal").withColumn("part", (F.floor(F.col("ordinal") / block) % parts).cast("int"))


def round_robin_loads(n: DataFrame, parts: int, block: int = 1) -> DataFrame:
    """part, n: the rows that :func:`round_robin` gives to each part, by the number of all (one row, n)."""
    whole, rest = F.expr(f"n div {parts * block}"), F.col("n") % (parts * block)
    each = n.select("n", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"))
    return each.select("part", (whole * block + F.least(F.greatest(rest - F.col("part") * block, F.lit(0)), F.lit(block))).cast("long").alias("n")).where("n > 0")


def balance(parts: DataFrame, load: str) -> DataFrame:
    """n_parts, most, mean, imbalance (largest over mean)."""
    return parts.groupBy("part").agg(F.sum(load).cast("double").alias("load")).agg(F.count(F.lit(1)).alias("n_parts"), F.max("load").alias("most"), F.avg("load").alias("mean")).withColumn("imbalance", F.round(F.col("most") / F.col("mean"), 6))


def seed_waves(g: PropertyGraph, waves: int) -> list[tuple[int, int]]:
    """Ranges [low, high) of first words of near-equal estimated work (squares of degrees), cut between bins of
    about equally many vertices. Since an embedding starts at its smallest word, ranges can be mined to the
    end one after another."""
    if waves < 2:
        return [ALL]
    d = written(g.degrees.select("vid", (F.col("d") * F.col("d")).alias("work")), "work")
    bounds = sorted(set(d.agg(F.percentile_approx("vid", [i / BINS for i in range(BINS + 1)], 10 * BINS).alias("c")).first()["c"] or []))
    bin_ = F.when(F.col("vid") >= F.lit(bounds[-1]), F.lit(len(bounds) - 1)).otherwise(F.size(F.filter(F.lit(bounds), lambda x: x <= F.col("vid"))) - 1) if bounds else F.lit(0)
    sums = {r["b"]: r["w"] for r in d.groupBy(bin_.alias("b")).agg(F.sum("work").alias("w")).collect()}  # BINS + 1 rows at most
    total, done, cuts = sum(sums.values()), 0, []
    for b in sorted(sums):
        # A range ends before the bin that would carry it further past its share than it now falls short.
        if len(cuts) < waves - 1 and cuts[-1:] != [bounds[b]] and done and abs(done - total * (len(cuts) + 1) / waves) <= abs(done + sums[b] - total * (len(cuts) + 1) / waves):
            cuts.append(bounds[b])
        done += sums[b]
    edges = [ALL[0], *cuts, ALL[1]]
    return list(zip(edges[:-1], edges[1:]))


def estimate_level(f: DataFrame, g: PropertyGraph, k: int) -> DataFrame:
    """One row: the neighbours of all members, an upper bound on the next step's candidates."""
    degree = g.adjacency.groupBy("vid").agg(F.count(F.lit(1)).alias("d"))
    return f.select(F.explode(F.array(*words(k))).alias("vid")).join(degree, "vid").agg(F.coalesce(F.sum("d"), F.lit(0)).alias("candidates_at_most"))
