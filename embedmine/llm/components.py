"""Connected components of an edge table, by star contractions; nothing goes to the driver
but a count and a checksum a round."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import spread_join, written


def components(edges: DataFrame) -> DataFrame:
    """(a, b) long pairs to (node, root): the smallest node reachable from each node that has an edge.

    Rounds alternate: first every node hands its larger neighbours to its smallest
    one, then every node ties its smaller neighbours together. The number of
    rounds grows with the logarithm of a component's size. The edges of a node with
    very many neighbours are never gathered in one task. Loops, repeated and
    reversed edges are allowed; an empty table gives an empty one.
    """
    now = written(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    seen = None
    while True:
        mark = now.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("a", "b"))).first()
        if tuple(mark) == seen or not mark[0]:
            break
        seen = tuple(mark)
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = spread_join(both, least, ["a"], ["b"]).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        low = large.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        floor = low.groupBy("a").agg(F.min("b").alias("m"))
        tied = spread_join(low, floor, ["a"], ["b"]).where("b <> m").select(F.greatest("b", "m").alias("a"), F.least("b", "m").alias("b"))
        now = written(tied.unionByName(floor.select("a", F.col("m").alias("b"))).distinct(), "edges")
    roots = now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct()
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(roots)
