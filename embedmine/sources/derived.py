"""Graphs derived from the given tables. Each is built once in a session."""

from __future__ import annotations

import sys
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import triples
from .graph import ListedGraph, PropertyGraph, dense_ids

cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Vectors of a block, about (two meet in a task); vectors from which their graph is kept as packed lists.
BLOCK_ROWS, LISTED_ROWS = 8000, 2000
_built: dict[tuple, PropertyGraph] = {}


def once(make: Callable[..., PropertyGraph]) -> Callable[..., PropertyGraph]:
    def of(spark: SparkSession, sf_dir: str, *args) -> PropertyGraph:
        key = (spark.sparkContext.applicationId, make.__name__, sf_dir, args)
        if key not in _built:
            _built[key] = make(spark, sf_dir, *args)
        return _built[key]

    of.__name__, of.__doc__ = make.__name__, make.__doc__
    return of


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@once
def copart(spark: SparkSession, sf_dir: str, tau: int = 2, label: str = "p_type") -> PropertyGraph:
    """Parts that stand together in at least ``tau`` orders."""
    items = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    other = items.select("l_orderkey", F.col("l_partkey").alias("b"))
    pairs = items.join(other, "l_orderkey").where("l_partkey < b").groupBy(F.col("l_partkey").alias("a"), "b").count().where(F.col("count") >= tau)
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("vid"), F.col(label).alias("label"))
    return PropertyGraph.build(pairs.select("a", "b"), part)


@once
def similar(spark: SparkSession, sf_dir: str, c: float = 0.3) -> PropertyGraph:
    """Vectors of cosine at least ``c``; blocks of vectors are compared with blocks, each pair of blocks in one task.
    A graph of all pairs above a threshold takes all comparisons: its building is quadratic by definition."""
    blocks, n_rows = 1, table(spark, sf_dir, "embeddings").count()
    while n_rows / blocks > BLOCK_ROWS:
        blocks *= 2
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("block"))
    dealt = rows.select("vec_id", "embedding", "block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other"))
    dealt = dealt.select("vec_id", "embedding", "block", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"))

    def close(group: pa.Table) -> pa.Table:
        ids = group.column("vec_id").to_numpy()
        x = np.array(group.column("embedding").to_pylist(), np.float64)
        x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
        block, i, j = group.column("block").to_numpy(), group.column("i")[0].as_py(), group.column("j")[0].as_py()
        p, q = np.flatnonzero(block == i), np.flatnonzero(block == j)
        y, found = x[q].T, [(np.zeros(0, np.int64),) * 2]
        for first in range(0, len(p), 500):  # products of 500 rows at a time
            at, to = np.nonzero(x[p[first : first + 500]] @ y >= c)
            found.append((at + first, to))
        at, to = (np.concatenate(z) for z in zip(*found))
        a, b = ids[p[at]], ids[q[to]]
        keep = a < b if i == j else a != b
        return pa.table({"a": a[keep], "b": b[keep]})

    labels = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("vid"), F.col("label").cast("string").alias("label"))
    if n_rows > LISTED_ROWS:
        # Pairs leave a task as packed lists of neighbours, of which each vertex has one for each block.
        def listed(group: pa.Table) -> pa.Table:
            pairs = close(group)
            a, b = pairs.column("a").to_numpy(), pairs.column("b").to_numpy()
            return triples.packed(np.concatenate([a, b]), np.concatenate([b, a]))

        buckets = max(int(spark.conf.get("spark.sql.shuffle.partitions")), n_rows // 2000)
        return ListedGraph(triples.gathered(dealt.groupBy("i", "j").applyInArrow(listed, "vid long, nbrs binary"), buckets), labels)
    pairs = dealt.groupBy("i", "j").applyInArrow(close, "a long, b long")
    return PropertyGraph.build(pairs, labels)


@once
def shared_line(spark: SparkSession, sf_dir: str, lo: int = 2, hi: int = 12, label: str = "lang") -> PropertyGraph:
    """Documents that share a line of 20 or more characters which ``lo`` to ``hi`` documents hold."""
    lines = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.length("line") >= 20)
    lines = lines.select("doc_id", F.sha2("line", 256).alias("line")).distinct()
    held = lines.groupBy("line").count().where(F.col("count").between(lo, hi)).select("line")
    lines = lines.join(held, "line")
    pairs = lines.select("line", F.col("doc_id").alias("a")).join(lines.select("line", F.col("doc_id").alias("b")), "line").where("a < b").select("a", "b").distinct()
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("vid"), F.col(label).alias("label"))
    return PropertyGraph.build(pairs, docs)


@once
def custsupp(spark: SparkSession, sf_dir: str, q: int = 45) -> PropertyGraph:
    """Customers (even ids) and suppliers (odd ids) with a returned line of quantity at least ``q``;
    labels: nations, edge labels: the smallest order priority."""
    lines = table(spark, sf_dir, "lineitem").where((F.col("l_returnflag") == "R") & (F.col("l_quantity") >= q)).select("l_orderkey", "l_suppkey")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority")
    pairs = lines.join(orders, lines.l_orderkey == orders.o_orderkey).select((2 * F.col("o_custkey")).alias("a"), (2 * F.col("l_suppkey") + 1).alias("b"), "o_orderpriority")
    nation = table(spark, sf_dir, "nation").select("n_nationkey", "n_name")
    c = table(spark, sf_dir, "customer").select((2 * F.col("c_custkey")).alias("vid"), F.col("c_nationkey").alias("n_nationkey"))
    s = table(spark, sf_dir, "supplier").select((2 * F.col("s_suppkey") + 1).alias("vid"), F.col("s_nationkey").alias("n_nationkey"))
    return PropertyGraph.build(pairs, c.unionByName(s).join(nation, "n_nationkey").select("vid", F.col("n_name").alias("label")), "o_orderpriority")


@once
def coactive(spark: SparkSession, sf_dir: str, minutes: int = 10) -> PropertyGraph:
    """Users who fire the same event type within ``minutes``: a range join by time bins."""
    e = table(spark, sf_dir, "events").select("user_id", "event_type", F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', ts)").alias("t"))
    width = minutes * 60_000_000
    left = e.select(F.col("user_id").alias("a"), "event_type", F.col("t").alias("ta"), F.floor(F.col("t") / width).alias("bin"))
    right = e.select(F.col("user_id").alias("b"), "event_type", F.col("t").alias("tb"), F.explode(F.array(*[F.floor(F.col("t") / width) + i for i in (-1, 0, 1)])).alias("bin"))
    pairs = left.join(right, ["event_type", "bin"]).where(f"a < b and abs(ta - tb) <= {width}").groupBy("a", "b").agg(F.min("event_type").alias("event_type"))
    best = Window.partitionBy("user_id").orderBy(F.desc("count"), "event_type")
    labels = e.groupBy("user_id", "event_type").count().withColumn("r", F.row_number().over(best)).where("r = 1")
    return PropertyGraph.build(pairs, labels.select(F.col("user_id").alias("vid"), F.col("event_type").alias("label")), "event_type")


@once
def geo(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Regions, nations, customers and suppliers along their foreign keys: a forest."""
    n = table(spark, sf_dir, "nation")
    c = table(spark, sf_dir, "customer")
    s = table(spark, sf_dir, "supplier")
    region, nation = lambda x: 4 * x, lambda x: 4 * x + 1
    pairs = n.select(region(F.col("n_regionkey")).cast("long").alias("a"), nation(F.col("n_nationkey")).cast("long").alias("b"))
    pairs = pairs.unionByName(c.select(nation(F.col("c_nationkey")).cast("long").alias("a"), (4 * F.col("c_custkey") + 2).alias("b")))
    pairs = pairs.unionByName(s.select(nation(F.col("s_nationkey")).cast("long").alias("a"), (4 * F.col("s_suppkey") + 3).alias("b")))
    labels = pairs.select(F.explode(F.array("a", "b")).alias("vid")).distinct().select("vid", F.element_at(F.array(*map(F.lit, ("region", "nation", "customer", "supplier"))), (F.col("vid") % 4 + 1).cast("int")).alias("label"))
    return PropertyGraph.build(pairs, labels)


@once
def many_graphs(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """A collection: in each conversation, turns that follow one another. vid // 100000 is the graph."""
    t = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role").distinct()
    vid = F.col("conv_id") * 100_000 + F.col("turn")
    after = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    pairs = t.select(vid.alias("a"), (F.col("conv_id") * 100_000 + after).alias("b")).where("b is not null")
    return PropertyGraph.build(pairs, t.select(vid.alias("vid"), F.col("role").alias("label")))


@once
def weblink(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Pages (even ids) and the targets of their links (odd ids, by rank of the text)."""
    p = table(spark, sf_dir, "pages")
    links = p.select("page_id", "url", F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]+)"'))).alias("target"))
    targets = dense_ids(links.select("target").distinct(), ["target"], "place").select("target", (2 * F.col("place") + 3).alias("b"))
    pairs = links.join(targets, "target").select((2 * F.col("page_id")).alias("a"), "b")
    hosts = p.select((2 * F.col("page_id")).alias("vid"), F.regexp_extract("url", r"://([^/]+)", 1).alias("label"))
    return PropertyGraph.build(pairs, hosts.unionByName(targets.select(F.col("b").alias("vid"), F.lit("path").alias("label"))))


def from_rows(spark: SparkSession, pairs: list[tuple], labels: dict[int, str | None] | None = None) -> PropertyGraph:
    """A small graph from Python values: (a, b) or (a, b, edge label)."""
    wide = bool(pairs) and len(pairs[0]) == 3
    frame = spark.createDataFrame(pairs, "a long, b long, e string" if wide else "a long, b long")
    names = None if labels is None else spark.createDataFrame(list(labels.items()), "vid long, label string")
    return PropertyGraph.build(frame, names, "e" if wide else None)


def toy_house(spark: SparkSession) -> PropertyGraph:
    """Four vertices, blue and yellow in turn, three blue-yellow edges and one blue-blue one."""
    return from_rows(spark, [(1, 2), (2, 3), (3, 4), (1, 3)], {1: "blue", 2: "yellow", 3: "blue", 4: "yellow"})


def toy_paths(spark: SparkSession) -> PropertyGraph:
    return from_rows(spark, [(1, 4), (2, 3), (2, 4), (3, 4), (4, 5)])
