"""Readers and writers of graphs: edge lists, label files, adjacency lines, JSON, ORC; SQL functions and views."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..plans.scratch import scratch_root
from .graph import PropertyGraph


def read_edge_list(spark: SparkSession, path: str, separator: str = " ") -> DataFrame:
    """Lines "src dst [label]" to a, b, e; blank lines and comments (#) are passed over."""
    part = F.split(F.trim("value"), separator)
    lines = spark.read.text(path).where((F.trim("value") != "") & ~F.col("value").startswith("#"))
    return lines.select(part[0].cast("long").alias("a"), part[1].cast("long").alias("b"), F.when(F.size(part) > 2, part[2]).alias("e"))


def read_labels(spark: SparkSession, path: str) -> DataFrame:
    """CSV lines vid,label."""
    return spark.read.schema("vid long, label string").csv(path)


def read_adjacency_lines(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """Lines "vid label nbr nbr ..." to (pairs, labels)."""
    part = F.split(F.trim("value"), r"\s+")
    lines = spark.read.text(path).where(F.trim("value") != "")
    pairs = lines.select(part[0].cast("long").alias("a"), F.explode(F.slice(part, 3, F.greatest(F.size(part) - 2, F.lit(0))).cast("array<bigint>")).alias("b"))
    return pairs, lines.select(part[0].cast("long").alias("vid"), part[1].alias("label"))


def write_adjacency_lines(g: PropertyGraph, path: str) -> None:
    near = g.adjacency.groupBy("vid").agg(F.array_join(F.array_sort(F.collect_list("nbr")).cast("array<string>"), " ").alias("n"))
    g.vertices.join(near, "vid", "left").select(F.concat_ws(" ", F.col("vid").cast("string"), F.coalesce("vlabel_text", F.lit("-")), F.coalesce("n", F.lit(""))).alias("value")).write.text(path)


def write_edge_list(g: PropertyGraph, path: str) -> None:
    g.edges.select(F.concat_ws(" ", F.col("src").cast("string"), F.col("dst").cast("string")).alias("value")).write.text(path)


def read_pairs(spark: SparkSession, path: str, kind: str = "json") -> DataFrame:
    """Edges (a, b, e) from JSON lines or ORC files with these columns; e may be missing or null."""
    if kind == "json":
        return spark.read.schema("a long, b long, e string").json(path)
    found = spark.read.format(kind).load(path)
    return found.select(F.col("a").cast("long"), F.col("b").cast("long"), (F.col("e") if "e" in found.columns else F.lit(None)).cast("string").alias("e"))


def write_pairs(g: PropertyGraph, path: str, kind: str = "json") -> None:
    g.edges.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.col("elabel_text").alias("e")).write.format(kind).save(path)


def write_embeddings(f: DataFrame, path: str, step: int, mode: str = "append") -> None:
    """A step's embeddings below ``path``, partitioned by step."""
    f.withColumn("step", F.lit(step)).write.mode(mode).partitionBy("step").parquet(path)


def edge_list_round_trip(g: PropertyGraph) -> DataFrame:
    path = f"{scratch_root(g.edges.sparkSession)}/edge-list-{uuid.uuid4().hex}"
    write_edge_list(g, path)
    return read_edge_list(g.edges.sparkSession, path).select("a", "b")


def pairs_round_trip(g: PropertyGraph, kind: str) -> DataFrame:
    path = f"{scratch_root(g.edges.sparkSession)}/pairs-{uuid.uuid4().hex}"
    write_pairs(g, path, kind)
    return read_pairs(g.edges.sparkSession, path, kind)


@udtf(returnType="a int, b int")
class DecodeCode:
    """Edges (a, b) between positions of a vertex-mode quick code."""

    def eval(self, code: int):
        b, at = 1, 0
        while code >> at:
            for a in range(b):
                if code >> (at + a) & 1:
                    yield a, b
            at += b
            b += 1


def register_functions(spark: SparkSession) -> None:
    spark.udtf.register("decode_code", DecodeCode)


def register_views(g: PropertyGraph, prefix: str = "") -> None:
    """Temporary views vertices, edges, adjacency."""
    g.vertices.createOrReplaceTempView(f"{prefix}vertices")
    g.edges.createOrReplaceTempView(f"{prefix}edges")
    g.adjacency.createOrReplaceTempView(f"{prefix}adjacency")


def mine_sql(g: PropertyGraph, what: str, **options) -> DataFrame:
    """Runs a mining method and registers its result as a view of that name: motifs, cliques, patterns, embeddings, path_store."""
    from ..apps import cliques, fsm, motifs
    from ..operators import layered

    register_views(g)
    if what == "motifs":
        out = motifs.count_motifs(g, **options)
    elif what == "cliques":
        out = cliques.clique_counts(g, **options)
    elif what == "patterns":
        out = fsm.frequent_subgraphs(g, **options).patterns
    elif what == "embeddings":
        out = motifs.embeddings(g, **options)
    elif what == "path_store":
        out = layered.build(motifs.embeddings(g, options["size"]), options["size"])
    else:
        raise ValueError(f"unknown method {what}")
    out.createOrReplaceTempView(what)
    return out
