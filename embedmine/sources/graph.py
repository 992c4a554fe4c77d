"""One large undirected graph with labels, as DataFrames."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..operators import triples
from ..plans.scratch import written

#: Adjacency rows up to which an expansion may broadcast them (at most 40 bytes each).
BROADCAST_ROWS = 400_000


def dense_ids(df: DataFrame, order: list[str], name: str) -> DataFrame:
    """Adds ``name``: the row's place from 0 in ``order``. Ranges are numbered apart and
    the counts of the ranges before are added, so no task sees all rows."""
    ranged = written(df.repartitionByRange(*order).withColumn("__range", F.spark_partition_id()), "ranged")
    counts = ranged.groupBy("__range").agg(F.count(F.lit(1)).alias("__n"))
    before = counts.select("__range", (F.sum("__n").over(Window.orderBy("__range")) - F.col("__n")).alias("__before"))
    at = F.row_number().over(Window.partitionBy("__range").orderBy(*order))
    return ranged.withColumn("__at", at).join(F.broadcast(before), "__range").withColumn(name, F.col("__before") + F.col("__at") - 1).drop("__range", "__at", "__before")


def running_sum(df: DataFrame, group: list[str], order: list[str], value: str, name: str, kind: str) -> DataFrame:
    """Adds ``name``: the sum of ``value`` over the rows before, in ``order`` within ``group``. As in
    :func:`dense_ids`, ranges are summed apart, however many rows a group has."""
    ranged = written(df.repartitionByRange(*group, *order).withColumn("__range", F.spark_partition_id()), "ranged")
    sums = ranged.groupBy("__range", *group).agg(F.sum(value).cast(kind).alias("__n"))  # one row a range, but for groups within it
    before = sums.select("__range", *group, F.coalesce(F.sum("__n").over(Window.partitionBy(*group).orderBy("__range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).cast(kind).alias("__before"))
    inner = F.coalesce(F.sum(value).over(Window.partitionBy("__range", *group).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return ranged.withColumn("__at", inner).join(before, ["__range", *group]).withColumn(name, (F.col("__before") + F.col("__at")).cast(kind)).drop("__range", "__at", "__before")


def measured(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` for a join: broadcast if its count allows it, else joined by shuffle."""
    return F.broadcast(df) if df.count() <= rows else df


@dataclass
class PropertyGraph:
    """vertices: vid long, vlabel int, vlabel_text; edges: eid long, src < dst, elabel int.

    Simple and undirected. Label 0 stands for "no label"; a null text label is
    that too. ``adjacency`` has both directions with the neighbour's label.
    """

    vertices: DataFrame
    edges: DataFrame
    n_edges: int = 0
    #: Whether two ids fit into one long.
    narrow: bool = False
    _adjacency: DataFrame | None = field(default=None, repr=False)
    _lists: DataFrame | None = field(default=None, repr=False)
    _triples: DataFrame | None = field(default=None, repr=False)

    @classmethod
    def build(cls, pairs: DataFrame, labels: DataFrame | None = None, edge_label: str | None = None) -> PropertyGraph:
        """From pairs (a, b[, edge_label]) in any order, and labels (vid, label text).

        Loops go, parallel edges become one (with the smallest label). Vertices
        are those of ``labels`` and all endpoints.
        """
        kept = pairs.where("a <> b").select(F.least("a", "b").cast("long").alias("src"), F.greatest("a", "b").cast("long").alias("dst"), (F.col(edge_label) if edge_label else F.lit(None)).cast("string").alias("elabel_text"))
        kept = kept.groupBy("src", "dst").agg(F.min("elabel_text").alias("elabel_text"))
        edges = dense_ids(kept, ["src", "dst"], "eid")
        if edge_label:
            edges = edges.join(codes(edges, "elabel_text", "elabel"), "elabel_text", "left").withColumn("elabel", F.coalesce("elabel", F.lit(0)))
        else:
            edges = edges.withColumn("elabel", F.lit(0))
        edges = written(edges.select("eid", "src", "dst", "elabel", "elabel_text"), "edges")
        return cls.of(cls.named(edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct(), labels), edges)

    @staticmethod
    def named(ends: DataFrame, labels: DataFrame | None) -> DataFrame:
        """The vertex table: those of ``labels`` and the distinct ``ends``; written."""
        if labels is None:
            vertices = ends.select("vid", F.lit(0).alias("vlabel"), F.lit(None).cast("string").alias("vlabel_text"))
        else:
            named = labels.select(F.col("vid").cast("long"), F.col("label").cast("string").alias("vlabel_text"))
            named = named.groupBy("vid").agg(F.min("vlabel_text").alias("vlabel_text"))
            named = named.unionByName(ends.join(named, "vid", "left_anti").select("vid", F.lit(None).cast("string").alias("vlabel_text")))
            vertices = named.join(codes(named, "vlabel_text", "vlabel"), "vlabel_text", "left").select("vid", F.coalesce("vlabel", F.lit(0)).alias("vlabel"), "vlabel_text")
        return written(vertices, "vertices")

    @classmethod
    def of(cls, vertices: DataFrame, edges: DataFrame) -> PropertyGraph:
        """From finished tables; counts the edges and looks at the range of their ends."""
        n, low, high = edges.agg(F.count(F.lit(1)), F.min("src"), F.max("dst")).first()
        return cls(vertices, edges, n, n == 0 or (low >= 0 and high < 1 << 31))

    @property
    def adjacency(self) -> DataFrame:
        """vid, nbr, eid, elabel, vlabel (of vid), nlabel (of nbr), written once."""
        if self._adjacency is None:
            both = self.edges.select(F.explode(F.array(F.struct(F.col("src").alias("vid"), F.col("dst").alias("nbr")), F.struct(F.col("dst").alias("vid"), F.col("src").alias("nbr")))).alias("x"), "eid", "elabel").select("x.vid", "x.nbr", "eid", "elabel")
            v = self.vertices.select("vid", "vlabel")
            both = both.join(v, "vid").join(v.select(F.col("vid").alias("nbr"), F.col("vlabel").alias("nlabel")), "nbr")
            self._adjacency = written(both.select("vid", "nbr", "eid", "elabel", "vlabel", "nlabel"), "adjacency")
        return self._adjacency

    @property
    def lists(self) -> DataFrame:
        """vid, d, nbrs: the packed neighbours of each vertex with an edge, written once."""
        if self._lists is None:
            self._lists = triples.lists_of(self.edges, self.n_edges)
        return self._lists

    @property
    def triples(self) -> DataFrame:
        """What :func:`triples.by_vertex` counts, once."""
        if self._triples is None:
            self._triples = triples.by_vertex(self.lists, self.n_edges)
        return self._triples

    @property
    def degrees(self) -> DataFrame:
        """vid, d of each vertex with an edge."""
        return self.adjacency.groupBy("vid").agg(F.count(F.lit(1)).alias("d")) if self.small else self.lists.select("vid", "d")

    @property
    def small(self) -> bool:
        return 2 * self.n_edges <= BROADCAST_ROWS

    def linked(self, a: Column, b: Column, flag: str) -> tuple[DataFrame, Column]:
        """(table, condition) of a join that sets ``flag`` to 1 where a and b are neighbours."""
        both = self.adjacency
        if self.narrow:
            table = both.select(F.shiftleft("vid", 32).bitwiseOR(F.col("nbr")).alias(f"{flag}_to"), F.lit(1).alias(flag))
            return self.shared(table), F.shiftleft(a, 32).bitwiseOR(b) == F.col(f"{flag}_to")
        table = both.select(F.col("vid").alias(f"{flag}_of"), F.col("nbr").alias(f"{flag}_to"), F.lit(1).alias(flag))
        return self.shared(table), (a == F.col(f"{flag}_of")) & (b == F.col(f"{flag}_to"))

    def shared(self, df: DataFrame) -> DataFrame:
        """``df``, broadcast if the graph's measured size allows it."""
        return F.broadcast(df) if self.small else df

    def stats(self) -> DataFrame:
        """n_vertices (with an edge), n_edges, n_labels (of all vertices), avg_degree."""
        used = self.edges.select(F.explode(F.array("src", "dst")).alias("vid")).agg(F.countDistinct("vid").alias("n_vertices"))
        m = self.edges.agg(F.count(F.lit(1)).alias("n_edges"))
        labels = self.vertices.agg(F.countDistinct("vlabel_text").alias("n_labels"))
        ratio = F.when(F.col("n_vertices") > 0, 2 * F.col("n_edges") / F.col("n_vertices")).otherwise(0.0)
        return used.crossJoin(m).crossJoin(labels).withColumn("avg_degree", F.round(ratio, 6))

    def validate(self) -> dict[str, int]:
        """Numbers of violations: repeated vertex or edge ids, loops or src > dst, parallel edges, unknown ends."""
        v, e = self.vertices, self.edges
        ends = e.select(F.explode(F.array("src", "dst")).alias("vid"))
        return {
            "repeated_vertices": v.groupBy("vid").count().where("count > 1").count(),
            "repeated_edges": e.groupBy("eid").count().where("count > 1").count(),
            "loops_or_order": e.where("src >= dst").count(),
            "parallel": e.groupBy("src", "dst").count().where("count > 1").count(),
            "unknown_ends": ends.join(v, "vid", "left_anti").count(),
        }

    def induced(self, keep) -> PropertyGraph:
        """The subgraph of the vertices that fulfil ``keep``; ids stay."""
        v = written(self.vertices.where(keep), "vertices")
        ids = v.select("vid")
        e = self.edges.join(ids.withColumnRenamed("vid", "src"), "src", "left_semi").join(ids.withColumnRenamed("vid", "dst"), "dst", "left_semi")
        e = written(e.select(self.edges.columns), "edges")
        return PropertyGraph.of(v, e)

    def relabelled_by_degree(self) -> PropertyGraph:
        """Ids by rising degree: canonical orders then start at vertices of low degree, away from hubs."""
        degree = self.edges.select(F.explode(F.array("src", "dst")).alias("vid")).groupBy("vid").agg(F.count(F.lit(1)).alias("d"))
        order = dense_ids(self.vertices.join(degree, "vid", "left").withColumn("d", F.coalesce("d", F.lit(0))), ["d", "vid"], "new")
        order = written(order.select("vid", "new", "vlabel_text"), "order")
        of = order.select("vid", "new")
        pairs = self.edges.join(of.select(F.col("vid").alias("src"), F.col("new").alias("a")), "src").join(of.select(F.col("vid").alias("dst"), F.col("new").alias("b")), "dst")
        return PropertyGraph.build(pairs.select("a", "b", "elabel_text"), order.select(F.col("new").alias("vid"), F.col("vlabel_text").alias("label")), "elabel_text")


class ListedGraph(PropertyGraph):
    """A graph given by its packed neighbour lists. Its tables of vertices, edges and adjacency, which take many
    times their room, are built when something asks for them."""

    def __init__(self, lists: DataFrame, labels: DataFrame):
        n, low, high = lists.agg(F.coalesce(F.sum("d"), F.lit(0)), F.min("vid"), F.max("vid")).first()
        self.n_edges, self.narrow = n // 2, n == 0 or (low >= 0 and high < 1 << 31)
        self._lists, self._labels, self._graph, self._vertices = lists, labels, None, None

    def _built(self) -> PropertyGraph:
        if self._graph is None:
            self._graph = PropertyGraph.build(triples.pairs_of(self._lists), self._labels)
        return self._graph

    @property
    def vertices(self) -> DataFrame:
        if self._vertices is None:
            self._vertices = self.named(self._lists.select("vid"), self._labels)
        return self._vertices

    @property
    def edges(self) -> DataFrame:
        return self._built().edges


def codes(df: DataFrame, text: str, name: str) -> DataFrame:
    """Distinct texts of a label column numbered from 1, for a join: broadcast if they are few by their count."""
    distinct = df.select(text).where(F.col(text).isNotNull()).distinct()
    numbered = dense_ids(distinct, [text], "__place").select(text, (F.col("__place") + 1).cast("int").alias(name))
    return measured(written(numbered, "labels"))
