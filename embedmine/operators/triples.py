"""Embeddings of three vertices, counted instead of generated, on graphs that are too large to broadcast.

The neighbours of a vertex are one packed list. Triangles are intersections of lists, made where blocks of lists
meet; nothing of the size of a step's candidates is shuffled or stored. Other connected triples follow from places
in the lists. Counts are kept for each first (smallest) word and quick code, as the engine's last step has them.
"""

from __future__ import annotations

import sys
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import written

cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Neighbours of a block's lists, about; two blocks meet in a task.
BLOCK_ENTRIES = 4_000_000
#: Neighbours gathered at once by a task.
GATHERED = 1_000_000


def pack(ids: np.ndarray) -> bytes:
    """Rising ids by their differences, compressed."""
    return zlib.compress(np.diff(ids, prepend=0).astype("<i8").tobytes(), 1)


def unpack(data: bytes) -> np.ndarray:
    return np.cumsum(np.frombuffer(zlib.decompress(data), "<i8"))


def packed(vid: np.ndarray, nbr: np.ndarray) -> pa.Table:
    """vid, nbrs: a packed list for each vertex of the pairs; repeated pairs count once."""
    order = np.lexsort((nbr, vid))
    vid, nbr = vid[order], nbr[order]
    fresh = np.ones(len(vid), bool)
    fresh[1:] = (vid[1:] != vid[:-1]) | (nbr[1:] != nbr[:-1])
    vid, nbr = vid[fresh], nbr[fresh]
    ids, at = np.unique(vid, return_index=True)
    ends = [*at[1:], len(vid)]
    return pa.table({"vid": pa.array(ids, pa.int64()), "nbrs": pa.array([pack(nbr[a:b]) for a, b in zip(at, ends)], pa.binary())})


def flat(vids: pa.ChunkedArray, lists: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(vid, length) of each list, and all neighbours in turn."""
    arrays = [unpack(x) for x in lists.to_pylist()]
    return vids.to_numpy().astype(np.int64), np.array([len(a) for a in arrays], np.int64), np.concatenate(arrays) if arrays else np.zeros(0, np.int64)


def gathered(parts: DataFrame, buckets: int) -> DataFrame:
    """vid, d, nbrs: parts of lists (vid, nbrs) as one list for each vertex, written."""

    def merge(group: pa.Table) -> pa.Table:
        vid, length, nbr = flat(group.column("vid"), group.column("nbrs"))
        out = packed(np.repeat(vid, length), nbr)
        return out.append_column("d", pa.array([len(unpack(x)) for x in out.column("nbrs").to_pylist()], pa.int64())).select(["vid", "d", "nbrs"])

    return written(parts.groupBy(F.pmod(F.xxhash64("vid"), F.lit(buckets))).applyInArrow(merge, "vid long, d long, nbrs binary"), "lists")


def lists_of(edges: DataFrame, n_edges: int) -> DataFrame:
    """The packed lists of edges src, dst."""
    both = edges.select(F.explode(F.array(F.struct(F.col("src").alias("vid"), F.col("dst").alias("nbr")), F.struct(F.col("dst").alias("vid"), F.col("src").alias("nbr")))).alias("x")).select("x.vid", "x.nbr")

    def part(batches):
        for batch in batches:
            if batch.num_rows:
                yield from packed(batch.column("vid").to_numpy(), batch.column("nbr").to_numpy()).to_batches()

    shuffles = int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return gathered(both.mapInArrow(part, "vid long, nbrs binary"), max(shuffles, 2 * n_edges // BLOCK_ENTRIES))


def pairs_of(lists: DataFrame) -> DataFrame:
    """a < b of each edge."""

    def spell(batches):
        for batch in batches:
            for row in batch.to_batches() if isinstance(batch, pa.Table) else [batch]:
                for vid, data in zip(row.column("vid").to_pylist(), row.column("nbrs").to_pylist()):
                    up = unpack(data)
                    up = up[up > vid]
                    if len(up):
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(up), vid, np.int64)), pa.array(up)], names=["a", "b"])

    return lists.mapInArrow(spell, "a long, b long")


def places(lists: DataFrame) -> DataFrame:
    """vid, far: over the larger neighbours of a vertex, their neighbours that are larger than it."""

    def run(batches):
        for batch in batches:
            vid, length, nbr = flat(pa.chunked_array([batch.column("vid")]), pa.chunked_array([batch.column("nbrs")]))
            start = np.cumsum(length) - length
            after = np.repeat(start + length - 1, length) - np.arange(len(nbr))
            low = nbr < np.repeat(vid, length)
            ids, of = np.unique(nbr[low], return_inverse=True)
            far = np.zeros(len(ids), np.int64)
            np.add.at(far, of, after[low])
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(far)], names=["vid", "far"])

    return lists.mapInArrow(run, "vid long, far long").groupBy("vid").agg(F.sum("far").alias("far"))


def blocks_of(n_edges: int) -> int:
    return max(3, -(-n_edges // BLOCK_ENTRIES))


def larger(lists: DataFrame) -> DataFrame:
    """vid, nbrs: the larger neighbours of each vertex that has some, which is all that :func:`meetings` reads."""

    def run(batches):
        for batch in batches:
            ids, lists = [], []
            for vid, data in zip(batch.column("vid").to_pylist(), batch.column("nbrs").to_pylist()):
                up = unpack(data)
                up = up[up > vid]
                if len(up):
                    ids.append(vid)
                    lists.append(pack(up))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(lists, pa.binary())], names=["vid", "nbrs"])

    return lists.select("vid", "nbrs").mapInArrow(run, "vid long, nbrs binary")


def dealt(lists: DataFrame, n_edges: int) -> DataFrame:
    """The lists with their block, once for each pair i <= j of blocks that theirs is in."""
    blocks = blocks_of(n_edges)
    out = lists.select("vid", "nbrs", F.pmod(F.xxhash64("vid"), F.lit(blocks)).cast("int").alias("block"))
    out = out.select("vid", "nbrs", "block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other"))
    return out.select("vid", "nbrs", "block", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"))


def met(lists: DataFrame, n_edges: int) -> DataFrame:
    """The lists as tasks read them: each pair of blocks is one partition."""
    blocks = blocks_of(2 * n_edges)
    pair = (F.col("j") * (F.col("j") + 1) / 2 + F.col("i")).cast("int")
    return dealt(lists, 2 * n_edges).withColumn("pair", pair).repartitionById(blocks * (blocks + 1) // 2, F.col("pair")).drop("pair")


def crossed(lists: DataFrame, blocks: int, names: str = "ij") -> DataFrame:
    """A row for each i <= j of the ``blocks`` (and each k) with the lists of its blocks, for :func:`groups`.

    A block is one row in one partition, and partitions meet as a product of tables: a list is shuffled to its block
    and with it, not once more for each of the other blocks.
    """

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        some = [b for b in batches if b.num_rows]
        if some:
            table = pa.Table.from_batches(some)
            ends = pa.array([0, table.num_rows], pa.int32())
            one = [pa.ListArray.from_arrays(ends, table.column(c).combine_chunks()) for c in ("vid", "nbrs")]
            yield pa.RecordBatch.from_arrays([table.column("block").combine_chunks()[:1], *one], names=["block", "vids", "nbrs"])

    rows = lists.select("vid", "nbrs", F.pmod(F.xxhash64("vid"), F.lit(blocks)).cast("int").alias("block")).repartitionById(blocks, F.col("block"))
    rows = rows.mapInArrow(whole, "block int, vids array<long>, nbrs array<binary>").repartitionById(blocks, F.col("block"))
    sides = [rows.select(F.col("block").alias(c), F.col("vids").alias(f"vids_{c}"), F.col("nbrs").alias(f"nbrs_{c}")) for c in names]
    out = sides[0].crossJoin(sides[1].hint("shuffle_replicate_nl")).where("i <= j")
    for side in sides[2:]:
        out = out.crossJoin(side.hint("shuffle_replicate_nl"))
    return out


def groups(batches: Iterator[pa.RecordBatch], names: str = "ij") -> Iterator[pa.Table]:
    """Of each row of :func:`crossed`, the lists: vid, nbrs, block, and the row's blocks i, j (and k)."""
    for batch in batches:
        for row in range(batch.num_rows):
            blocks = {c: batch.column(c)[row].as_py() for c in names}
            of = {b: c for c, b in blocks.items()}  # each block once
            vid, nbrs = (pa.concat_arrays([batch.column(f"{x}_{c}")[row].values for c in of.values()]) for x in ("vids", "nbrs"))
            block = np.repeat(list(of), [len(batch.column(f"vids_{c}")[row]) for c in of.values()])
            yield pa.table({"vid": vid, "nbrs": nbrs, "block": block} | {c: np.full(len(vid), b) for c, b in blocks.items()})


def meetings(group: pa.Table) -> Iterator[tuple[np.ndarray, int, np.ndarray, np.ndarray]]:
    """(ids, x, y, z): triangles of a smallest vertex x, as places in the rising ``ids``, whose two smaller
    vertices x < y are an edge between the blocks i and j of the task. The lists are those of both blocks."""
    vid, length, nbr = flat(group.column("vid"), group.column("nbrs"))
    block, i, j = group.column("block").to_numpy(), group.column("i")[0].as_py(), group.column("j")[0].as_py()
    larger = nbr > np.repeat(vid, length)
    up = np.add.reduceat(larger.astype(np.int64), np.cumsum(length) - length)
    nbr = nbr[larger]
    ids = np.unique(np.concatenate([vid, nbr]))
    at, to = np.searchsorted(ids, vid), np.searchsorted(ids, nbr)
    start = np.cumsum(up) - up
    row = np.full(len(ids), -1, np.int64)
    row[at] = np.arange(len(vid))
    mark = np.zeros(len(ids), bool)
    for x in range(len(vid)):
        mine = to[start[x] : start[x] + up[x]]
        rows = row[mine]
        rows = rows[rows >= 0]
        # Both ends in one block meet in the task of that block alone.
        rows = rows[(block[rows] == (j if block[x] == i else i)) & (up[rows] > 0)]
        if not len(rows):
            continue
        mark[mine] = True
        ends = np.cumsum(up[rows])
        done = 0
        while done < len(rows):
            # As many lists at once as fit, one at least.
            before = ends[done - 1] if done else 0
            more = max(done + 1, int(np.searchsorted(ends, before + GATHERED, "right")))
            some = rows[done:more]
            size = up[some]
            first = np.cumsum(size) - size
            third = to[np.repeat(start[some] - first, size) + np.arange(int(size.sum()))]
            hit = np.flatnonzero(mark[third])
            yield ids, at[x], at[some][np.searchsorted(first, hit, "right") - 1], third[hit]
            done = more
        mark[mine] = False


def closed(lists: DataFrame, n_edges: int) -> DataFrame:
    """vid, tri, low: triangles at a vertex, and those of which it is the smallest.

    Blocks of vertices meet two by two: the task of blocks i and j has the larger neighbours of their vertices, and
    for every edge between them the lists of its ends; each edge's triangles that end in a larger vertex are counted there.
    """

    def meet(group: pa.Table) -> pa.Table:
        ids, tri, low = None, None, None
        for ids, x, y, z in meetings(group):
            if tri is None:
                tri, low = np.zeros(len(ids), np.int64), np.zeros(len(ids), np.int64)
            low[x] += len(z)
            for at in (y, z):
                if len(at) * 4 > len(ids):
                    tri += np.bincount(at, minlength=len(ids))
                else:
                    np.add.at(tri, at, 1)
        if tri is None:
            return pa.table({"vid": pa.array([], pa.int64()), "tri": pa.array([], pa.int64()), "low": pa.array([], pa.int64())})
        tri += low
        some = np.flatnonzero(tri)
        return pa.table({"vid": pa.array(ids[some], pa.int64()), "tri": pa.array(tri[some]), "low": pa.array(low[some])})

    return dealt(larger(lists), n_edges).groupBy("i", "j").applyInArrow(meet, "vid long, tri long, low long").groupBy("vid").agg(F.sum("tri").alias("tri"), F.sum("low").alias("low"))


def listed(lists: DataFrame, n_edges: int, orders: tuple[str, ...] = ("xyz",)) -> DataFrame:
    """x < y < z of each triangle, or its images in each of the ``orders`` of x, y and z; the tasks hand them on as they
    find them, one order after another, so that equal values stand together."""

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def images() -> Iterator[pa.RecordBatch]:
            found = dict(zip("xyz", (pa.array(np.concatenate(c)) for c in zip(*held))))
            for order in orders:
                yield pa.RecordBatch.from_arrays([found[c] for c in order], names=["x", "y", "z"])

        tables = list(batches)
        if not any(b.num_rows for b in tables):
            return
        for ids, x, y, z in meetings(pa.Table.from_batches(tables)):
            if len(z):
                held.append((np.full(len(z), ids[x]), ids[y], ids[z]))
                n += len(z)
            if n >= 100_000:
                yield from images()
                held, n = [], 0
        if held:
            yield from images()

    return met(larger(lists), n_edges).mapInArrow(meet, "x long, y long, z long")


def by_vertex(lists: DataFrame, n_edges: int) -> DataFrame:
    """vid, d, up (larger neighbours), tri (triangles at it), low (those of which it is the smallest), far (see
    :func:`places`), of each vertex with an edge; written."""
    known = lists.select("vid", "d").join(places(lists), "vid", "left").join(closed(lists, n_edges), "vid", "left")

    def count(batches):
        for batch in batches:
            vid, length, nbr = flat(pa.chunked_array([batch.column("vid")]), pa.chunked_array([batch.column("nbrs")]))
            up = np.add.reduceat((nbr > np.repeat(vid, length)).astype(np.int64), np.cumsum(length) - length) if len(vid) else length
            yield pa.RecordBatch.from_arrays([pa.array(vid), pa.array(up)], names=["vid", "up"])

    ups = lists.mapInArrow(count, "vid long, up long")
    zero = [F.coalesce(c, F.lit(0)).alias(c) for c in ("tri", "low", "far")]
    return written(known.join(ups, "vid").select("vid", "d", "up", *zero), "triples")


def by_first(stats: DataFrame) -> DataFrame:
    """w0, code, n: the canonical embeddings of three vertices by first word and quick code."""
    pairs = (F.col("up") * (F.col("up") - 1) / 2).cast("long")
    # The third word touches the first one alone, the second one alone, or both.
    codes = [(3, pairs - F.col("low")), (5, F.col("far") - 2 * F.col("low")), (7, F.col("low"))]
    each = F.array(*[F.struct(F.lit(c).cast("long").alias("code"), n.alias("n")) for c, n in codes])
    return stats.select(F.col("vid").alias("w0"), F.explode(each).alias("x")).select("w0", "x.code", "x.n").where("n > 0")


def counted(stats: DataFrame, vertices: DataFrame, size: int) -> DataFrame:
    """The canonical embeddings of 1 to 3 vertices by first word and quick code: w0, code, n."""
    if size == 1:
        return vertices.select(F.col("vid").alias("w0"), F.lit(0).cast("long").alias("code"), F.lit(1).cast("long").alias("n"))
    if size == 2:
        return stats.where("up > 0").select(F.col("vid").alias("w0"), F.lit(1).cast("long").alias("code"), F.col("up").alias("n"))
    return by_first(stats)


def candidates(stats: DataFrame, size: int) -> int:
    """Extensions beyond the first word of all edges (size 3) or vertices, canonical or not: the vertices next to either end."""
    n = F.col("up") if size == 2 else F.col("up") * (F.col("up") - 1) + F.col("far") - 2 * F.col("low")
    return stats.agg(F.coalesce(F.sum(n), F.lit(0))).first()[0]
