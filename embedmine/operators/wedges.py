"""Rows of pairs of neighbours at a vertex, on graphs that are too large to broadcast: connected triples, pairs of edges
and squares.

A row has one vertex (its centre) where all that decides it is known, so that each is made once and handed on as it is
found. Nothing of the size of the rows is shuffled or stored: what tasks read are the packed lists of ``triples``.
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
from .triples import BLOCK_ENTRIES, GATHERED, blocks_of, crossed, flat, groups, pack, unpack

cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Last words that a task hands on at once; pairs of neighbours of a vertex for one row of :func:`dealt_pairs`.
HANDED, PAIRS = 500_000, 4_000_000
#: Labels whose bits one mask holds.
MASK = 62


class Rows:
    """Columns of numbers and one of lists (``es``, last), held until a batch of them is worth handing on."""

    def __init__(self, *names: str):
        self.names, self.held, self.n = names, [], 0

    def add(self, keep: np.ndarray, last: np.ndarray, *fixed: np.ndarray | int) -> None:
        """For each row of ``keep`` the members of ``last`` that it marks, beside the ``fixed`` values of the row."""
        self.put(np.count_nonzero(keep, axis=1), np.broadcast_to(last, keep.shape)[keep], *fixed)

    def put(self, size: np.ndarray, values: np.ndarray, *fixed: np.ndarray | int) -> None:
        """``size`` of the ``values`` for each row, in turn."""
        some = np.flatnonzero(size)
        if len(some):
            self.held.append(([np.broadcast_to(f, size.shape)[some] for f in fixed], size[some], values))
            self.n += len(values)

    def batches(self, least: int = 0) -> Iterator[pa.RecordBatch]:
        if not self.held or self.n < least:
            return
        fixed, size, values = zip(*self.held)
        ends = np.concatenate([[0], np.cumsum(np.concatenate(size))]).astype(np.int32)
        columns = [pa.array(np.concatenate(c)) for c in zip(*fixed)]
        yield pa.RecordBatch.from_arrays([*columns, pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(values)))], names=[*self.names, "es"])
        self.held, self.n = [], 0


def connected(lists: DataFrame, n_edges: int) -> DataFrame:
    """w0 < w1 < w2 of each connected set of three vertices.

    The growths of a set meet at its centre: a path has one, of a triangle's three the smallest keeps it. The task of
    two blocks has the lists of both ends of each edge between them, and decides the sets at either end whose smaller
    other word is the other end.
    """

    def meet(group: pa.Table) -> Iterator[pa.RecordBatch]:
        vid, length, nbr = flat(group.column("vid"), group.column("nbrs"))
        block, i, j = group.column("block").to_numpy(), group.column("i")[0].as_py(), group.column("j")[0].as_py()
        ids = np.unique(np.concatenate([vid, nbr]))
        to = np.searchsorted(ids, nbr).astype(np.int32)
        start = np.cumsum(length) - length
        row = np.full(len(ids), -1, np.int64)
        row[np.searchsorted(ids, vid)] = np.arange(len(vid))
        place = np.full(len(ids), -1, np.int32)
        out = Rows("x", "o", "mid")
        for v in range(len(vid)):
            mine = to[start[v] : start[v] + length[v]]
            rows = row[mine]
            other = j if block[v] == i else i
            mine_at = np.flatnonzero((rows >= 0) & (block[rows] == other))
            if not len(mine_at):
                continue
            own, d = ids[mine], len(mine)
            low = int(np.searchsorted(own, vid[v]))  # neighbours before it
            place[mine] = np.arange(d)
            for some in pieces(mine_at, length[rows[mine_at]], d):
                keep = np.arange(d) > some[:, None]
                less = int(np.searchsorted(some, low))
                out.add(keep[less:], own, vid[v], own[some[less:]], False)
                if less:
                    keep = keep[:less] & ~linked(to, start, length, place, rows[some[:less]], d)
                    out.add(keep[:, low:], own[low:], own[some[:less]], vid[v], False)
                    out.add(keep[:, :low], own[:low], own[some[:less]], vid[v], True)
                yield from out.batches(HANDED)
            place[mine] = -1
        yield from out.batches()

    def all_met(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in groups(batches):
            yield from meet(group)

    found = crossed(lists, blocks_of(2 * n_edges)).mapInArrow(all_met, "x long, o long, mid boolean, es array<long>").select("x", "o", "mid", F.explode("es").alias("e"))
    return found.select(F.col("x").alias("w0"), F.when(F.col("mid"), F.col("e")).otherwise(F.col("o")).alias("w1"), F.when(F.col("mid"), F.col("o")).otherwise(F.col("e")).alias("w2"))


def pieces(members: np.ndarray, sizes: np.ndarray, width: int) -> Iterator[np.ndarray]:
    """``members`` in turn, as many at once as their lists and a table of their ``width`` leave room for, one at least."""
    ends, done = np.cumsum(sizes), 0
    while done < len(members):
        before = ends[done - 1] if done else 0
        more = max(done + 1, min(int(np.searchsorted(ends, before + GATHERED, "right")), done + 4 * GATHERED // max(width, 1)))
        yield members[done:more]
        done = more


def linked(to: np.ndarray, start: np.ndarray, length: np.ndarray, place: np.ndarray, rows: np.ndarray, width: int) -> np.ndarray:
    """For each of the lists ``rows``, which of the placed ids (``place`` from 0 below ``width``) it has."""
    size = length[rows]
    first = np.cumsum(size) - size
    at = place[to[np.repeat(start[rows] - first, size) + np.arange(int(size.sum()))]]
    hit = np.flatnonzero(at >= 0)
    out = np.zeros((len(rows), width), bool)
    out[np.searchsorted(first, hit, "right") - 1, at[hit]] = True
    return out


def spelled(values: np.ndarray) -> bytes:
    """Numbers by all their lowest bytes, then the next ones, compressed: small numbers take little room."""
    return zlib.compress(np.ascontiguousarray(values, "<i8").view(np.uint8).reshape(-1, 8).T.tobytes(), 1)


def read(data: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(zlib.decompress(data), np.uint8).reshape(8, -1).T).view("<i8").ravel()


def bucket_of(ids: np.ndarray, buckets: int) -> np.ndarray:
    return ((ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)).astype(np.int64) % buckets


def incident(lists: DataFrame, labels: DataFrame) -> DataFrame:
    """vid, d, label, first, nbrs, eids, labels: the d neighbours of a vertex packed, with the ids of its edges, which rise
    with them, and the neighbours' labels; written. An edge's id is its place by (smaller end, larger end); ``eids`` has
    those to smaller neighbours, the others count from ``first``."""
    from ..sources.graph import measured, running_sum

    shuffles = int(lists.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    buckets = 4 * shuffles

    def ups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = [int(np.count_nonzero((a := unpack(x)) > v)) for v, x in zip(batch.column("vid").to_pylist(), batch.column("nbrs").to_pylist())]
            yield pa.RecordBatch.from_arrays([batch.column("vid"), pa.array(n, pa.int64())], names=["vid", "up"])

    def entries(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(to, of, eid, label): what each vertex tells its neighbours; eid -1 to smaller ones, which know it."""
        vid, length, nbr = flat(pa.chunked_array([batch.column("vid")]), pa.chunked_array([batch.column("nbrs")]))
        of = np.repeat(vid, length)
        above = nbr > of
        below = np.repeat(length - np.add.reduceat(above.astype(np.int64), np.cumsum(length) - length), length)
        place = np.arange(len(nbr)) - np.repeat(np.cumsum(length) - length, length) - below
        eid = np.where(above, np.repeat(batch.column("first").to_numpy(), length) + place, -1)
        return nbr, of, eid, np.repeat(batch.column("label").to_numpy(), length)

    def tell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """What many vertices tell the neighbours of a bucket, in one row."""
        held, n = [], 0

        def rows() -> Iterator[pa.RecordBatch]:
            to, of, eid, label = (np.concatenate(c) for c in zip(*held))
            bucket = bucket_of(to, buckets)
            order = np.lexsort((of, to, bucket))
            bucket, to, of, eid, label = (c[order] for c in (bucket, to, of, eid, label))
            some, at = np.unique(bucket, return_index=True)
            for b, first, end in zip(some.tolist(), at, [*at[1:], len(to)]):
                t, o, e = to[first:end], of[first:end], eid[first:end]
                ids, size = np.unique(t, return_counts=True)
                packed = [pa.array([x], pa.binary()) for x in (pack(ids), spelled(size), spelled(np.diff(o, prepend=0)), spelled(np.diff(e[e >= 0], prepend=0)), spelled(label[first:end]))]
                yield pa.RecordBatch.from_arrays([pa.array([b], pa.int32()), *packed], names=["bucket", "ids", "sizes", "nbrs", "eids", "labels"])

        for batch in batches:
            for first in range(0, batch.num_rows, 1000):
                held.append(entries(batch.slice(first, 1000)))
                n += len(held[-1][0])
                if 2 * n >= BLOCK_ENTRIES:
                    yield from rows()
                    held, n = [], 0
        if held:
            yield from rows()

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        told = []
        for batch in batches:
            for ids, sizes, nbrs, eids, labels in zip(*(batch.column(c).to_pylist() for c in ("ids", "sizes", "nbrs", "eids", "labels"))):
                vid, nbr = np.repeat(unpack(ids), read(sizes)), np.cumsum(read(nbrs))
                eid = np.full(len(vid), -1)
                eid[nbr < vid] = np.cumsum(read(eids))
                told.append((vid, nbr, eid, read(labels)))
        if not told:
            return
        vid, nbr, eid, label = (np.concatenate(c) for c in zip(*told))
        order = np.lexsort((nbr, vid))
        vid, nbr, eid, label = vid[order], nbr[order], eid[order], label[order]
        ids, at, d = np.unique(vid, return_index=True, return_counts=True)
        spans = list(zip(at, at + d))
        packed = [[spelled(np.diff(nbr[a:b], prepend=0)) for a, b in spans], [spelled(np.diff(eid[a:b][eid[a:b] >= 0], prepend=0)) for a, b in spans], [spelled(label[a:b]) for a, b in spans]]
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(d), *[pa.array(p, pa.binary()) for p in packed]], names=["vid", "d", "nbrs", "eids", "labels"])

    own = measured(written(running_sum(lists.select("vid", "nbrs").mapInArrow(ups, "vid long, up long"), [], ["vid"], "up", "first", "long").join(labels, "vid").select("vid", "first", "label"), "first"))
    sent = lists.select("vid", "nbrs").join(own, "vid").mapInArrow(tell, "bucket int, ids binary, sizes binary, nbrs binary, eids binary, labels binary")
    got = sent.repartitionById(buckets, F.col("bucket")).mapInArrow(gather, "vid long, d long, nbrs binary, eids binary, labels binary")
    return written(got.join(own, "vid"), "incident")


def unpacked(batch: pa.RecordBatch) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """vid, label, neighbours, ids of the edges to them, their labels, of each row of :func:`incident`."""
    for vid, label, first, nbrs, eids, labels in zip(*(batch.column(c).to_pylist() for c in ("vid", "label", "first", "nbrs", "eids", "labels"))):
        nbr, low = np.cumsum(read(nbrs)), np.cumsum(read(eids))
        yield vid, label, nbr, np.concatenate([low, first + np.arange(len(nbr) - len(low))]), read(labels).astype(np.int32)


def supports(edges: DataFrame, n_labels: int) -> DataFrame:
    """center, a <= b, support: of the patterns of two edges by the labels of their centre and ends, from :func:`incident`.

    The centres of a pattern have neighbours of both labels, and two of them if these are equal. Its ends are
    neighbours of such a centre that has another neighbour of the other label: masks of labels, sent packed, united by end.
    """
    buckets = 4 * int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    names = ["ends", "own", "centers", "parts", "masks"]

    def centres(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seen: dict[tuple[int, int, int], int] = {}
            for _, label, _, _, labels in unpacked(batch):
                kinds, n = np.unique(labels, return_counts=True)
                for p, (a, many) in enumerate(zip(kinds.tolist(), n.tolist())):
                    for b in kinds[p + (many < 2) :].tolist():
                        seen[label, a, b] = seen.get((label, a, b), 0) + 1
            columns = list(zip(*((*k, n) for k, n in seen.items()))) or [()] * 4
            yield pa.RecordBatch.from_arrays([*[pa.array(c, pa.int32()) for c in columns[:3]], pa.array(columns[3], pa.int64())], names=["center", "a", "b", "n"])

    def ends(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            held = []
            for _, label, nbr, _, labels in unpacked(batch):
                kinds, inverse, n = np.unique(labels, return_inverse=True, return_counts=True)
                for part in range(-(-n_labels // MASK)):
                    bits = np.where(kinds // MASK == part, np.int64(1) << (kinds % MASK).astype(np.int64), 0)
                    mask = np.bitwise_or.reduce(bits)
                    each = (mask & ~np.where(n > 1, 0, bits))[inverse]
                    held.append((nbr, labels, np.full(len(nbr), label, np.int32), np.full(len(nbr), part, np.int32), each))
            if not held:
                continue
            nbr, own, label, part, mask = (np.concatenate(c) for c in zip(*held))
            nbr, own, label, part, mask = union(nbr, own, label, part, mask)
            bucket = bucket_of(nbr, buckets)
            order = np.argsort(bucket, kind="stable")
            some, at = np.unique(bucket[order], return_index=True)
            for b, mine in zip(some.tolist(), np.split(order, at[1:])):
                packed = [spelled(np.diff(nbr[mine], prepend=0)), *[spelled(c[mine]) for c in (own, label, part, mask)]]
                yield pa.RecordBatch.from_arrays([pa.array([b], pa.int32()), *[pa.array([x], pa.binary()) for x in packed]], names=["bucket", *names])

    def union(nbr: np.ndarray, own: np.ndarray, label: np.ndarray, part: np.ndarray, mask: np.ndarray) -> tuple[np.ndarray, ...]:
        order = np.lexsort((part, label, nbr))
        nbr, own, label, part, mask = nbr[order], own[order], label[order], part[order], mask[order]
        at = np.flatnonzero(np.concatenate([[True], (np.diff(nbr) != 0) | (np.diff(label) != 0) | (np.diff(part) != 0)]))
        return nbr[at], own[at], label[at], part[at], np.bitwise_or.reduceat(mask, at)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        told = []
        for batch in batches:
            for nbr, *others in zip(*(batch.column(c).to_pylist() for c in names)):
                told.append((np.cumsum(read(nbr)), *map(read, others)))
        if not told:
            return
        _, own, label, part, mask = union(*(np.concatenate(c) for c in zip(*told)))
        for bit in range(MASK):
            hit = np.flatnonzero((mask >> bit) & 1)
            code, n = np.unique((label[hit] * n_labels + own[hit]) * n_labels + part[hit] * MASK + bit, return_counts=True)
            center, a, b = code // n_labels**2, code // n_labels % n_labels, code % n_labels
            columns = [pa.array(c.astype(np.int32)) for c in (center, np.minimum(a, b), np.maximum(a, b))]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(a > b), pa.array(n.astype(np.int64))], names=["center", "a", "b", "turned", "n"])

    at_center = edges.mapInArrow(centres, "center int, a int, b int, n long").groupBy("center", "a", "b").agg(F.sum("n").alias("n"))
    masks = edges.mapInArrow(ends, ", ".join(["bucket int", *[f"{c} binary" for c in names]])).repartitionById(buckets, F.col("bucket"))
    at_end = masks.mapInArrow(count, "center int, a int, b int, turned boolean, n long").groupBy("center", "a", "b", "turned").agg(F.sum("n").alias("n"))
    return at_center.unionByName(at_end.drop("turned")).groupBy("center", "a", "b").agg(F.min("n").alias("support"))


def dealt_pairs(edges: DataFrame) -> DataFrame:
    """The rows of :func:`incident` with turn, turns: as they are stored, evenly, but those of many pairs are sent, once for
    each turn."""
    rows = edges.withColumn("turns", F.greatest(F.ceil(F.col("d") * F.col("d") / (2 * PAIRS)).cast("int"), F.lit(1)))
    many = rows.where("turns > 1").withColumn("turn", F.explode(F.sequence(F.lit(0), F.col("turns") - 1)))
    many = many.repartition(4 * int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions")), "vid", "turn")
    return rows.where("turns = 1").withColumn("turn", F.lit(0)).unionByName(many)


def frequent_pairs(lists: DataFrame, labels: DataFrame, least: int) -> DataFrame:
    """w0 < w1: edges that meet in a vertex, whose pattern (by the vertices' labels) has a support of ``least``.
    labels: vid, label (from 0)."""
    edges = incident(lists, labels)
    n_labels = labels.agg(F.coalesce(F.max("label"), F.lit(0))).first()[0] + 1
    good: dict[int, list[int]] = {}
    for center, a, b in supports(edges, n_labels).where(F.col("support") >= least).select("center", "a", "b").collect():
        good.setdefault(center, []).append(a * n_labels + b)
    good_of = {c: np.sort(np.array(codes, np.int64)) for c, codes in good.items()}

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = Rows("w0")
        for batch in batches:
            for (_, label, _, eid, own), turn, turns in zip(unpacked(batch), batch.column("turn").to_pylist(), batch.column("turns").to_pylist()):
                if label not in good_of:
                    continue
                kinds, inverse = np.unique(own, return_inverse=True)
                code = np.minimum.outer(kinds, kinds).astype(np.int64) * n_labels + np.maximum.outer(kinds, kinds)
                allowed = np.isin(code, good_of[label])
                if not allowed.any():
                    continue
                mine = np.arange(turn, len(eid), turns)
                for first in range(0, len(mine), max(1, HANDED // len(eid))):
                    some = mine[first : first + max(1, HANDED // len(eid))]
                    keep = np.arange(len(eid)) > some[:, None]
                    if not allowed.all():
                        keep &= allowed[inverse[some]][:, inverse]
                    out.add(keep, eid, eid[some])
                    yield from out.batches(HANDED)
        yield from out.batches()

    return dealt_pairs(edges).mapInArrow(pairs, "w0 long, es array<long>").select("w0", F.explode("es").alias("w1"))


def squares(lists: DataFrame, n_edges: int, induced: bool) -> DataFrame:
    """v1 ... v4 of each cycle v1-v2-v3-v4 with v1 smallest and v2 < v4; ``induced``: without chords.

    v1 and v3 meet in the task of their blocks, where the pairs of their common neighbours are handed on. Where chords
    count, v2 is of the task's third block, whose lists tell its links to v4.
    """
    names = "ijk" if induced else "ij"

    def meet(group: pa.Table) -> Iterator[pa.RecordBatch]:
        group = group.sort_by("vid")
        vid, length, nbr = flat(group.column("vid"), group.column("nbrs"))
        block, (i, j, *k) = group.column("block").to_numpy(), (group.column(c)[0].as_py() for c in names)
        ids = np.unique(np.concatenate([vid, nbr]))
        to = np.searchsorted(ids, nbr).astype(np.int32)
        del nbr
        at = np.searchsorted(ids, vid)
        start = np.cumsum(length) - length
        row = np.full(len(ids), -1, np.int32)
        row[at] = np.arange(len(vid))
        opposite = (block == i) | (block == j)
        ends = np.repeat(opposite, length)
        order = np.argsort(to[ends], kind="stable")
        member = np.repeat(np.arange(len(vid), dtype=np.int32), length)[ends][order]  # of each id, the lists that it is in
        n = np.bincount(to[ends], minlength=len(ids))
        begin = np.cumsum(n) - n
        place, mark = np.full(len(ids), -1, np.int32), np.zeros(len(ids), bool)
        out = Rows("v1", "v2", "v3")
        for x in np.flatnonzero(opposite):
            own = to[start[x] : start[x] + length[x]]
            ys = own[own > at[x]]
            if len(ys) < 2:
                continue
            size = n[ys]
            first = np.cumsum(size) - size
            z = member[np.repeat(begin[ys] - first, size) + np.arange(int(size.sum()))]
            y = np.repeat(np.arange(len(ys)), size)
            keep = (z > x) & (block[z] == (j if block[x] == i else i))
            if induced:
                mark[own] = True
                keep &= ~mark[at[z]]
                mark[own] = False
            z, y = z[keep], y[keep]
            turn = np.argsort(z, kind="stable")
            z, y = z[turn], y[turn]
            after = np.searchsorted(z, z, "right") - np.arange(len(z)) - 1  # later common neighbours of x and z
            if induced:
                between = np.flatnonzero((row[ys] >= 0) & (block[row[ys]] == k[0]))
                index = np.full(len(ys), -1, np.int64)
                index[between] = np.arange(len(between))
                after[index[y] < 0] = 0
                place[ys] = np.arange(len(ys))
                parts = [linked(to, start, length, place, row[ys[some]], len(ys)) for some in pieces(between, length[row[ys[between]]], len(ys))]
                place[ys] = -1
                chord = np.concatenate(parts) if parts else np.zeros((0, len(ys)), bool)
            here = np.flatnonzero(after)
            for some in pieces(here, after[here], 1):
                size = after[some]
                first = np.cumsum(size) - size
                last = y[np.repeat(some + 1 - first, size) + np.arange(int(size.sum()))]
                if induced:
                    free = ~chord[np.repeat(index[y[some]], size), last]
                    last, size = last[free], np.add.reduceat(free.astype(np.int64), first)
                out.put(size, ids[ys[last]], vid[x], ids[ys[y[some]]], vid[z[some]])
                yield from out.batches(HANDED)
        yield from out.batches()

    def all_met(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in groups(batches, names):
            yield from meet(group)

    blocks = max(2, -(-4 * n_edges // (3 * BLOCK_ENTRIES)))
    found = crossed(lists, blocks, names).mapInArrow(all_met, "v1 long, v2 long, v3 long, es array<long>")
    return found.select("v1", "v2", "v3", F.explode("es").alias("v4"))
