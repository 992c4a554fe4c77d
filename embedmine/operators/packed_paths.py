"""The path store of the embeddings of three vertices on graphs that are too large to broadcast, from packed
neighbour lists: no embedding is made.

With common neighbours counted, an entry needs no embedding to be known. Level 0 (v, y), an edge with v < y: some larger
neighbour of v or of y goes on from it. Level 1 (v, z): v and z share a neighbour below both, or z is a neighbour of v
and some neighbour of v below both lacks an edge to z. Blocks of vertices meet two by two, and each pair of vertices is
decided in one task alone, so that entries are distinct as they are made.
"""

from __future__ import annotations

import sys
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import written
from . import triples

cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Edges of a pattern of three vertices: its name in the rows of this module (0: a store without patterns).
OPEN, CLOSED = 2, 3
#: Rows of a batch that leaves a task.
BATCH = 200_000
Masks = dict[int, np.ndarray]
Step = tuple[int, np.ndarray, Masks, np.ndarray, Masks, np.ndarray]


def decided(group: pa.Table, halves: int) -> Iterator[Step]:
    """(v, ys, first, zs, second, back) for each vertex v of the task and each block of it that v meets: ids of the
    block, and by number of edges which y of them are in entries (v, y) of level 0 and which z in entries (v, z) of level 1
    (all beyond v); the ys back of entries (y, v) of level 1, which are of open triples.

    ``halves``: embeddings are told apart by first word modulo this number, and the entries of the parts merged.
    """
    vid, length, nbr = triples.flat(group.column("vid"), group.column("nbrs"))
    block, i, j = group.column("block").to_numpy(), group.column("i")[0].as_py(), group.column("j")[0].as_py()
    by_id = np.argsort(vid, kind="stable")
    start = np.cumsum(length) - length
    # All lists again, by rising vertex.
    took = length[by_id]
    first = np.cumsum(took) - took
    nbr = nbr[np.repeat(start[by_id] - first, took) + np.arange(len(nbr))]
    vid, length, block, start = vid[by_id], took, block[by_id], first
    ids = np.unique(np.concatenate([vid, nbr]))
    n = len(ids)
    at, to = np.searchsorted(ids, vid), np.searchsorted(ids, nbr)
    del nbr
    owner = np.repeat(np.arange(len(vid)), length)
    listed = at[owner] * n + to
    order = np.argsort(to, kind="stable")  # by neighbour, then by vertex
    of, x = owner[order], to[order]
    part = [np.concatenate([[0], np.cumsum(ids[to] % halves == h)]) for h in range(halves)]
    del owner
    for a, b in [(i, i)] if i == j else [(i, j), (j, i)]:
        mine_of = block[of] == b
        columns = np.flatnonzero(block == b)
        zs = vid[columns]
        column = np.full(n, -1, np.int64)
        column[at[columns]] = np.arange(len(columns))
        # The vertices of block b next to each vertex x, as one array; past: how many of them come before or at an entry.
        near, past = column[at[of[mine_of]]], np.empty(len(to), np.int64)
        past[order] = np.cumsum(mine_of)
        bounds = np.searchsorted(x[mine_of], np.arange(n + 1))
        self_at = np.searchsorted(x[mine_of] * n + at[of[mine_of]], np.arange(n) * (n + 1))

        def counts(begin: np.ndarray, end: np.ndarray) -> np.ndarray:
            """How often each vertex of block b lies in the ranges of ``near``."""
            size = end - begin
            keep = size > 0
            begin, size = begin[keep], size[keep]
            out, ends, done = np.zeros(len(columns), np.int64), np.cumsum(size), 0
            while done < len(size):
                before = ends[done - 1] if done else 0
                more = max(done + 1, int(np.searchsorted(ends, before + triples.GATHERED, "right")))
                some = size[done:more]
                lead = np.cumsum(some) - some
                out += np.bincount(near[np.repeat(begin[done:more] - lead, some) + np.arange(int(some.sum()))], minlength=len(columns))
                done = more
            return out

        for v in np.flatnonzero(block == a):
            p, here = at[v], slice(start[v], start[v] + length[v])
            mine, passed = to[here], past[here]
            below = int(np.searchsorted(mine, p))
            above = mine[below:]
            c = column[above]
            after = len(above) - 1 - np.flatnonzero(c >= 0)  # larger neighbours of v beyond each
            c = c[c >= 0]
            rows = columns[c]
            # Entries of the lists of those neighbours up to v itself.
            to_v = np.searchsorted(listed, at[rows] * n + p)
            # Level 0. Neighbours of both that are larger than both.
            high = counts(passed[below:], self_at[above])[c]
            goes_on = after > high
            beyond = start[rows] + length[rows] - to_v - 1  # neighbours of y beyond v
            goes_on |= beyond > len(above) - 1
            for e in np.flatnonzero(~goes_on & (beyond > 0)):
                theirs = to[to_v[e] + 1 : start[rows[e]] + length[rows[e]]]
                goes_on[e] = not np.isin(theirs, above, assume_unique=True).all()
            # Level 1.
            opened, closed, back = np.zeros(len(columns), bool), np.zeros(len(columns), bool), np.zeros(len(c), bool)
            adjacent = np.zeros(len(columns), bool)
            adjacent[c] = True
            for h in range(halves):
                lower = slice(0, below) if halves == 1 else np.flatnonzero(ids[mine[:below]] % halves == h)
                low = counts(passed[lower], bounds[mine[lower] + 1])
                hit = low > 0
                opened |= hit & ~adjacent
                closed |= hit & adjacent
                opened[c] |= len(mine[lower]) > low[c]
                back |= part[h][to_v] - part[h][start[rows]] > low[c]
            ys = vid[rows]
            yield int(vid[v]), ys, {OPEN: goes_on, CLOSED: high > 0}, zs, {OPEN: opened, CLOSED: closed}, ys[back]


def kinds(masks: Masks, per_pattern: bool) -> list[tuple[int, np.ndarray]]:
    return list(masks.items()) if per_pattern else [(0, masks[OPEN] | masks[CLOSED])]


def entries(lists: DataFrame, n_edges: int, per_pattern: bool = True, halves: int = 1) -> DataFrame:
    """n_edges (of the pattern; 0 in a store without patterns), level, node, next: the distinct entries, as the tasks find them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        n = 0

        def batch() -> pa.RecordBatch:
            size = [max(len(x[2]), len(x[3])) for x in held]
            full = [np.concatenate(y) for y in zip(*[[z if isinstance(z, np.ndarray) else np.full(s, z) for z in x] for x, s in zip(held, size)])]
            return pa.RecordBatch.from_arrays([pa.array(full[0].astype(np.int32)), pa.array(full[1].astype(np.int32)), pa.array(full[2]), pa.array(full[3])], names=["n_edges", "level", "node", "next"])

        table = list(batches)
        if not any(b.num_rows for b in table):
            return
        for v, ys, first, zs, second, back in decided(pa.Table.from_batches(table), halves):
            for level, ids, masks in ((0, ys, first), (1, zs, second)):
                for kind, mask in kinds(masks, per_pattern):
                    found = ids[mask]
                    held.append((kind, level, np.full(len(found), v), found))
                    n += len(found)
            held.append((OPEN if per_pattern else 0, 1, back, np.full(len(back), v)))
            n += len(back)
            if n >= BATCH:
                yield batch()
                held, n = [], 0
        if n:
            yield batch()

    return triples.met(lists, n_edges).mapInArrow(run, "n_edges int, level int, node long, next long")


def costs(lists: DataFrame, n_edges: int, per_pattern: bool = True) -> DataFrame:
    """n_edges, level (0 or 1), node, cost: what :func:`balance.path_costs` gives for the entries, of which only those
    of level 0 are kept, packed by node, and those of level 1 counted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = list(batches)
        if not any(b.num_rows for b in table):
            return
        rows, nexts, backs = [], Counter(), []
        for v, ys, first, _, second, back in decided(pa.Table.from_batches(table), 1):
            for kind, mask in kinds(first, per_pattern):
                if mask.any():
                    rows.append((kind, v, None, triples.pack(ys[mask])))
            for kind, mask in kinds(second, per_pattern):
                nexts[kind, v] += int(np.count_nonzero(mask))
            backs.append(back)
        for z, m in zip(*np.unique(np.concatenate(backs), return_counts=True)):
            nexts[OPEN if per_pattern else 0, int(z)] += int(m)
        rows += [(kind, v, m, None) for (kind, v), m in nexts.items() if m]
        for at in range(0, len(rows), 10_000):
            some = list(zip(*rows[at : at + 10_000]))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(some, (pa.int32(), pa.int64(), pa.int64(), pa.binary()))], names=["n_edges", "node", "cost", "nbrs"])

    found = written(triples.met(lists, n_edges).mapInArrow(run, "n_edges int, node long, cost long, nbrs binary"), "path-lists")
    second = written(found.where("cost is not null").groupBy("n_edges", "node").agg(F.sum("cost").alias("cost")), "path-costs")
    out = second.select("n_edges", F.lit(1).alias("level"), "node", "cost")
    for kind in (OPEN, CLOSED) if per_pattern else (0,):
        # A list of level 0 holds larger ids alone.
        pairs = triples.pairs_of(found.where((F.col("n_edges") == kind) & F.col("nbrs").isNotNull()).select(F.col("node").alias("vid"), "nbrs"))
        below = second.where(F.col("n_edges") == kind).select(F.col("node").alias("b"), "cost")
        first = pairs.join(below, "b").groupBy("a").agg(F.sum("cost").alias("cost"))
        out = out.unionByName(first.select(F.lit(kind).alias("n_edges"), F.lit(0).alias("level"), F.col("a").alias("node"), "cost"))
    return out


def stored_edges(lists: DataFrame) -> DataFrame:
    """node, n, nexts: the path store of the embeddings of two vertices, which has one pattern and one level, with the words
    after a node as one packed list; of the packed neighbours ``lists`` of the first words; written."""
    ups = triples.larger(lists).withColumnsRenamed({"vid": "node", "nbrs": "nexts"})

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = [len(triples.unpack(x)) for x in batch.column("nexts").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("node"), pa.array(n, pa.int64()), batch.column("nexts")], names=["node", "n", "nexts"])

    return written(ups.mapInArrow(count, "node long, n long, nexts binary"), "paths-2")


def decoded_edges(store: DataFrame, lists: DataFrame) -> DataFrame:
    """vid, up: by first word, the embeddings of two vertices that the paths of ``store`` give; a path is one if
    its words rise and are neighbours. Written."""
    met = store.select("node", "nexts").join(lists.select(F.col("vid").alias("node"), "nbrs"), "node")

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            up = []
            for node, nexts, nbrs in zip(*(batch.column(c).to_pylist() for c in ("node", "nexts", "nbrs"))):
                real = np.intersect1d(triples.unpack(nexts), triples.unpack(nbrs), assume_unique=True)
                up.append(int(np.count_nonzero(real > node)))
            yield pa.RecordBatch.from_arrays([batch.column("node"), pa.array(up, pa.int64())], names=["vid", "up"])

    return written(met.mapInArrow(check, "vid long, up long").where("up > 0"), "decoded-2")
