"""Near-duplicates by SimHash with a Gray-order hierarchical index.

Fingerprints that differ in at most 4 of 64 bits agree on at least one of five
blocks of bits. A block with its bits is a masked pattern that many fingerprints
share: the index's upper nodes. Each distinct fingerprint goes under the five
patterns that it has. Below each pattern, whatever its size, the fingerprints
are sorted by Gray rank, so that neighbours share bits; every FAN of them form a
node that keeps the bits they agree on, every FAN nodes the next, up to the pattern.

The search goes down from a pattern paired with itself. Differences are
accumulated: a pair of nodes inherits those of its parents and adds the ones in
the bits that only now are fixed in both. That is a lower bound for all their
members, and with the bits still free an upper one. Over 4 at least, the pair
of groups is left; 4 at most, all members are linked at once; else the pairs of
children are taken.

A pattern with more fingerprints than one task should hold is split again by
five blocks of its free bits, as often as needed: this is exact, since within 4
differences one of those blocks agrees again. Sizes are counted before rows move.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_value, numbered, spread_join, without, written
from .components import components

by_value(__name__)

#: Words in a shingle, hash seed, differing bits that still link.
SHINGLE, SEED, RADIUS = 4, 42, 4
#: Fingerprints below one pattern that a task takes at once; above, the pattern is split.
CAPACITY = 16384
#: Children of a node of the tree.
FAN = 4
#: Pairs of nodes compared at a time.
PAIRS = 16384


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    """Signed 64-bit SimHash of the lower-cased (A-Z) whole text; 0 without words."""
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    if len(words) < shingle:
        grams = [b" ".join(words)]
    else:
        grams = list(map(b" ".join, zip(*(words[i:] for i in range(shingle)))))
    ones = np.zeros(64, np.int64)
    for i in range(0, len(grams), 65536):
        part = grams[i : i + 65536]
        h = np.fromiter(map(xxhash.xxh64_intdigest, part, [SEED] * len(part)), "<u8", len(part))
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(grams), bitorder="little").view("<i8")[0])


def fingerprints(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", shingle: int = SHINGLE) -> DataFrame:
    """doc_id, tag (XXH64 of the text, null: 0), fp for every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = pa.array([fingerprint(t.as_py(), shingle) for t in batch.column(2)], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), fps], names=["doc_id", "tag", "fp"])

    kind = docs.schema[doc_id].dataType.simpleString()
    tag = F.when(F.col(text).isNull(), F.lit(0)).otherwise(F.xxhash64(text)).alias("tag")
    return docs.select(F.col(doc_id).alias("doc_id"), tag, F.col(text).alias("text")).mapInArrow(run, f"doc_id {kind}, tag long, fp long")


def gray_rank(codes: np.ndarray) -> np.ndarray:
    """Place of each code word in the reflected Gray sequence."""
    rank = codes.copy()
    for shift in (1, 2, 4, 8, 16, 32):
        rank ^= rank >> np.uint64(shift)
    return rank


def merge_labels(labels: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Union by smallest label, in place; a, b are positions that are linked."""
    while len(a):
        x, y = labels[a], labels[b]
        open_ = x != y
        a, b, x, y = a[open_], b[open_], x[open_], y[open_]
        if not len(a):
            return
        np.minimum.at(labels, np.maximum(x, y), np.minimum(x, y))
        while True:
            up = labels[labels]
            if np.array_equal(up, labels):
                break
            labels[:] = up


class Forest:
    """The Gray-order trees of a chunk of fingerprints, one below each pattern.

    ``levels[d]``: (bits, mask) of the nodes at depth d, the fingerprints themselves at 0.
    ``first[d]``: where a node's children begin at depth d - 1; ``span[d]``: where its
    fingerprints begin. Both have a closing entry.
    """

    def __init__(self, node: np.ndarray, fp: np.ndarray):
        order = np.lexsort((gray_rank(fp), node))
        self.codes, root = fp[order], node[order]
        begins = np.flatnonzero(np.r_[True, root[1:] != root[:-1]]) if len(root) else np.zeros(0, np.int64)
        low = high = self.codes
        self.levels = [(low, ~np.zeros_like(low))]
        self.first, self.span = [np.arange(len(low) + 1)], [np.arange(len(low) + 1)]
        while len(low) > len(begins):
            sizes = np.diff(np.r_[begins, len(low)])
            first = np.flatnonzero((np.arange(len(low)) - np.repeat(begins, sizes)) % FAN == 0)
            low, high = np.bitwise_and.reduceat(low, first), np.bitwise_or.reduceat(high, first)
            begins = np.searchsorted(first, begins)
            self.levels.append((low, ~(low ^ high)))
            self.first.append(np.r_[first, self.first[-1].size - 1])
            self.span.append(self.span[-1][self.first[-1]])

    def members(self, depth: int, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(places of the fingerprints below the nodes, place of their node's first one)."""
        begin, end = self.span[depth][nodes], self.span[depth][nodes + 1]
        size = end - begin
        return np.arange(size.sum()) + np.repeat(begin - np.cumsum(size) + size, size), np.repeat(begin, size)

    def children(self, depth: int, x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(pair, child of x, child of y): each unordered pair of children once, a fingerprint not with itself."""
        of, fan = self.first[depth], np.arange(FAN)
        p, q = np.broadcast_arrays(of[x][:, None, None] + fan[:, None], of[y][:, None, None] + fan)
        real = (p < of[x + 1][:, None, None]) & (q < of[y + 1][:, None, None]) & ((p < q) | ((p == q) & (depth > 1)) | (x != y)[:, None, None])
        return np.broadcast_to(np.arange(len(x))[:, None, None], p.shape)[real], p[real], q[real]


def forest_links(node: np.ndarray, fp: np.ndarray, radius: int = RADIUS) -> tuple[np.ndarray, np.ndarray]:
    """(code, code of its class) for the codes that have links among those under their pattern ``node``."""
    tree = Forest(node, fp)
    labels = np.arange(len(tree.codes))

    def descend(depth: int, a: np.ndarray, b: np.ndarray, differ: np.ndarray, known: np.ndarray) -> None:
        """Pairs (a, b) of nodes with the differences found above them and the bits these are in."""
        bits, mask = tree.levels[depth]
        for i in range(0, len(a), PAIRS):
            part = slice(i, i + PAIRS)
            x, y, low, seen = a[part], b[part], differ[part], known[part]
            if depth:  # members that are in one class already need no search
                least, most = np.minimum.reduceat(labels, tree.span[depth][:-1]), np.maximum.reduceat(labels, tree.span[depth][:-1])
                open_ = (least[x] != most[x]) | (least[y] != most[y]) | (least[x] != least[y])
                x, y, low, seen = x[open_], y[open_], low[open_], seen[open_]
            fixed = mask[x] & mask[y]
            low = low + np.bitwise_count((bits[x] ^ bits[y]) & fixed & ~seen)
            near = low <= radius
            sure = near & (low + np.bitwise_count(~fixed) <= radius)
            if not depth:
                merge_labels(labels, x[sure], y[sure])
                continue
            if sure.any():
                heads = tree.span[depth][x[sure]]
                for places, head in (tree.members(depth, x[sure]), tree.members(depth, y[sure])):
                    merge_labels(labels, places, head)
                merge_labels(labels, heads, tree.span[depth][y[sure]])
            on = near & ~sure
            pair, p, q = tree.children(depth, x[on], y[on])
            descend(depth - 1, p, q, low[on][pair], fixed[on][pair])

    top = len(tree.levels) - 1
    if top:
        roots = np.flatnonzero(np.diff(tree.span[top]) > 1)
        descend(top, roots, roots, np.zeros(len(roots), np.uint8), np.zeros(len(roots), np.uint64))
    out = np.flatnonzero(labels != np.arange(len(labels)))
    return tree.codes[out], tree.codes[labels[out]]


def free_blocks(used: int, parts: int = RADIUS + 1) -> list[int]:
    """Masks that divide the bits outside ``used`` into ``parts`` near-equal blocks, high bits first."""
    free = [i for i in range(63, -1, -1) if not used >> i & 1]
    return [sum(1 << i for i in free[len(free) * k // parts : len(free) * (k + 1) // parts]) for k in range(parts)]


def signed(mask: int) -> int:
    return mask - (1 << 64) if mask >> 63 else mask


def search_patterns(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (node, fp) sorted by node to links (a, b); a chunk holds whole patterns."""
    kept: list[np.ndarray] = [np.zeros((2, 0), np.int64)]

    def search(rows: np.ndarray) -> Iterator[pa.RecordBatch]:
        a, b = forest_links(rows[0], np.ascontiguousarray(rows[1]).view(np.uint64))
        if len(a):
            yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

    for batch in batches:
        if not batch.num_rows:
            continue
        kept.append(np.stack([c.to_numpy(zero_copy_only=False) for c in batch.columns]))
        if sum(k.shape[1] for k in kept) < 4 * CAPACITY:
            continue
        rows = np.concatenate(kept, axis=1)
        cut = int(np.argmax(rows[0] == rows[0, -1]))  # the last pattern may go on in the next batch
        yield from search(rows[:, :cut])
        kept = [rows[:, cut:]]
    yield from search(np.concatenate(kept, axis=1))


def split_patterns(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (node, used, fp) to five rows each, under the patterns that have a block of their free bits more."""
    for batch in batches:
        node, used, fp = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
        for u in np.unique(used):
            rows = used == u
            codes, above = fp[rows], node[rows].view(np.uint64)
            for t, mask in enumerate(free_blocks(int(u) & (2**64 - 1))):
                part = (codes.view(np.uint64) & np.uint64(mask)) * np.uint64(0x9E3779B97F4A7C15)
                part ^= part >> np.uint64(29)
                below = (above ^ part) * np.uint64(0xBF58476D1CE4E5B9) + np.uint64(t + 1)
                more = np.full(len(codes), signed((int(u) & (2**64 - 1)) | mask), np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(below.view(np.int64)), pa.array(more), pa.array(codes)], names=["node", "used", "fp"])


def near_links(distinct: DataFrame) -> DataFrame:
    """Links (a, b) that span the classes of the distinct fingerprints in column fp."""
    blocks = [F.struct(F.lit(t).cast("long").alias("t"), F.lit(signed(m)).cast("long").alias("used"), F.col("fp").bitwiseAND(F.lit(signed(m))).alias("part")) for t, m in enumerate(free_blocks(0))]
    todo = distinct.select("fp", F.explode(F.array(*blocks)).alias("n")).select(F.xxhash64("n.t", "n.part").alias("node"), "n.used", "fp")
    found = None
    while True:
        full = todo.groupBy("node").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > CAPACITY)
        full = written(full.select("node"), "full-patterns")
        done = full.isEmpty()
        light = todo if done else spread_join(todo, full, ["node"], ["fp"], "left_anti")
        links = written(light.select("node", "fp").repartition("node").sortWithinPartitions("node").mapInArrow(search_patterns, "a long, b long"), "near-links")
        found = links if found is None else found.unionByName(links)
        if done:
            return found
        heavy = spread_join(todo, full, ["node"], ["fp"], "left_semi").select("node", "used", "fp")
        todo = written(heavy.mapInArrow(split_patterns, "node long, used long, fp long"), "split-patterns")


def near_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", shingle: int = SHINGLE) -> DataFrame:
    """One row per row of ``docs``: doc_id, fingerprint (hex), component_id, component_tag, tag.

    component_id is the smallest doc_id (null only if all are) among the
    documents reachable by links; component_tag names that document's text.
    Null and empty texts have fingerprint zero and are linked like any other.
    """
    rows = written(fingerprints(docs, text, doc_id, shingle).withColumn("run", F.spark_partition_id()), "fingerprints")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("z"), F.col("doc_id").alias("i"), F.col("tag").alias("g"))).alias("best")
    distinct = written(rows.groupBy("fp").agg(first), "distinct-fingerprints")
    roots = components(near_links(distinct))
    grouped = written(distinct.join(roots.withColumnRenamed("node", "fp"), "fp"), "class-members")
    least = grouped.groupBy("root").agg(F.min("best").alias("class_best"))
    classes = spread_join(grouped.select("fp", "root"), least, ["root"], ["fp"]).select("fp", "class_best")
    verdict = distinct.join(classes, "fp", "left").select("fp", F.coalesce("class_best", "best").alias("best"))
    # A fingerprint of very many rows has one entry for each run, so that no task gathers its rows.
    entries = rows.select("run", "fp").distinct().join(verdict, "fp")
    return rows.join(entries, ["run", "fp"]).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.col("best.i").alias("component_id"), F.col("best.g").alias("component_tag"), "tag")


def drop_near_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``docs`` with one document of each class, the one of smallest doc_id; columns unchanged,
    whatever their names. Rows that repeat doc_id and text are one document: one of them stays."""
    rows, of = numbered(docs)
    marks = near_duplicates(rows, of[text], of[doc_id])
    stays = F.col("doc_id").eqNullSafe(F.col("component_id")) & (F.col("tag") == F.col("component_tag"))
    marks = marks.groupBy("doc_id", "tag").agg(F.max(stays).alias("stays"), F.count(F.lit(1)).alias("times"))
    tag = F.when(F.col(of[text]).isNull(), F.lit(0)).otherwise(F.xxhash64(of[text]))
    return without(rows, marks, F.col(of[doc_id]), tag).select(*[F.col(n).alias(c) for c, n in of.items()])
