"""Sharding by best-fit-decreasing bin packing of indivisible groups.

Equal texts form a group that stays together. Groups are taken by falling size;
each enters the bin with the least remaining capacity that still holds it, found
in a balanced tree. The capacity is the smallest, by bisection, for which the
wanted number of shards suffices, so the shards are filled alike. A unit above the
share has a shard of its own, and the capacity is that of the shards left.

Groups of equal size are interchangeable, so the packing runs on the histogram
of sizes: of ``n`` groups of one size the tightest bin takes as many as it can
at once. Distinct sizes number at most the square root of twice all bytes. Only a
group heavier than a shard's share, which no shard could hold, is divided: into parts
of as many rows as the share holds and one part of the rows that are left.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_value, ranked, spread_join, text_or_empty, written

by_value(__name__)

SHARDS = 40
OVERHEAD = 16


class Node:
    __slots__ = ("key", "left", "level", "right")

    def __init__(self, key):
        self.key, self.level, self.left, self.right = key, 1, None, None


def _skew(t):
    if t.left is not None and t.left.level == t.level:
        t.left.right, t.left, t = t, t.left.right, t.left
    return t


def _split(t):
    if t.right is not None and t.right.right is not None and t.right.right.level == t.level:
        r = t.right
        t.right, r.left = r.left, t
        r.level += 1
        return r
    return t


def insert(t: Node | None, key) -> Node:
    """Balanced (level-coded) insertion of a key that the tree lacks."""
    if t is None:
        return Node(key)
    if key < t.key:
        t.left = insert(t.left, key)
    else:
        t.right = insert(t.right, key)
    return _split(_skew(t))


def remove(t: Node | None, key) -> Node | None:
    if t is None:
        return None
    if key < t.key:
        t.left = remove(t.left, key)
    elif key > t.key:
        t.right = remove(t.right, key)
    elif t.left is None and t.right is None:
        return None
    elif t.left is None:
        near = t.right
        while near.left is not None:
            near = near.left
        t.key, t.right = near.key, remove(t.right, near.key)
    else:
        near = t.left
        while near.right is not None:
            near = near.right
        t.key, t.left = near.key, remove(t.left, near.key)
    below = min(t.left.level if t.left else 0, t.right.level if t.right else 0) + 1
    if below < t.level:
        t.level = below
        if t.right is not None:
            t.right.level = min(t.right.level, below)
    t = _skew(t)
    if t.right is not None:
        t.right = _skew(t.right)
        if t.right.right is not None:
            t.right.right = _skew(t.right.right)
    t = _split(t)
    if t.right is not None:
        t.right = _split(t.right)
    return t


def tightest(t: Node | None, size: int):
    """The smallest (room, bin) with room for ``size``, or None."""
    best = None
    while t is not None:
        if t.key[0] >= size:
            best, t = t.key, t.left
        else:
            t = t.right
    return best


def best_fit(sizes: list[tuple[int, int]], capacity: int, bins: int | None = None) -> list[tuple[int, int, int]] | None:
    """(size, count) by falling size to (size, bin, how many), in order; None if ``bins`` do not suffice.

    Without ``bins`` new ones are opened as needed (the fewest-bins form).
    """
    tree, opened, out = None, 0, []
    for size, count in sizes:
        if size > capacity:
            return None
        while count:
            at = tightest(tree, size)
            if at is None:
                if bins is not None and opened == bins:
                    return None
                at, opened = (capacity, opened), opened + 1
            else:
                tree = remove(tree, at)
            take = min(count, at[0] // size) if size else count
            out.append((size, at[1], take))
            count -= take
            tree = insert(tree, (at[0] - take * size, at[1]))
    return out


def smallest_fit(sizes: list[tuple[int, int]], bins: int) -> list[tuple[int, int, int]]:
    """Best fit at the smallest capacity for which ``bins`` suffice."""
    total = sum(s * n for s, n in sizes)
    low = max(-(-total // bins), max((s for s, n in sizes if n), default=0))
    high = low
    best = best_fit(sizes, high, bins)
    while best is None:
        low, high = high, high + max(1, (high - total // bins), total // bins // 10000)
        best = best_fit(sizes, high, bins)
    while high - low > max(1, total // bins // 100_000):
        middle = (low + high) // 2
        found = best_fit(sizes, middle, bins)
        low, high, best = (low, middle, found) if found is not None else (middle, high, best)
    return best


def level_fit(sizes: list[tuple[int, int]], bins: int) -> list[tuple[int, int, int]]:
    """(size, count) by falling size to (size, bin, how many), the bins as level as units allow.

    A unit above the share of the bins that are left has a bin of its own; the
    others meet their own smallest capacity. Where that would leave a bin empty
    (few units, of one size, say), its fullest bin is kept and the rest levelled again.
    """
    left, out, first = {s: n for s, n in sizes if n}, [], 0
    while left:
        total, largest = sum(s * n for s, n in left.items()), max(left)
        if largest * (bins - first) > total:
            kept = [(largest, first, 1)]
        else:
            found = smallest_fit(sorted(left.items(), reverse=True), bins - first)
            loads: dict[int, int] = {}
            for size, b, n in found:
                loads[b] = loads.get(b, 0) + size * n
            if len(loads) == bins - first:
                return out + [(size, first + b, n) for size, b, n in found]
            fullest = max(loads, key=loads.get)
            kept = [(size, first, n) for size, b, n in found if b == fullest]
        for size, _, n in kept:
            left[size] -= n
            if not left[size]:
                del left[size]
        out, first = out + kept, first + 1
    return out


def shard(docs: DataFrame, shards: int = SHARDS, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """One row per row of ``docs``: doc_id, size, text_crc32, law ("bytes"), shard, slot, grown_shard (null).

    Size: UTF-8 bytes and 16 more. Null texts are a group of their own, with
    the checksum of the empty text. Slots are gapless from 0 in each shard.
    """
    salts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    body = text_or_empty(text)
    rows = docs.select(
        F.monotonically_increasing_id().alias("row"),
        F.col(doc_id).alias("doc_id"),
        (F.octet_length(body) + OVERHEAD).cast("long").alias("size"),
        F.crc32(body.cast("binary")).alias("text_crc32"),
        F.when(F.col(text).isNull(), F.unhex(F.lit("00"))).otherwise(F.unhex(F.sha2(body, 256))).alias("group"),
    )
    rows = written(rows, "sizes")
    total = rows.agg(F.sum("size")).first()[0] or 0
    share = max(1, -(-total // shards))
    # Groups of more than a 16th of the share, 16 a shard at most, are broadcast, so that no task gathers their rows.
    heavy = rows.groupBy("group").agg(F.sum("size").alias("bytes")).where(F.col("bytes") * 16 > share)
    heavy = written(heavy.select("group", (F.col("bytes") > share).alias("divided")), "heavy")
    rows = rows.join(F.broadcast(heavy), "group", "left")
    divided = ranked(rows.where("divided"), ["group"], ["row"], "rank", salts)  # rows of a group are of one size
    divided = divided.withColumn("part", F.floor(F.col("rank") / F.greatest(F.lit(1), F.floor(F.lit(share) / F.col("size"))))).drop("rank")
    rows = rows.where("divided is null or not divided").withColumn("part", F.lit(0).cast("long")).unionByName(divided)
    rows = rows.withColumn("heavy", F.col("divided").isNotNull()).drop("divided")
    units = written(rows.groupBy("group", "part", "heavy").agg(F.sum("size").alias("bytes")), "units")

    def fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = [x for b in batches for x in zip(b.column(0).to_pylist(), b.column(1).to_pylist())]
        at, out = {}, []
        for size, bin_, n in level_fit(sorted(found, reverse=True), shards):
            out.append((size, at.get(size, 0), at.get(size, 0) + n, bin_))
            at[size] = at.get(size, 0) + n
        for i in range(0, len(out), 50_000):
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out[i : i + 50_000])], names=["bytes", "low", "high", "shard"])

    sizes = units.groupBy("bytes").agg(F.count(F.lit(1)).alias("n"))
    plan = sizes.coalesce(1).mapInArrow(fit, "bytes long, low long, high long, shard long")
    plan = written(plan, "plan").groupBy("bytes").agg(F.collect_list(F.struct("low", "high", "shard")).alias("plan"))  # a size is in each shard once at most
    placed = spread_join(ranked(units, ["bytes"], ["group", "part"], "rank", salts), plan, ["bytes"], ["group", "part"])  # many groups may have one size
    placed = placed.select("group", "part", "heavy", F.filter("plan", lambda x: (F.col("rank") >= x["low"]) & (F.col("rank") < x["high"]))[0]["shard"].cast("int").alias("shard"))
    placed = written(placed, "placed-units")
    light = rows.where("not heavy").drop("heavy", "part").join(placed.where("not heavy").select("group", "shard"), "group").drop("group")
    rows = rows.where("heavy").drop("heavy").join(F.broadcast(placed.where("heavy").drop("heavy")), ["group", "part"]).drop("group", "part")
    rows = written(light.unionByName(rows), "placed")
    return ranked(rows, ["shard"], ["row"], "slot", salts).select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
