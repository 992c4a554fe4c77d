"""Canonicality of embeddings as column expressions.

An embedding is a row of word columns w0, w1, ... in visiting order. Its
representative among all orders of the same words starts at the smallest word
and goes on with the smallest unvisited word that touches a visited one. A
parent in that order, extended by ``ext``, stays in it iff ``ext`` exceeds the
first word and every word that comes after the first one ``ext`` touches.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


#: Below all vertex and edge ids.
LEAST = -(1 << 63)


def words(k: int) -> list[str]:
    return [f"w{i}" for i in range(k)]


def every(conditions: list[Column]) -> Column:
    return reduce(lambda a, b: a & b, conditions, F.lit(True))


def some(conditions: list[Column]) -> Column:
    return reduce(lambda a, b: a | b, conditions, F.lit(False))


def later_words(k: int, at: int) -> Column:
    """The largest word after position ``at``; the least long (ids exceed it) if there is none."""
    rest = [F.col(w) for w in words(k)[at + 1 :]]
    return F.lit(LEAST).cast("long") if not rest else rest[0] if len(rest) == 1 else F.greatest(*rest)


def is_canonical(k: int, touches: list[Column], ext: Column) -> Column:
    """Of a canonical parent with k words and one extension; ``touches[i]``: it touches word i."""
    conditions = [ext > F.col("w0")]
    for j in range(1, k):
        conditions.append(~some(touches[:j]) | (ext > F.col(f"w{j}")))
    return every(conditions)


def bit(mask: Column, i: int) -> Column:
    return F.shiftrightunsigned(mask, i).bitwiseAND(F.lit(1)) == 1


def touch_offset(k: int) -> int:
    """Where in the code the touch mask of the word after k words begins."""
    return k * (k - 1) // 2


def extended_code(code: Column, touch: Column, k: int) -> Column:
    """The quick code of the child: the parent's with the new word's mask above it (11 words fit a long)."""
    if k > 10:
        raise ValueError("quick codes of vertex mode hold 11 words")
    return code.bitwiseOR(F.shiftleft(touch, touch_offset(k)))


def canonical_order(ids: set[int], neighbours: dict[int, set[int]]) -> tuple[int, ...]:
    """The representative order from scratch; for tests."""
    seen = [min(ids)]
    while len(seen) < len(ids):
        border = {v for u in seen for v in neighbours[u] if v in ids} - set(seen)
        if not border:
            raise ValueError("not connected")
        seen.append(min(border))
    return tuple(seen)
