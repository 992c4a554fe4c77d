"""Mixing sources to target weights by iterative proportional fitting (DataFrame functions only).

Token weights of the cells (source, language, topic) are raked to the targets
of one dimension after the other until all three hold. A cell's fitted weight
over its tokens gives its documents' relative chance; the chances are scaled,
with 1 as the ceiling, so that the expected tokens meet the budget.

Few cells are raked by one task in a few plans. Beyond that, each step aggregates
its margins and joins them back, so that no task sees all cells.
"""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import text_or_empty, written

DIMENSIONS = ("source", "lang", "topic")
#: Target shares, where none are given: actual shares to this power.
TEMPER = 0.7
ROUNDS, ROUNDS_A_PLAN = 24, 6
#: Share of the tokens that the sample should hold.
RATE = 0.5
#: Cells up to which one task rakes them and a join may broadcast them (about 100 bytes each); beyond, margins are joined.
SMALL = 100_000
#: Rounds in which the set of values at probability 1 must settle (each adds one at least; a handful is usual).
SETTLE = 200
SEED = "mix"
NONE = "(none)"


def topic_of(text: Column) -> Column:
    """A plain rule for the form of a text: table, markup, licence, contact or prose."""
    return (
        F.when(text.contains(" | "), "table")
        .when(text.rlike(r"[%&*#$]{3}"), "markup")
        .when(text.contains("Licensed under"), "licence")
        .when(text.contains("@"), "contact")
        .otherwise("prose")
    )


def tokens_of(text: Column) -> Column:
    """One token for each four bytes of UTF-8, at least one."""
    return F.greatest(F.lit(1).cast("long"), F.ceil(F.octet_length(text) / 4))


def draw(doc_id: Column, text: Column, seed: str = SEED) -> Column:
    """A document's fixed uniform number, from its id (from its text without one)."""
    key = F.concat(F.lit(f"{seed}:"), F.coalesce(doc_id.cast("string"), F.md5(text.cast("binary"))))
    return F.conv(F.substring(F.md5(key.cast("binary")), 1, 13), 16, 10).cast("double") / float(1 << 52)


def ceiled(cells: DataFrame, rate: float) -> DataFrame:
    """Adds prob: in proportion to weight over tokens, 1 at most, so that the expected tokens are ``rate`` of all.

    What exceeds 1 is set to 1 and its surplus goes to the others, until nothing
    more exceeds it; a round is one aggregate of the cells.
    """
    ratio = F.col("weight") / F.col("tokens")
    bar = float("inf")
    for _ in range(SETTLE):
        full = ratio >= bar
        row = cells.agg(F.sum("tokens"), F.sum(F.when(full, F.col("tokens")).otherwise(0)), F.sum(F.when(full, 0.0).otherwise(F.col("weight")))).first()
        left = rate * (row[0] or 0) - (row[1] or 0)
        lower = row[2] / left if row[2] and left > 0 else bar
        if lower >= bar:
            break
        bar = lower
    return cells.withColumn("prob", F.when(ratio >= bar, 1.0).otherwise(F.least(F.lit(1.0), ratio / bar)) if 0 < bar < float("inf") else F.lit(0.0))


def shortfalls(fitted: DataFrame) -> DataFrame:
    """dimension, value, target and expected share of the chosen tokens, and gap, the part by which the raked
    weight misses what the raking aimed at (0 where it has converged); from the result of :func:`fitted_cells`."""
    out = None
    for d in DIMENSIONS:
        rows = fitted.groupBy(F.col(d).alias("value")).agg(F.first(f"want_{d}").alias("want"), F.first(f"give_{d}").alias("give"), F.sum("weight").alias("raked"), F.sum(F.col("prob") * F.col("tokens")).alias("have"))
        rows = written(rows, "margins")
        all_ = rows.agg(F.sum("want").alias("all_want"), F.sum("have").alias("all_have"))
        gap = F.when(F.col("give") > 0, F.abs(F.col("raked") / F.col("give") - 1)).otherwise(0.0)
        rows = rows.join(F.broadcast(all_)).select(F.lit(d).alias("dimension"), "value", (F.col("want") / F.col("all_want")).alias("target"), (F.col("have") / F.col("all_have")).alias("expected"), gap.alias("gap"))
        out = rows if out is None else out.unionByName(rows)
    return out


def margins(cells: DataFrame, d: str, given: Mapping[str, float] | None, rate: float) -> DataFrame:
    """__value, want (target tokens) and give (tokens in reach at this rate) of one dimension.

    No value can hold more than all its tokens at probability 1: what it lacks goes to the other values.
    """
    table = cells.groupBy(d).agg(F.sum("tokens").alias("tokens"))
    if given is None:
        share = F.pow(F.col("tokens").cast("double"), F.lit(TEMPER))
    else:
        pairs = [x for k, v in given.items() for x in (F.lit(k), F.lit(float(v)))]
        share = F.coalesce(F.create_map(*pairs)[F.col(d)], F.lit(0.0)) if pairs else F.lit(0.0)
    table = written(table.withColumn("share", share), "shares")
    total, shares = table.agg(F.sum("tokens"), F.sum("share")).first()
    want = F.col("share") * ((total or 0) / shares) if shares else F.lit(0.0)
    table = ceiled(table.withColumn("weight", want), rate)
    return table.select(F.col(d).alias("__value"), F.col("weight").alias(f"want_{d}"), (F.col("prob") * F.col("tokens") / rate).alias(f"give_{d}"))


def fitted_cells(cells: DataFrame, targets: Mapping[str, Mapping[str, float]] | None = None, rounds: int = ROUNDS, rate: float = RATE) -> DataFrame:
    """(source, lang, topic, tokens) to the same with weight, prob, and by dimension the target in
    tokens (want_<dimension>) and what of it is in reach (give_<dimension>).

    A weight is never more than prob 1 can hold. Where a target is out of reach at
    this rate, the rest is spread over the other values; :func:`shortfalls` tells.

    ``targets``: shares by dimension and value; a dimension that is not named
    is tempered. A value that a named dimension lacks has share 0.
    """
    cells = written(cells.withColumn("weight", F.col("tokens").cast("double")), "cells")
    small = cells.count() <= SMALL
    state = cells
    for d in DIMENSIONS:
        state = state.join(margins(cells, d, (targets or {}).get(d), rate), F.col(d) == F.col("__value")).drop("__value")
    state = written(state, "cells")

    def raked(have: Column, d: str) -> Column:
        return F.when(have > 0, F.least(F.col("weight") * F.col(f"give_{d}") / have, F.col("tokens") / rate)).otherwise(0.0)

    done = 0
    while done < rounds:
        if small:
            state = state.coalesce(1)
            for _ in range(min(ROUNDS_A_PLAN, rounds - done)):
                for d in DIMENSIONS:
                    state = state.withColumn("weight", raked(F.sum("weight").over(Window.partitionBy(d)), d))
            state, done = written(state, "cells"), done + ROUNDS_A_PLAN
            continue
        for d in DIMENSIONS:
            have = state.groupBy(d).agg(F.sum("weight").alias("__have"))
            state = written(state.join(have, d).withColumn("weight", raked(F.col("__have"), d)).drop("__have"), "cells")
        done += 1
    state = ceiled(state, rate)
    return state.select(*DIMENSIONS, "tokens", "weight", "prob", *[F.col(f"{x}_{d}") for x in ("want", "give") for d in DIMENSIONS])


def mix(docs: DataFrame, targets: Mapping[str, Mapping[str, float]] | None = None, rate: float = RATE, rounds: int = ROUNDS, topic: Column | None = None, tokens: Column | None = None, seed: str = SEED, text: str = "text", source: str = "source", lang: str = "lang", doc_id: str = "doc_id", columns: list[str] | None = None) -> DataFrame:
    """The rows of ``docs``, columns ``columns`` (default: doc_id), with topic, tokens, prob and chosen.

    Null source or language is a value of its own, "(none)"; a null text counts
    as empty (one token). Repeated rows have one draw and are chosen together.
    An empty table gives an empty result.
    """
    body = text_or_empty(text)
    keys = {"source": F.coalesce(F.col(source), F.lit(NONE)), "lang": F.coalesce(F.col(lang), F.lit(NONE)), "topic": topic_of(body) if topic is None else topic}
    size = tokens_of(body) if tokens is None else tokens
    names = columns or [doc_id]
    keyed = docs.select(*names, *[v.alias(f"__{k}") for k, v in keys.items()], size.alias("__tokens"), draw(F.col(doc_id), body, seed).alias("__draw"))
    cells = keyed.groupBy(*[F.col(f"__{k}").alias(k) for k in keys]).agg(F.sum("__tokens").alias("tokens"))
    fitted = written(fitted_cells(cells, targets, rounds, rate), "cells").select(*[F.col(k).alias(f"__{k}") for k in keys], F.col("prob").alias("__prob"))
    if fitted.count() <= SMALL:
        fitted = F.broadcast(fitted)
    return keyed.join(fitted, [f"__{k}" for k in keys]).select(*names, F.col("__topic").alias("mix_topic"), F.col("__tokens").alias("mix_tokens"), F.col("__prob").alias("prob"), (F.col("__draw") < F.col("__prob")).alias("chosen"))


def sample_mix(docs: DataFrame, targets: Mapping[str, Mapping[str, float]] | None = None, rate: float = RATE, **names) -> DataFrame:
    """``docs`` with the chosen rows only, columns unchanged."""
    kept = docs.select(*[F.col(c).alias(f"__c{i}") for i, c in enumerate(docs.columns)])
    of = {c: f"__c{i}" for i, c in enumerate(docs.columns)}
    where = {k: of[names.get(k, k)] for k in ("text", "source", "lang", "doc_id")}
    return mix(kept, targets, rate, columns=kept.columns, **where).where("chosen").select(*[F.col(v).alias(k) for k, v in of.items()])
