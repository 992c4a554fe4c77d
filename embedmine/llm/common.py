"""What the operators share: shared scratch tables, worker caches, text helpers."""

from __future__ import annotations

import sys
import types

from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.scratch import scratch_root, written

__all__ = ["ASCII_SPACE", "by_value", "id_remainder", "numbered", "ranked", "scratch_root", "spread_join", "squeezed", "text_or_empty", "without", "worker_cache", "written"]

#: The ASCII white space that the text contracts name.
ASCII_SPACE = " \t\n\x0b\x0c\r"


def by_value(module: str) -> None:
    """Send the functions of a module to the Python workers with their code, so
    that executors need no copy of this package."""
    cloudpickle.register_pickle_by_value(sys.modules[module])


def worker_cache(name: str) -> dict:
    """A dict that lives as long as the Python worker (tasks reuse workers)."""
    holder = sys.modules.setdefault("_llm_worker_cache", types.ModuleType("_llm_worker_cache"))
    return holder.__dict__.setdefault(name, {})


def text_or_empty(text: str | Column) -> Column:
    return F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))


def squeezed(text: Column) -> Column:
    """The text without ASCII white space."""
    return F.translate(text, ASCII_SPACE, "")


def id_remainder(doc_id: str, modulus: int) -> Column:
    """crc32 of the id's decimal text, modulo ``modulus``; a null id counts as ''."""
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary")) % modulus


def numbered(docs: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """``docs`` with its columns renamed __c0, __c1, ..., so that none is named like a
    column an operator adds, and the new name of each."""
    of = {c: f"__c{i}" for i, c in enumerate(docs.columns)}
    return docs.select(*[F.col(f"`{c}`").alias(n) for c, n in of.items()]), of


def spread_join(rows: DataFrame, table: DataFrame, key: list[str], salt_by: list[str], how: str = "inner") -> DataFrame:
    """``rows`` joined with ``table``, which has one row a key; no task gathers a key's rows.

    Rows are dealt by the key and a salt, a hash of ``salt_by``. First the distinct
    (salt, key) pairs meet the table: at most one pair a salt for a key of very many rows.
    Then the rows meet their own pair.
    """
    salts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    salted = rows.withColumn("__salt", F.pmod(F.xxhash64(*salt_by), F.lit(salts)))
    entries = salted.select("__salt", *key).distinct().join(table, key)
    return salted.join(entries, ["__salt", *key], how).drop("__salt")


#: Verdicts up to which a join may broadcast them (under 100 bytes each).
FEW = 50_000


def without(rows: DataFrame, verdicts: DataFrame, doc_id: Column, tag: Column) -> DataFrame:
    """The ``rows`` that stay, by verdicts (doc_id, tag, stays, times), one for each pair.

    Only what goes, or stands there several times, is looked up: rows that match
    none of these verdicts do not move while the verdicts are few by their count.
    Of rows that repeat doc_id and tag one stays.
    """
    found = verdicts.where(~F.col("stays") | (F.col("times") > 1))
    found = written(found.select(F.col("doc_id").alias("__id"), F.col("tag").alias("__tag"), (F.col("stays") & (F.col("times") > 1)).alias("__once")), "verdicts")
    few, again = found.agg(F.count(F.lit(1)) <= FEW, F.count_if("__once")).first()
    shared = F.broadcast if few else lambda x: x
    marked = rows.withColumn("__of", tag)
    same = doc_id.eqNullSafe(F.col("__id")) & (F.col("__of") == F.col("__tag"))
    kept = marked.join(shared(found), same, "left_anti").drop("__of")
    if not again:
        return kept
    repeated = marked.join(shared(found.where("__once")), same).dropDuplicates(["__id", "__tag"])
    return kept.unionByName(repeated.select(rows.columns))


def ranked(df: DataFrame, key: list[str], order: list[str], out: str, salts: int) -> DataFrame:
    """Adds ``out``: the row's place from 0 within ``key``, without bringing a
    key's rows into one task. Rows are numbered within (key, salt); the counts
    of the salts before are added. Ties in ``order`` must not matter.
    """
    salted = df.withColumn("__salt", F.pmod(F.xxhash64(*order), F.lit(salts)))
    counts = salted.groupBy(*key, "__salt").agg(F.count(F.lit(1)).alias("__n"))
    before = counts.select(
        *key,
        "__salt",
        (F.sum("__n").over(Window.partitionBy(*key).orderBy("__salt")) - F.col("__n")).alias("__before"),
    )
    inner = salted.withColumn("__at", F.row_number().over(Window.partitionBy(*key, "__salt").orderBy(*order)))
    return inner.join(before, [*key, "__salt"]).withColumn(out, F.col("__before") + F.col("__at") - 1).drop("__salt", "__n", "__before", "__at")


by_value(__name__)
