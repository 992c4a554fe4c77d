"""Exact duplicates by a tree merge of sorted digest runs (DataFrame functions only).

Every input partition writes one *run*: its documents' digests in sorted order.
Runs are merged in rounds of a binomial tree; ``fan_in`` runs meet at a time
(2 gives the plain binomial rounds, more gives multiway merging with fewer
rounds). A merge keeps for each digest the number of documents and the best
identifier so far. A digest's entries at one level number at most one a run, so
however many copies a text has, no task ever gathers them: a group of a third
of all rows is one entry in each run.

The runs are dealt by (run, digest), so the last round is spread over the
cluster as well. Texts do not move; only 80-byte entries do.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import numbered, squeezed, text_or_empty, without, written

#: Runs that meet in one merge.
FAN_IN = 16


def digest_runs(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """One row per document: run, row (unique), doc_id, chars, digest, check; sorted in each run.

    ``digest`` is SHA-256 of the text without ASCII white space; ``check`` (its
    XXH64) verifies it: entries merge only where both agree.
    """
    body = text_or_empty(text)
    norm = squeezed(body)
    rows = docs.select(
        F.spark_partition_id().alias("run"),
        F.monotonically_increasing_id().alias("row"),
        F.col(doc_id).alias("doc_id"),
        F.length(body).cast("long").alias("chars"),
        F.unhex(F.sha2(norm, 256)).alias("digest"),
        F.xxhash64(norm).alias("check"),
    )
    return written(rows.sortWithinPartitions("digest", "check"), "digest-runs")


def merge_runs(runs: DataFrame, fan_in: int = FAN_IN) -> tuple[DataFrame, DataFrame]:
    """(entries of each run, entries of the tree's root): digest, check, size, best."""
    key = ["digest", "check"]
    best = F.struct((-F.col("chars")).alias("c"), F.col("doc_id").isNull().alias("z"), F.col("doc_id").alias("i"), F.col("row").alias("r"))
    first = runs.groupBy("run", *key).agg(F.count(F.lit(1)).alias("size"), F.min(best).alias("best"))
    width = (runs.agg(F.max("run")).first()[0] or 0) + 1
    level = first
    while width > 1:
        level = level.groupBy(F.floor(F.col("run") / fan_in).alias("run"), *key).agg(F.sum("size").alias("size"), F.min("best").alias("best"))
        width = -(-width // fan_in)
    return first, level


def exact_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", fan_in: int = FAN_IN) -> DataFrame:
    """One row per row of ``docs``: doc_id, keep_id, group_size, kept, text_sha256.

    Texts are equal if they agree without ASCII white space; null counts as
    empty. Of a group the longest original (code points) stays, then the
    smallest doc_id (null last), then the first row: of repeated rows exactly
    one has ``kept``. An empty table gives an empty result. Other columns are
    not read.
    """
    runs = digest_runs(docs, text, doc_id)
    first, root = merge_runs(runs, fan_in)
    several = root.where("size > 1").select("digest", "check", F.col("size").alias("group_size"), F.col("best.i").alias("keep_id"), F.col("best.r").alias("keep_row"))
    entries = first.select("run", "digest", "check").join(several, ["digest", "check"])
    return runs.join(entries, ["run", "digest", "check"], "left").select(
        "doc_id",
        F.when(F.col("group_size").isNull(), F.col("doc_id")).otherwise(F.col("keep_id")).alias("keep_id"),
        F.coalesce("group_size", F.lit(1).cast("long")).alias("group_size"),
        F.coalesce(F.col("row") == F.col("keep_row"), F.lit(True)).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def drop_exact_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``docs`` with one row of each group of equal texts, columns unchanged, whatever their names.

    Rows that repeat both doc_id and text are one document given several times:
    any one of them stays.
    """
    rows, of = numbered(docs)
    marks = exact_duplicates(rows, of[text], of[doc_id]).groupBy("doc_id", F.unhex("text_sha256").alias("tag")).agg(F.max("kept").alias("stays"), F.count(F.lit(1)).alias("times"))
    digest = F.unhex(F.sha2(squeezed(text_or_empty(of[text])), 256))
    return without(rows, marks, F.col(of[doc_id]), digest).select(*[F.col(n).alias(c) for c, n in of.items()])
