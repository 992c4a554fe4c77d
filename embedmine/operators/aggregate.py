"""Aggregation by pattern in two levels, domains, and minimum-image support."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import patterns
from ..plans.scratch import written
from ..sources.graph import measured

PATTERN = ["k", "n_edges", "degs", "lbls"]


def code_keys(f: DataFrame) -> list[str]:
    return ["code", "labels"] if "labels" in f.columns else ["code"]


def by_quick(f: DataFrame, aggregates: dict[str, Column]) -> DataFrame:
    """First level: values by quick code; isomorphism is not touched."""
    return f.groupBy(*code_keys(f)).agg(*[v.alias(n) for n, v in aggregates.items()])


def by_pattern(quick: DataFrame, k: int | None, merge: dict[str, Column]) -> DataFrame:
    """Second level: quick values (one row a code) with their canonical forms, merged: canon, PATTERN columns, values."""
    return patterns.canonicalize(quick, k, grouped=True).groupBy("canon", *PATTERN).agg(*[v.alias(n) for n, v in merge.items()])


def forms_of(f: DataFrame, k: int | None, values: dict[str, Column] | None = None) -> DataFrame:
    """The quick codes of a level, one row each: n embeddings, further first-level values, canonical form."""
    quick = by_quick(f, {"n": F.count(F.lit(1)), **(values or {})})
    # Codes are few bytes but dear to canonicalize: dealt to all tasks, not merged by their size.
    quick = quick.repartition(int(f.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return written(patterns.canonicalize(quick, k, grouped=True), "forms")


def count_by_pattern(f: DataFrame, k: int | None) -> DataFrame:
    """canon, PATTERN, n: embeddings of each pattern, in two levels."""
    return by_pattern(by_quick(f, {"n": F.count(F.lit(1))}), k, {"n": F.sum("n")})


def count_one_level(f: DataFrame, k: int) -> DataFrame:
    """The same without the first level: a canonical form for every embedding (for the ablation)."""
    labelled = "labels" in f.columns

    def run(batches):
        for batch in batches:
            forms = [patterns.described(*patterns.vertex_pattern(r["code"], k, r.get("labels")), fresh=True) for r in batch.to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in forms], t) for i, t in enumerate((pa.string(), pa.int32(), pa.int32(), pa.string(), pa.string()))], names=["canon", *PATTERN])

    forms = f.select("code", *(["labels"] if labelled else [])).mapInArrow(run, "canon string, k int, n_edges int, degs string, lbls string")
    return forms.groupBy("canon", *PATTERN).agg(F.count(F.lit(1)).alias("n"))


def supports(f: DataFrame, forms: DataFrame, least: int | None = None, name: str = "support") -> DataFrame:
    """canon, PATTERN, and the smallest domain of a pattern's vertices, over embeddings with their visited vertices ``vs``.

    An embedding feeds all positions that its pattern's symmetries exchange, so
    domains belong to orbits; vertices are counted once in each. With ``least``
    a pattern whose embeddings, times the vertices of an orbit, cannot reach it is left out before the distinct.
    """
    keys = code_keys(f)
    if least is not None:
        hopeful = forms.groupBy("canon", "k").agg(F.sum("n").alias("n")).where(F.col("n") * F.col("k") >= least).select("canon")
        forms = written(forms.join(hopeful, "canon", "left_semi"), "hopeful")
    # Patterns travel as two hashes of their form, 128 bits: narrow rows of fixed width for the wide distinct.
    form = [F.xxhash64("canon").alias("form"), F.xxhash64("canon", F.lit(1)).alias("again")]
    of = measured(forms.select(*keys, *form, "orbit"))
    images = f.select(*keys, "vs").join(of, keys).select("form", "again", F.explode(F.arrays_zip("orbit", "vs")).alias("i")).select("form", "again", "i.orbit", "i.vs").distinct()
    sizes = images.groupBy("form", "again", "orbit").agg(F.count(F.lit(1)).alias("size")).groupBy("form", "again").agg(F.min("size").alias(name))
    return forms.select("canon", *PATTERN, *form).distinct().join(sizes, ["form", "again"]).select("canon", *PATTERN, name)


def approximate_support(f: DataFrame, k: int, error: float = 0.02) -> DataFrame:
    """Support from distinct-count sketches: a cheap pre-test."""
    forms = forms_of(f, None)
    of = measured(forms.select("code", "labels", "canon", *PATTERN, "orbit"))
    images = f.select("code", "labels", "vs").join(of, ["code", "labels"]).select("canon", *PATTERN, F.explode(F.arrays_zip("orbit", "vs")).alias("i"))
    sizes = images.groupBy("canon", *PATTERN, F.col("i.orbit").alias("orb")).agg(F.approx_count_distinct("i.vs", error).alias("size"))
    return sizes.groupBy("canon", *PATTERN).agg(F.min("size").alias("support"))


def support_near(f: DataFrame, k: int, threshold: int, error: float = 0.02) -> DataFrame:
    """canon, PATTERN, support of the patterns that reach ``threshold``: sketches decide where they are clear
    (five errors off), and the rest is counted exactly. ``support`` is exact for all that are returned."""
    rough = written(approximate_support(f, k, error), "sketched")
    low = rough.where(F.col("support") >= threshold * (1 - 5 * error)).select("canon")
    forms = forms_of(f, None).join(low, "canon", "left_semi")
    return supports(f, written(forms, "forms"), threshold).where(F.col("support") >= threshold)
