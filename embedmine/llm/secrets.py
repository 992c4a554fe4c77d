"""Secret scans with an incremental blob ledger (DataFrame functions only).

Every version of every document is content-addressed: equal texts are one blob.
A ledger table remembers which (blob, rule version) pairs have been scanned and
what was found. A scan reads only the pairs that the ledger lacks, adds them to
it, and joins the findings back to all paths that hold the blob.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType, StringType, StructField, StructType

from .common import scratch_root, text_or_empty

FOUND = ArrayType(StructType([StructField("start", IntegerType()), StructField("rank", IntegerType()), StructField("stop", IntegerType()), StructField("kind", StringType())]))


@dataclass(frozen=True)
class Rule:
    """Leftmost non-overlapping matches of ``pattern`` whose ``group`` has ``least`` characters.

    ``hint``: a literal that every match holds, to skip texts cheaply.
    """

    kind: str
    version: int
    pattern: str
    group: int = 0
    least: int = 0
    base: bool = False
    hint: str = ""

    @property
    def key(self) -> str:
        return f"{self.kind}@{self.version}"


#: The patterns. The runs of access and hex are written with their
#: least length: their matches are whole runs, so that this drops the same ones.
RULES = (
    Rule("assign", 1, r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6, base=True),
    Rule("access", 1, r"AKIA[A-Z0-9]{16,}", base=True, hint="AKIA"),
    Rule("hex", 1, r"[0-9a-f]{24,}", base=True),
    Rule("pem", 1, r"-----BEGIN [A-Z ]*PRIVATE KEY-----", hint="PRIVATE KEY-----"),
    Rule("jwt", 1, r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", hint=".eyJ"),
    Rule("forge", 1, r"gh[pousr]_[A-Za-z0-9]{36,}", hint="gh"),
    Rule("chat", 1, r"xox[abprs]-[A-Za-z0-9-]{10,}", hint="xox"),
)


def once(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use`` of a value that is computed one time, though lambdas in it read it again and again."""
    return F.element_at(F.transform(F.array(value), use), 1)


def without_repeats(found: Column) -> Column:
    """The spans sorted, each one time. (array_distinct compares all pairs of structs.)"""
    return once(F.array_sort(found), lambda s: F.filter(s, lambda x, i: (i == 0) | (x != F.get(s, i - 1))))


def find(text: Column, rule: Rule, rank: int) -> Column:
    """Array of (start, rank, stop, kind) in code points, stop exclusive.

    The pieces between the matches and the matches themselves tell the places:
    the lengths of all before them, summed first by blocks of as many matches as
    there are blocks, then within each, so that no long array grows match by match.
    """
    nothing = F.array().cast(FOUND)
    hits = F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(0))
    parts = F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(rule.group)) if rule.group else hits
    pieces = F.arrays_zip(F.slice(F.split(text, rule.pattern, -1), 1, F.size(hits)).alias("gap"), hits.alias("hit"), parts.alias("part"))
    sized = F.transform(pieces, lambda x: F.struct(F.length(x["gap"]).alias("gap"), F.length(x["hit"]).alias("hit"), (F.length(x["part"]) >= rule.least).alias("good")))

    def spans(rows: Column) -> Column:
        wide = F.ceil(F.sqrt(F.size(rows))).cast("int")
        blocks = F.sequence(F.lit(0), F.floor((F.size(rows) - 1) / wide).cast("int"))
        places = lambda b: F.sequence(b * wide, F.least((b + 1) * wide, F.size(rows)) - 1)
        lengths = F.transform(blocks, lambda b: F.aggregate(places(b), F.lit(0), lambda n, i: n + F.get(rows, i)["gap"] + F.get(rows, i)["hit"]))
        zero = F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("out"))
        bases = F.aggregate(lengths, zero, lambda acc, n: F.struct((acc["at"] + n).alias("at"), F.concat(acc["out"], F.array(acc["at"])).alias("out")), lambda acc: acc["out"])

        def step(acc: Column, i: Column) -> Column:
            x = F.get(rows, i)
            begin = acc["at"] + x["gap"]
            stop = begin + x["hit"]
            span = F.struct(begin.alias("start"), F.lit(rank).alias("rank"), stop.alias("stop"), F.lit(rule.kind).alias("kind"))
            return F.struct(stop.alias("at"), F.when(x["good"], F.concat(acc["out"], F.array(span))).otherwise(acc["out"]).alias("out"))

        within = lambda base, b: F.aggregate(places(b), F.struct(base.alias("at"), nothing.alias("out")), step, lambda acc: acc["out"])
        return F.flatten(F.transform(bases, within))

    hinted = text.contains(rule.hint) & text.rlike(rule.pattern) if rule.hint else text.rlike(rule.pattern)
    return F.when(hinted, once(sized, spans)).otherwise(nothing)


def scan(blobs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(blob, body, seen) to (blob, scanned, found): the rules that ``seen`` lacks."""
    due = {r: ~F.coalesce(F.array_contains("seen", r.key), F.lit(False)) for r in rules}
    nothing = F.array().cast(FOUND)
    found = F.concat(*[F.when(due[r], find(F.col("body"), r, i)).otherwise(nothing) for i, r in enumerate(rules)])
    scanned = F.filter(F.array(*[F.when(due[r], F.lit(r.key)) for r in rules]), lambda x: x.isNotNull())
    return blobs.select("blob", scanned.alias("scanned"), found.alias("found"))


def scan_versions(versions: DataFrame, ledger: str, text: str = "text", path: str = "doc_id", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Scans what the ledger at path ``ledger`` lacks, adds it there, and returns one row for
    each row of ``versions``: path, blob, found (sorted by start, then by rule).

    Null texts count as empty; repeated rows share a blob and a result. A blob
    whose scan is repeated after a failure is the same row again: findings are
    read as sets. An empty table adds nothing.
    """
    spark = versions.sparkSession
    body = text_or_empty(text)
    blob = F.unhex(F.sha2(body, 256))
    blobs = versions.select(blob.alias("blob"), body.alias("body")).groupBy("blob").agg(F.first("body").alias("body"))
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(ledger)
    known = place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(place)
    schema = StructType([StructField("blob", versions.select(blob.alias("b")).schema["b"].dataType), StructField("scanned", ArrayType(StringType())), StructField("found", FOUND)])
    if known:
        before = spark.read.schema(schema).parquet(ledger).groupBy("blob").agg(F.flatten(F.collect_set("scanned")).alias("seen"))
        blobs = blobs.join(before, "blob", "left").where(F.coalesce(F.size(F.array_except(F.array(*[F.lit(r.key) for r in rules]), "seen")), F.lit(1)) > 0)
    else:
        blobs = blobs.withColumn("seen", F.lit(None).cast("array<string>"))
    scan(blobs, rules).write.mode("append").parquet(ledger)
    active = [r.key for r in rules]
    kinds = F.array(*[F.lit(k.rsplit("@", 1)[0]) for k in active])
    entries = spark.read.schema(schema).parquet(ledger).where(F.size("found") > 0).where(F.arrays_overlap("scanned", F.array(*map(F.lit, active))))
    of_rule = lambda x: F.array_contains(F.col("scanned"), F.element_at(F.create_map(*[y for r in rules for y in (F.lit(r.kind), F.lit(r.key))]), x["kind"]))
    entries = entries.select("blob", F.filter("found", lambda x: F.array_contains(kinds, x["kind"]) & of_rule(x)).alias("found")).where(F.size("found") > 0)
    per_blob = entries.groupBy("blob").agg(without_repeats(F.flatten(F.collect_set("found"))).alias("found"))
    paths = versions.select(F.col(path).alias(path), blob.alias("blob"))
    return paths.join(per_blob, "blob", "left").select(path, "blob", F.coalesce("found", F.array().cast(FOUND)).alias("found"))


def spelled(found: Column) -> Column:
    return F.concat_ws(",", F.transform(found, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["stop"].cast("string"))))


def secret_spans(docs: DataFrame, ledger: str | None = None, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans of every row."""
    ledger = ledger or f"{scratch_root(docs.sparkSession)}/ledger-{uuid.uuid4().hex}"
    found = scan_versions(docs, ledger, text, doc_id)
    base = [r.kind for r in RULES if r.base]

    def number(kind: str) -> Column:
        return F.size(F.filter("found", lambda x: x["kind"] == kind)).cast("long").alias(f"n_{kind}")

    return found.select(F.col(doc_id).alias("doc_id"), *map(number, base), F.sha2(spelled(F.filter("found", lambda x: x["kind"].isin(base))), 256).alias("base_sha256"), spelled(F.col("found")).alias("spans"))
