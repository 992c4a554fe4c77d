"""Quality classifier with supervised subword embeddings.

Words and the character n-grams inside them are hashed to buckets, each with a
learned vector. A document is the average of its buckets' vectors; a linear
layer and softmax give the class. Vectors and layer are trained together by
stochastic gradient descent in numpy.

With two classes the logit is linear in the average, so scoring needs one
number a bucket (its vector times the difference of the two output rows). The
n-grams of a whole batch of texts are hashed at once with rolling polynomial
hashes over the batch's characters (code points, so that an umlaut is one).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import by_value, id_remainder

by_value(__name__)

#: Documented bound: labelled documents learned from (expected number; whole texts).
SAMPLE = 3000
BITS, DIM, EPOCHS, RATE = 16, 10, 8, 0.4
GRAMS = (3, 4, 5)
#: Characters hashed at a time; longer texts go on in the next part, cut at white space.
PART = 1 << 19
PRIME = 0x9E3779B97F4A7C15 | 1
#: ASCII white space to blanks.
BLANKS = str.maketrans(dict.fromkeys("\t\n\x0b\x0c\r", " "))


def powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[:1] = 1
    return np.cumprod(out, dtype=np.uint64)


def parts(texts: list[str]) -> Iterator[tuple[list[int], list[str]]]:
    """Groups of (document, its lower-case text or a part of it) of about PART characters."""
    at, out, size = [], [], 0
    for i, text in enumerate(texts):
        text = text.lower().translate(BLANKS)
        begin = 0
        while begin < len(text) or not begin:
            end = len(text)
            if end - begin > PART:
                end = text.rfind(" ", begin + 1, begin + PART)
                end = end if end > begin else begin + PART
            at.append(i)
            out.append(text[begin:end])
            size += end - begin
            begin = end
            if size >= PART:
                yield at, out
                at, out, size = [], [], 0
            if end >= len(text):
                break
    if at:
        yield at, out


def hashed(pieces: list[str]) -> tuple[np.ndarray, list[tuple[np.ndarray, np.ndarray]]]:
    """Starts of the pieces in their joined characters, and (positions, buckets) of words and n-grams."""
    joined = "".join(f" {p} " for p in pieces)
    b = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
    starts = np.cumsum([0] + [len(p) + 2 for p in pieces])[:-1]
    blank = b == 32
    shift = np.uint64(64 - BITS)
    wide = b.astype(np.uint64) + np.uint64(1)
    out = []
    # Words: differences of a prefix hash, moved to a common origin.
    prime = PRIME % (1 << 64)
    begin = np.flatnonzero(blank[:-1] & ~blank[1:]) + 1
    end = np.flatnonzero(~blank[:-1] & blank[1:]) + 1
    prefix = np.r_[np.uint64(0), np.cumsum(wide * powers(prime, len(b)), dtype=np.uint64)]
    words = (prefix[end] - prefix[begin]) * powers(pow(prime, -1, 1 << 64), len(b))[begin]
    out.append((begin, ((words ^ (words >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)) >> shift))
    blanks = np.r_[0, np.cumsum(blank)]
    h = wide
    for n in range(2, max(GRAMS) + 1):
        h = h[:-1] * np.uint64(prime) + wide[n - 1 :]
        if n in GRAMS and len(h):
            inner = np.flatnonzero(blanks[n - 1 : n - 1 + len(h)] == blanks[1 : 1 + len(h)])
            x = h[inner]
            out.append((inner, ((x ^ (x >> np.uint64(29))) * np.uint64(0x94D049BB133111EB + 2 * n)) >> shift))
    return starts, out


def bucket_counts(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Distinct buckets of a text and their counts. Bucket 0 also stands once in every text."""
    total = np.zeros(1 << BITS, np.int64)
    total[0] = 1
    for _, pieces in parts([text]):
        for _, buckets in hashed(pieces)[1]:
            total += np.bincount(buckets.astype(np.int64), minlength=1 << BITS)
    at = np.flatnonzero(total)
    return at.astype(np.uint16), total[at].astype(np.float32)


def logits(texts: list[str], weight: np.ndarray) -> np.ndarray:
    total, count = np.full(len(texts), float(weight[0])), np.ones(len(texts))
    for at, pieces in parts(texts):
        starts, found = hashed(pieces)
        for where, buckets in found:
            piece = np.searchsorted(starts, where, side="right") - 1
            n = np.bincount(piece, minlength=len(pieces))
            s = np.bincount(piece, weights=weight[buckets.astype(np.int64)], minlength=len(pieces))
            np.add.at(total, at, s)
            np.add.at(count, at, n)
    return total / count


def fit(rows: list[tuple[np.ndarray, np.ndarray, int]], seed: int = 1) -> np.ndarray:
    """Stochastic gradient descent over (buckets, counts, label); a weight a bucket for class 1 against 0."""
    rng = np.random.default_rng(seed)
    vectors = rng.uniform(-1 / DIM, 1 / DIM, (1 << BITS, DIM)).astype(np.float32)
    layer = np.zeros((2, DIM), np.float32)
    steps, done = EPOCHS * len(rows), 0
    for _ in range(EPOCHS):
        for i in rng.permutation(len(rows)):
            at, n, label = rows[i]
            share = n.astype(np.float32)
            share /= share.sum()
            hidden = share @ vectors[at]
            z = layer @ hidden
            p = np.exp(z - z.max())
            p /= p.sum()
            p[label] -= 1
            rate = RATE * (1 - done / steps)
            back = layer.T @ p
            layer -= rate * np.outer(p, hidden)
            # The average's gradient, shared out so that a bucket moves as in a text of a hundred features.
            vectors[at] -= rate * np.minimum(1.0, 100 * share)[:, None] * back
            done += 1
    return vectors.astype(np.float64) @ (layer[1] - layer[0]).astype(np.float64)


def train(docs: DataFrame, labels: DataFrame, learn: Column, text: str = "text", doc_id: str = "doc_id", label: str = "quality", sample: int = SAMPLE) -> np.ndarray:
    """Weights learned from about ``sample`` of the labelled documents that ``learn`` admits.

    An id that is labelled more than once counts once, with its highest label;
    null ids, labels and texts are left out. Without labels all weights are 0.
    """
    marks = labels.where(F.col(doc_id).isNotNull() & F.col(label).isin(0, 1)).where(learn).groupBy(F.col(doc_id).alias("__id")).agg(F.max(label).cast("int").alias("__y"))
    marks = marks.withColumn("__u", F.pmod(F.xxhash64("__id", F.lit("quality")), F.lit(1 << 30)))
    n = marks.count()
    if not n:
        return np.zeros(1 << BITS)
    chosen = marks.where(F.col("__u") < int((1 << 30) * min(1.0, sample / n)))  # about ``sample`` rows: safe to broadcast
    rows = docs.select(F.col(doc_id).alias("__id"), F.col(text).alias("__text")).where(F.col("__text").isNotNull()).join(F.broadcast(chosen), "__id").select("__id", "__u", "__y", "__text")

    def counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                at, n = bucket_counts(batch.column(3)[row].as_py())
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(row, 1), batch.column(1).slice(row, 1), batch.column(2).slice(row, 1), pa.array([at.tobytes()], pa.binary()), pa.array([n.astype(np.float16 if n.max() < 2000 else np.float32).tobytes()], pa.binary())], names=["id", "u", "y", "at", "n"])

    kind = docs.schema[doc_id].dataType.simpleString()
    found = rows.mapInArrow(counts, f"id {kind}, u long, y int, at binary, n binary").toLocalIterator()
    data = []
    for r in found:
        at = np.frombuffer(r["at"], np.uint16)
        data.append(((r["u"], r["id"], r["at"]), at, np.frombuffer(r["n"], np.float16 if len(r["n"]) == 2 * len(at) else np.float32), r["y"]))  # 4 bytes a bucket, as a rule
    data.sort(key=lambda x: x[0])
    return fit([x[1:] for x in data]) if data else np.zeros(1 << BITS)


def held_out(doc_id: str = "doc_id") -> Column:
    """Rows kept from training: crc32 of the id modulo 3 is 1."""
    return id_remainder(doc_id, 3) == 1


def score(docs: DataFrame, weight: np.ndarray, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """doc_id, score for every row: the probability of class 1 over the whole text (null: empty)."""
    shared = docs.sparkSession.sparkContext.broadcast(weight)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for begin in range(0, batch.num_rows, 512):
                part = batch.slice(begin, 512)
                z = logits([t.as_py() or "" for t in part.column(1)], shared.value)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(1 / (1 + np.exp(-np.clip(z, -60, 60))))], names=["doc_id", "score"])

    kind = docs.schema[doc_id].dataType.simpleString()
    return docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, f"doc_id {kind}, score double")


def classify(docs: DataFrame, labels: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """doc_id, held_out, score, predicted for every row; repeated rows give repeated results."""
    weight = train(docs, labels, ~held_out(doc_id), text, doc_id)
    return score(docs, weight, text, doc_id).select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
