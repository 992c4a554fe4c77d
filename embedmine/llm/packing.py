"""Packing of documents into sequences by minimum bin slack.

For each bin the largest remaining length is fixed and a subset-sum over the
other lengths (bitsets held as integers) finds the fullest combination that
fits, which is then removed. Lengths are whole numbers up to the capacity, so
the search works on their histogram: a combination found once is taken as often
as its lengths last. Only that histogram, at most ``capacity`` rows however
many documents there are, goes to the driver; documents find their place by
their rank among those of equal length.
"""

from __future__ import annotations

import base64
import json
import os
import re
import zlib
from array import array
from collections.abc import Iterator, Mapping

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_value, ranked, worker_cache, written

by_value(__name__)

CAPACITY, END_ID = 1024, 2
#: Entries of the tokenizer's word cache in a worker, and the longest word that it holds.
CACHE, CACHED_LENGTH = 200_000, 40
#: A single blank between two characters that are no white space: tokens never cross it.
BREAK = re.compile(r"(?<=\S) (?=\S)")


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def added_tokens(vocabulary: str) -> dict[str, int]:
    """The added tokens of the JSON file beside the rank file (none without one): content to id."""
    beside = os.path.splitext(vocabulary)[0] + ".json"
    if not os.path.exists(beside):
        return {}
    with open(beside, encoding="utf-8") as lines:
        added = json.load(lines)["added_tokens"]
    for token in added:
        if token["single_word"] or token["lstrip"] or token["rstrip"] or " " in token["content"]:
            raise ValueError(f"added token with rules that are not implemented: {token}")
    return {token["content"]: token["id"] for token in added}


class Encoder:
    """Ids of the byte-level BPE as little-endian unsigned 32-bit bytes, with a cache of words.

    Texts are split at the ``added`` tokens (content to id) first; without
    ``added``, such strings are text like any other.
    """

    def __init__(self, vocabulary: str, added: Mapping[str, int] | None = None):
        import public_tokenizers
        import tiktoken

        with open(vocabulary, "rb") as lines:
            ranks = {base64.b64decode(word): int(rank) for word, rank in map(bytes.split, lines)}
        self.bpe = tiktoken.Encoding("byte_bpe", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=dict(added or {}))
        self.added = self.bpe.special_tokens_set
        self.known: dict[str, bytes] = {}

    def of(self, text: str) -> bytes:
        if any(token in text for token in self.added):
            return array("I", self.bpe.encode(text, allowed_special=self.added)).tobytes()
        return array("I", self.bpe.encode_ordinary(text)).tobytes()

    def encode(self, text: str) -> bytes:
        first, *words = BREAK.split(text)
        try:
            return self.of(first) + b"".join(map(self.known.__getitem__, words))
        except KeyError:
            pass
        if len(self.known) > CACHE:
            self.known.clear()
        extra = {}
        for word in set(words).difference(self.known):
            (self.known if len(word) <= CACHED_LENGTH else extra)[word] = self.of(" " + word)
        return self.of(first) + b"".join([self.known.get(w) or extra[w] for w in words])


def pieces(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", capacity: int = CAPACITY, vocabulary: str | None = None, keep_ids: bool = True) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 (and ids) of every document's pieces.

    Added tokens of the vocabulary are found inside texts. Ids end with END_ID; a null text counts as empty, so every row has one piece
    at least. Longer documents are cut into pieces of ``capacity``; the first is shorter.
    """
    vocabulary = vocabulary or default_vocabulary()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = worker_cache("encoders")
        if vocabulary not in cache:
            cache[vocabulary] = Encoder(vocabulary, added_tokens(vocabulary))
        encoder, end = cache[vocabulary], array("I", [END_ID]).tobytes()
        for batch in batches:
            at, piece, start, length, crc, ids = [], array("i"), array("q"), array("q"), array("q"), []
            for row, text in enumerate(batch.column(1)):
                data = encoder.encode(text.as_py() or "") + end
                n = len(data) // 4
                begin, stop = 0, n % capacity or min(n, capacity)
                while begin < n:
                    part = data[4 * begin : 4 * stop]
                    at.append(row)
                    piece.append(-(-(begin) // capacity))
                    start.append(begin)
                    length.append(stop - begin)
                    crc.append(zlib.crc32(part))
                    if keep_ids:
                        ids.append(np.frombuffer(part, "<i4"))
                    begin, stop = stop, stop + capacity
            columns = [batch.column(0).take(pa.array(at, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())]
            names = ["doc_id", "piece", "start", "length", "ids_crc32"]
            if keep_ids:
                columns.append(pa.array(ids, pa.list_(pa.int32())))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(columns, names=names)

    kind = docs.schema[doc_id].dataType.simpleString()
    schema = f"doc_id {kind}, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * keep_ids
    return docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, schema)


def fullest(counts: Mapping[int, int], capacity: int) -> dict[int, int]:
    """The largest length, with the lengths beside it that leave the least slack: length to times."""
    largest = max(counts)
    room = capacity - largest
    reach, steps = 1, []
    for length in sorted((x for x in counts if x <= room), reverse=True):
        left, take = min(counts[length] - (length == largest), room // length), 1
        while left > 0 and not reach >> room & 1:
            take = min(take, left)
            steps.append((length, take, reach))
            reach |= reach << take * length
            reach &= (2 << room) - 1
            left, take = left - take, take * 2
        if reach >> room & 1:
            break
    used, total = {largest: 1}, reach.bit_length() - 1
    for length, take, before in reversed(steps):
        if not before >> total & 1:
            used[length] = used.get(length, 0) + take
            total -= take * length
    return used


def plan_bins(histogram: Mapping[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int, int]]:
    """(length, low, high, times, bin, offset): of the items of that length, those of ranks low to
    high - 1 go ``times`` to each bin, from ``bin`` on, the first of them at ``offset``."""
    left, done = {k: v for k, v in histogram.items() if v}, dict.fromkeys(histogram, 0)
    out, at = [], 0
    while left:
        used = fullest(left, capacity)
        repeats = min(left[k] // n for k, n in used.items())
        offset = 0
        for length in sorted(used, reverse=True):
            n = used[length]
            out.append((length, done[length], done[length] + repeats * n, n, at, offset))
            done[length] += repeats * n
            left[length] -= repeats * n
            if not left[length]:
                del left[length]
            offset += n * length
        at += repeats
    return out


def pack(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", capacity: int = CAPACITY, vocabulary: str | None = None, keep_ids: bool = True) -> DataFrame:
    """The rows of :func:`pieces` with sequence_id and offset.

    Full pieces are sequences of their own (odd numbers), bins of shorter ones
    have even numbers. Equal documents and repeated rows each have their place.
    """
    spark = docs.sparkSession
    cut = written(pieces(docs, text, doc_id, capacity, vocabulary, keep_ids).withColumn("row", F.monotonically_increasing_id()), "pieces")
    short = cut.where(F.col("length") < capacity)
    histogram = {r["length"]: r["n"] for r in short.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most capacity - 1 rows
    plan = plan_bins(histogram, capacity)
    ranges: dict[int, int] = {}
    for length, *_ in plan:
        ranges[length] = ranges.get(length, 0) + 1
    grain = {k: -(-histogram[k] // n) for k, n in ranges.items()}  # ranks to a block, so that blocks hold few ranges each
    blocks = [(x[0], b, *map(int, x[1:])) for x in plan for b in range(x[1] // grain[x[0]], (x[2] - 1) // grain[x[0]] + 1)]
    bins = spark.createDataFrame(blocks, "length long, block long, low long, high long, times long, bin long, first long")
    grains = spark.createDataFrame(list(grain.items()), "length long, grain long")
    salts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    places = ranked(short.select("row", "length"), ["length"], ["row"], "rank", salts)
    places = places.join(F.broadcast(grains), "length").withColumn("block", F.floor(F.col("rank") / F.col("grain")))
    at = F.col("rank") - F.col("low")
    places = places.join(F.broadcast(bins), ["length", "block"]).where("rank >= low and rank < high").select(
        "row", (2 * (F.col("bin") + F.floor(at / F.col("times")))).alias("sequence_id"), (F.col("first") + at % F.col("times") * F.col("length")).alias("offset")
    )
    columns = [c for c in cut.columns if c != "row"]
    whole = cut.where(F.col("length") >= capacity).select(*columns, (2 * F.col("row") + 1).alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    return whole.unionByName(short.join(places, "row").select(*columns, "sequence_id", "offset"))
