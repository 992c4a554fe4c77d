"""Language identification, word first with back-off to shorter character n-grams.

Training counts words and character n-grams by language. A known word scores
its log relative frequency in each language; a word that no language knows is
cut into its longest n-grams, and if none of these is known, into shorter ones,
down to single characters. A document's score for a language is the sum over
its words; the posterior is their softmax.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import by_value, id_remainder

by_value(__name__)

#: Documented bound of the model: documents learned from, by language (expected number; whole texts).
#: Every word and n-gram that stands in them is known.
SAMPLE_PER_LANGUAGE = 1500
LONGEST = 5
#: What stands for the probability of an entry that a language lacks.
MISSING = -16.0
UNKNOWN = "und"
#: A run of letters; white space, digits, marks of punctuation and "_" end it.
LETTERS = re.compile(r"[^\W\d_]+")
#: Memory bound of the cache of scored unseen words.
CACHE = 100_000


def grams(word: str, n: int) -> list[str]:
    padded = f" {word} " if n > 1 else word
    return [padded[i : i + n] for i in range(len(padded) - n + 1)]


def count_tokens(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(lang, text) to (lang, n, token, count); n = 0 stands for a word. Emits early when large."""
    schema = pa.schema([("lang", pa.string()), ("n", pa.int32()), ("token", pa.string()), ("count", pa.int64())])
    counts: Counter = Counter()

    def flush():
        keys = list(counts)
        out = pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.string()), pa.array([k[1] for k in keys], pa.int32()), pa.array([k[2] for k in keys], pa.string()), pa.array(counts.values(), pa.int64())], schema=schema)
        counts.clear()
        return out

    for batch in batches:
        for lang, text in zip(batch.column(0).to_pylist(), batch.column(1)):
            for word, c in Counter(LETTERS.findall((text.as_py() or "").lower())).items():
                counts[lang, 0, word] += c
                for n in range(1, LONGEST + 1):
                    for g in grams(word, n):
                        counts[lang, n, g] += c
            if len(counts) > 100_000:
                yield flush()
    if counts:
        yield flush()


class Model:
    """``words`` and ``grams``: token to a tuple of log frequencies, one a language."""

    def __init__(self, langs: list[str], words: dict, grams_by_length: list[dict]):
        self.langs, self.words, self.grams = langs, words, grams_by_length

    def unseen(self, word: str) -> tuple:
        for n in range(LONGEST, 0, -1):
            known = [g for g in map(self.grams[n].get, grams(word, n)) if g]
            if known:
                return tuple(sum(x) / len(known) for x in zip(*known))
        return (0.0,) * len(self.langs)

    def predict(self, text: str | None, cache: dict) -> tuple[str, float]:
        counts = Counter(LETTERS.findall(text.lower())) if text else {}
        if not self.langs or not any(c.isalpha() for word in counts for c in word):  # numerals are no letters
            return UNKNOWN, 0.0
        total = [0.0] * len(self.langs)
        for word, c in counts.items():
            logs = self.words.get(word) or cache.get(word)
            if logs is None:
                if len(cache) >= CACHE:
                    cache.clear()
                logs = cache[word] = self.unseen(word)
            for i, x in enumerate(logs):
                total[i] += c * x
        best = max(range(len(total)), key=lambda i: (total[i], -i))
        return self.langs[best], 1 / sum(math.exp(max(-700.0, x - total[best])) for x in total)


def train(docs: DataFrame, learn: Column, text: str = "text", lang: str = "lang", doc_id: str = "doc_id", sample: int = SAMPLE_PER_LANGUAGE) -> Model:
    """Counts over whole texts of about ``sample`` documents a language among those that
    ``learn`` admits, chosen by a hash of the id. Languages with fewer give all they have."""
    rows = docs.where(learn & F.col(lang).isNotNull() & F.col(text).isNotNull()).select(F.col(lang).alias("lang"), F.col(text).alias("text"), F.pmod(F.xxhash64(F.col(doc_id), F.lit("language")), F.lit(1 << 30)).alias("u"))
    sizes = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not sizes:
        return Model([], {}, [{} for _ in range(LONGEST + 1)])
    bound = F.create_map(*[x for k, n in sizes.items() for x in (F.lit(k), F.lit(min(1 << 30, int((1 << 30) * sample / n))))])
    chosen = rows.where(F.col("u") < bound[F.col("lang")]).select("lang", "text")
    counts = chosen.mapInArrow(count_tokens, "lang string, n int, token string, count long").groupBy("lang", "n", "token").agg(F.sum("count").alias("count"))
    totals = counts.groupBy("lang", "n").agg(F.sum("count").alias("total"))
    kept = counts.join(F.broadcast(totals), ["lang", "n"])  # a row for each language and length
    langs = sorted(sizes)
    logs = F.collect_list(F.struct("lang", F.log(F.col("count") / F.col("total")).alias("log")))  # one a language at most
    tables: list[dict] = [{} for _ in range(LONGEST + 1)]
    same: dict[tuple, tuple] = {}  # rare entries share few rows of frequencies, which the workers then share too
    for r in kept.groupBy("n", "token").agg(logs.alias("logs")).toLocalIterator():
        found = dict(r["logs"])
        row = tuple(found.get(x, MISSING) for x in langs)
        tables[r["n"]][r["token"]] = same.setdefault(row, row)
    return Model(langs, tables[0], tables)


def predict(docs: DataFrame, model: Model, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """doc_id, lang_pred, score for every row, over whole texts.

    A null text, or one without a letter, is ``und`` with score 0. Of languages
    that tie the first by name wins. Repeated rows give repeated results.
    """
    shared = docs.sparkSession.sparkContext.broadcast((model.langs, model.words, model.grams))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, cache = Model(*shared.value), {}
        for batch in batches:
            out = [known.predict(t.as_py(), cache) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([x[0] for x in out], pa.string()), pa.array([x[1] for x in out], pa.float64())], names=["doc_id", "lang_pred", "score"])

    kind = docs.schema[doc_id].dataType.simpleString()
    return docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, f"doc_id {kind}, lang_pred string, score double")


def held_out(doc_id: str = "doc_id") -> Column:
    """Rows kept from training: crc32 of the id modulo 5 is 0."""
    return id_remainder(doc_id, 5) == 0


def identify(docs: DataFrame, text: str = "text", lang: str = "lang", doc_id: str = "doc_id") -> DataFrame:
    """Trains on the rows that are not held out and predicts every row."""
    model = train(docs, ~held_out(doc_id), text, lang, doc_id)
    return predict(docs, model, text, doc_id).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")


def keep_identified(docs: DataFrame, text: str = "text", lang: str = "lang", doc_id: str = "doc_id", least: float = 0.5) -> DataFrame:
    """``docs`` without the rows whose language is unknown or less than ``least``
    probable; columns unchanged. One pass: rows carry their own verdict."""
    model = train(docs, ~held_out(doc_id), text, lang, doc_id)
    shared = docs.sparkSession.sparkContext.broadcast((model.langs, model.words, model.grams))
    at = docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, cache = Model(*shared.value), {}
        for batch in batches:
            out = [known.predict(t.as_py(), cache) for t in batch.column(at)]
            yield batch.filter(pa.array([name != UNKNOWN and score >= least for name, score in out], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
