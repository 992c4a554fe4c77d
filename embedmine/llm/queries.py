"""The registered queries of this subpackage, and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import exact_dedup, language, media, mixing, packing, pseudonyms, quality, secrets, sharding, simhash


#: The key of the registered query; users bring their own.
PSEUDONYM_KEY = "example key of the registered query"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(documents(spark, sf_dir), columns=["doc_id", "source", "lang"]).select("doc_id", "source", "lang", F.col("mix_topic").alias("topic"), F.col("mix_tokens").alias("tokens"), F.round("prob", 6).alias("prob"), "chosen")


def op2_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(documents(spark, sf_dir)).select("doc_id", "fingerprint", "component_id")


def op3_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op4_shard_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard(documents(spark, sf_dir))


def op5_secret_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secret_spans(documents(spark, sf_dir))


def op6_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pseudonyms.pseudonymize(documents(spark, sf_dir), key=PSEUDONYM_KEY)


def op7_pack_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir), keep_ids=False)


def op8_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_duplicates(documents(spark, sf_dir))


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.identify(documents(spark, sf_dir))


def op10_ogg_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.media_features(documents(spark, sf_dir))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    all_ = (op1_mix_sources, op2_simhash_near_dedup, op3_quality_classifier, op4_shard_best_fit, op5_secret_ledger, op6_pseudonyms, op7_pack_sequences, op8_exact_dedup, op9_language_id, op10_ogg_media, pipeline)
    return {f.__name__: f for f in all_}


OP8 = r"""
WITH d AS (
  SELECT doc_id, length(coalesce(text, '')) AS chars,
         sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g')) AS h
  FROM documents)
SELECT doc_id, first_value(doc_id) OVER w AS keep_id,
       count(*) OVER (PARTITION BY h) AS group_size,
       row_number() OVER w = 1 AS kept, h AS text_sha256
FROM d WINDOW w AS (PARTITION BY h ORDER BY chars DESC, doc_id NULLS LAST)
"""


def _op1() -> str:
    """Targets within reach, then the raking rounds with their ceiling, written out one after another."""
    parts = [
        f"""k AS MATERIALIZED (SELECT doc_id, source, lang, coalesce(source, '{mixing.NONE}') AS s, coalesce(lang, '{mixing.NONE}') AS l,
          CASE WHEN contains(b, ' | ') THEN 'table' WHEN regexp_matches(b, '[%&*#$]{{3}}') THEN 'markup'
               WHEN contains(b, 'Licensed under') THEN 'licence' WHEN contains(b, '@') THEN 'contact' ELSE 'prose' END AS t,
          greatest(1, CAST(ceil(octet_length(encode(b)) / 4.0) AS BIGINT)) AS tokens,
          CAST(('0x' || substr(md5('{mixing.SEED}:' || coalesce(CAST(doc_id AS VARCHAR), md5(b))), 1, 13)) AS BIGINT) / {float(1 << 52)!r} AS u
        FROM (SELECT doc_id, source, lang, coalesce(text, '') AS b FROM documents))""",
        "c AS MATERIALIZED (SELECT s, l, t, CAST(sum(tokens) AS BIGINT) AS tokens FROM k GROUP BY ALL)",
    ]
    def filled(of: str, weight: str, key: str) -> str:
        """of with prob: weight over tokens, scaled, 1 at most, tokens * prob adding up to the rate. In falling
        order, a row is at 1 if it would exceed 1 with all rows before it at 1."""
        sums = f"sum(tokens) OVER () AS tt, sum({weight}) OVER () AS tw, coalesce(sum(tokens) OVER b, 0) AS bt, coalesce(sum({weight}) OVER b, 0) AS bw"
        rows = f"SELECT *, {weight} / tokens AS f, {sums} FROM {of} WINDOW b AS (ORDER BY {weight} / tokens DESC, {key} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)"
        marked = f"SELECT *, ({mixing.RATE} * tt - bt) * f >= tw - bw AS one FROM ({rows})"
        rest = f"({mixing.RATE} * tt - sum(CASE WHEN one THEN tokens ELSE 0 END) OVER ()) / sum(CASE WHEN one THEN 0 ELSE {weight} END) OVER ()"
        return f"SELECT * EXCLUDE (f, tt, tw, bt, bw, one), CASE WHEN one THEN 1.0 ELSE least(1.0, f * {rest}) END AS prob FROM ({marked})"

    for d in "slt":
        parts.append(f"n{d} AS MATERIALIZED (SELECT {d}, tokens, share / sum(share) OVER () * sum(tokens) OVER () AS want FROM (SELECT {d}, CAST(sum(tokens) AS BIGINT) AS tokens, pow(CAST(sum(tokens) AS DOUBLE), {mixing.TEMPER}) AS share FROM c GROUP BY {d}))")
        parts.append(f"m{d} AS MATERIALIZED (SELECT {d}, prob * tokens / {mixing.RATE} AS give_{d} FROM ({filled(f'n{d}', 'want', d)}))")
    parts.append("r0 AS MATERIALIZED (SELECT s, l, t, tokens, CAST(tokens AS DOUBLE) AS w, give_s, give_l, give_t FROM c JOIN ms USING (s) JOIN ml USING (l) JOIN mt USING (t))")
    n = 0
    for _ in range(mixing.ROUNDS):
        for d in "slt":
            parts.append(f"r{n + 1} AS MATERIALIZED (SELECT * REPLACE (least(w * give_{d} / sum(w) OVER (PARTITION BY {d}), tokens / {mixing.RATE}) AS w) FROM r{n})")
            n += 1
    parts.append(f"p AS MATERIALIZED ({filled(f'r{n}', 'w', 's, l, t')})")
    return "WITH " + ",\n".join(parts) + "\nSELECT doc_id, source, lang, t AS topic, k.tokens, round(CAST(prob AS DOUBLE), 6) AS prob, u < prob AS chosen FROM k JOIN p USING (s, l, t)"


def _op5() -> str:
    """Places of the matches from the pieces between them, as list functions."""
    ctes = ["d AS (SELECT doc_id, coalesce(text, '') AS b FROM documents)"]
    for rank, r in enumerate(secrets.RULES):
        pattern = r.pattern.replace("'", "''")
        ctes.append(
            f"""k{rank} AS (SELECT doc_id, {rank} AS rank, '{r.kind}' AS kind, unnest(range(1, len(m) + 1)) AS i, m, g, v
              FROM (SELECT doc_id, regexp_extract_all(b, '{pattern}') AS m, regexp_extract_all(b, '{pattern}', {r.group}) AS v, string_split_regex(b, '{pattern}') AS g FROM d WHERE regexp_matches(b, '{pattern}')))"""
        )
        ctes.append(
            f"""s{rank} AS (SELECT doc_id, rank, kind, CAST(list_sum(list_transform(g[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(m[1:i - 1], lambda x: length(x))), 0) AS BIGINT) AS start, length(m[i]) AS n
              FROM k{rank} WHERE length(v[i]) >= {r.least})"""
        )
    base = ", ".join(f"'{r.kind}'" for r in secrets.RULES if r.base)
    number = ", ".join(f"count(kind) FILTER (kind = '{r.kind}') AS n_{r.kind}" for r in secrets.RULES if r.base)
    ctes.append("s AS (" + " UNION ALL ".join(f"SELECT * FROM s{i}" for i in range(len(secrets.RULES))) + ")")
    ctes.append("p AS (SELECT d.doc_id, rank, kind, start, kind || ':' || start || ':' || (start + n) AS part FROM d LEFT JOIN s ON d.doc_id = s.doc_id)")
    return "WITH " + ",\n".join(ctes) + f"""
SELECT doc_id, {number}, sha256(coalesce(string_agg(part, ',' ORDER BY start, rank) FILTER (kind IN ({base})), '')) AS base_sha256,
       coalesce(string_agg(part, ',' ORDER BY start, rank), '') AS spans
FROM p GROUP BY doc_id"""


def oracle_sql() -> dict[str, str]:
    return {"op5_secret_ledger": _op5(), "op1_mix_sources": _op1(), "op8_exact_dedup": OP8}
