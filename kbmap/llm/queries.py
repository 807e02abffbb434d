"""The registered queries of this subpackage and their DuckDB equivalents where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import embdedup, mixing, pieces, pii, quality, simhash, sstable, toxicity, urlfilter, warc

from .common import Cut


def _read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def _tokenizer(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_sstable_token_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sstable.round_trip(_read(spark, sf_dir, "documents"), _tokenizer("word_bpe_49k.json"), end_id=2)


def op2_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlfilter.judge(_read(spark, sf_dir, "pages"))


def op3_pii_deobfuscation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.detect(_read(spark, sf_dir, "documents"))


def op4_toxicity_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.classify(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "labels"))


def op6_archive_converter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.convert_pages(_read(spark, sf_dir, "pages")).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op7_sentencepiece_lattice(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.encode(_read(spark, sf_dir, "documents"), _tokenizer("piece_bpe_32k.model"))


def op8_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embdedup.near_duplicates(_read(spark, sf_dir, "embeddings"))


def op9_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    weighed = mixing.weigh(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "embeddings"))
    cut = Cut(spark)
    drawn = mixing.sample(cut, cut(weighed))
    return drawn.select("doc_id", "source", "lang", "topic", "n_tokens", F.round("weight", 6).alias("weight"), F.round("probability", 6).alias("probability"), "kept")


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(_read(spark, sf_dir, "documents")).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"
    )


def _op5_sql() -> str:
    stop = ", ".join(f"'{x}'" for w in quality.STOP_WORDS for x in (w, w.capitalize()))
    rules = " AND ".join(
        cond
        for r in quality.RULES
        for cond in (
            *([f"{r.numerator} * 100 >= {r.denominator} * {float(r.low)}"] if r.low is not None else []),
            *([f"{r.numerator} * 100 <= {r.denominator} * {float(r.high)}"] if r.high is not None else []),
        )
    )
    return f"""
WITH d AS (
  SELECT doc_id, coalesce(text, '') AS text,
         list_filter(string_split_regex(coalesce(text, ''), '[ \\t\\n\\x0B\\f\\r]+'), lambda w: w <> '') AS w,
         list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^ \\t\\n\\x0B\\f\\r]')) AS l
  FROM documents),
g AS (
  SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, w[i], w[i + 1], w[i + 2]) AS n
  FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM d)),
r AS (
  SELECT doc_id, count(DISTINCT i + k) AS n_repeat_words
  FROM (SELECT doc_id, i, unnest([0, 1, 2]) AS k FROM g WHERE n > 1) GROUP BY doc_id),
m AS (
  SELECT doc_id, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars,
         length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
         len(l)::BIGINT AS n_lines, (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines,
         len(list_distinct(list_filter(w, lambda x: x IN ({stop}))))::BIGINT AS n_stop_words,
         ((length(text) - length(replace(text, '!!', ''))) // 2)::BIGINT AS n_shouts, 1 AS one,
         coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words
  FROM d LEFT JOIN r USING (doc_id))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND {rules} AS kept
FROM (SELECT *, (n_words < {quality.MIN_WORDS} OR 100 * n_repeat_words > {quality.MAX_REPEAT_PERCENT} * n_words) AS base_failed FROM m)
"""


def op10_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(_read(spark, sf_dir, "documents"), n=3)
    return found.select("doc_id", simhash.hex_fingerprint(F.col("fp")).alias("fingerprint"), "component_id")


def queries() -> dict:
    return {f.__name__: f for f in (
        op1_sstable_token_shards, op2_url_filter, op3_pii_deobfuscation, op4_toxicity_chain, op5_quality_rules,
        op6_archive_converter, op7_sentencepiece_lattice, op8_embedding_near_dedup, op9_source_mixing, op10_simhash_near_dedup,
    )}


#: Archives: what the records say must be what the pages say.
_OP6_SQL = """
WITH p AS (
  SELECT page_id, coalesce(html, '') AS html, octet_length(encode(coalesce(html, '')))::BIGINT AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages),
g AS (SELECT payload_digest, min(page_id) AS first, count(*) AS n FROM p WHERE payload_bytes >= 100 GROUP BY 1)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN n > 1 AND page_id <> first THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN n > 1 AND page_id <> first THEN first END AS refers_to
FROM p LEFT JOIN g USING (payload_digest)
"""

#: All pairs of vectors by exact cosine; components by repeated minima.
_OP8_SQL = """
WITH RECURSIVE v AS (
  SELECT vec_id, embedding::DOUBLE[] AS e, sqrt(list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x))) AS n FROM embeddings),
l AS (
  SELECT a.vec_id AS x, b.vec_id AS y FROM v a JOIN v b ON a.vec_id <> b.vec_id AND a.n > 0 AND b.n > 0
  WHERE list_dot_product(a.e, b.e) >= 0.9 * a.n * b.n),
r AS (SELECT vec_id AS s, vec_id AS t FROM v UNION SELECT r.s, l.y FROM r JOIN l ON r.t = l.x)
SELECT v.vec_id, (SELECT count(*) FROM l WHERE l.x = v.vec_id)::BIGINT AS n_links, c.m AS component_id, v.vec_id = c.m AS kept
FROM v JOIN (SELECT s, min(t) AS m FROM r GROUP BY s) c ON c.s = v.vec_id
"""


def _op9_sql() -> str:
    dims = mixing.DIMENSIONS
    steps = ["w0 AS (SELECT c.*, tokens / (SELECT sum(tokens) FROM c) AS share, tokens / (SELECT sum(tokens) FROM c) AS raked, " + ", ".join(f"t_{d}.target AS target_{d}" for d in dims) + " FROM c " + " ".join(f"JOIN t_{d} USING ({d})" for d in dims) + ")"]
    k = 0
    for _ in range(mixing.ROUNDS):
        for d in dims:
            steps.append(f"w{k + 1} AS MATERIALIZED (SELECT * REPLACE (raked * target_{d} / sum(raked) OVER (PARTITION BY {d}) AS raked) FROM w{k})")
            k += 1
    targets = ",\n".join(
        f"t_{d} AS (SELECT {d}, x / sum(x) OVER () AS target FROM (SELECT {d}, pow(sum(tokens), {mixing.TEMPERATURE}) AS x FROM c GROUP BY {d}))" for d in dims
    )
    return f"""
WITH topics AS (SELECT vec_id AS doc_id, min(label)::VARCHAR AS topic FROM embeddings GROUP BY 1),
d AS (
  SELECT doc_id, coalesce(source, '(none)') AS source, coalesce(lang, '(none)') AS lang, coalesce(topic, '(none)') AS topic,
         len(list_filter(string_split_regex(coalesce(text, ''), '[ \\t\\n\\x0B\\f\\r]+'), lambda w: w <> ''))::BIGINT AS n_tokens
  FROM documents LEFT JOIN topics USING (doc_id)),
c AS (SELECT source, lang, topic, sum(n_tokens)::DOUBLE AS tokens FROM d GROUP BY ALL HAVING sum(n_tokens) > 0),
{targets},
{", ".join(steps)},
p AS (SELECT source, lang, topic, raked / share AS weight, raked / share / max(raked / share) OVER () AS probability FROM w{k})
SELECT doc_id, source, lang, topic, n_tokens, round(coalesce(weight, 0.0), 6) AS weight, round(coalesce(probability, 0.0), 6) AS probability,
       ('0x' || substr(md5(doc_id::VARCHAR || ':7'), 1, 8))::BIGINT / 4294967296.0::DOUBLE < coalesce(probability, 0.0) AS kept
FROM d LEFT JOIN p USING (source, lang, topic)
"""


def oracle_sql() -> dict[str, str]:
    return {"op5_quality_rules": _op5_sql(), "op6_archive_converter": _OP6_SQL, "op8_embedding_near_dedup": _OP8_SQL, "op9_source_mixing": _op9_sql()}
