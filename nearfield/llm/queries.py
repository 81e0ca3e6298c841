"""The operators' queries over the given tables, and their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import block_search, fingerprints, jaccard_groups, language, line_dedup, mixing, pieces, token_files, toxicity, warc

#: The chain's categories in order: name, and the label column and value that mean it.
CATEGORIES = {"low_quality": ("quality", 0), "toxic": ("toxic", 1)}


def tokenizer_path(name: str) -> str:
    """Place of a public vocabulary file; another folder's path may be given to the operators instead."""
    import public_tokenizers

    return public_tokenizers.path(name)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_toxicity_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    chain = toxicity.learn(docs, table(spark, sf_dir, "labels"), CATEGORIES)
    return toxicity.predict(docs.select("doc_id", "text"), chain).select("doc_id", "p_low_quality", "p_toxic", F.col("is_toxic").alias("toxic"))


def op2_elias_fano_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.token_table(table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"))


def op3_sainte_lague_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op4_block_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return block_search.nearest(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 100 == 0)


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    kept = line_dedup.dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return kept.select("doc_id", "n_lines", "n_dropped", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def op6_unigram_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.encode_pieces(table(spark, sf_dir, "documents"), tokenizer_path("piece_bpe_32k.model"), with_ids=False)


def op7_minhash_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.edited_fingerprints(table(spark, sf_dir, "documents"))


def op8_language_centroids(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(False))
    model = language.learn(docs, ~held_out)
    found = language.identify(docs, model)
    return found.withColumn("held_out", held_out).select("doc_id", "held_out", "lang_pred", "score", "rejected")


def op9_warc_transactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.digest_rows(warc.captures(table(spark, sf_dir, "pages")))


def op10_jaccard_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_groups.jaccard_components(table(spark, sf_dir, "documents"), words=3, percent=90).select("doc_id", "n_shingles", "component_id", "n_links")


def near_pairs_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Beside op7: near-duplicate pairs of its signatures' bands, joined in Spark and verified by exact Jaccard."""
    return fingerprints.near_pairs(table(spark, sf_dir, "documents")).select("a", "b", F.round("jaccard", 6).alias("jaccard"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_toxicity_chain, op2_elias_fano_tokens, op3_sainte_lague_mix, op4_block_nearest, op5_line_dedup, op6_unigram_pieces, op7_minhash_fingerprints, op8_language_centroids, op9_warc_transactions, op10_jaccard_groups, pipeline, near_pairs_minhash)}

_MIX = r"""
WITH sized AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
         md5(concat_ws('|', 'mix', coalesce(doc_id::VARCHAR, 'null'))) AS place
  FROM documents),
by_source AS (
  SELECT source, sum(size)::BIGINT AS source_size FROM sized GROUP BY source),
weighed AS (
  SELECT *, source_size * 2.0::DOUBLE AS cap,
         CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 3.0::DOUBLE WHEN 1 THEN 1.0::DOUBLE ELSE 2.0::DOUBLE END AS weight
  FROM by_source),
levels AS (
  SELECT *, ((SELECT sum(source_size)::DOUBLE * 1.5 FROM by_source)
             - coalesce(sum(cap) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
            / sum(weight) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level
  FROM weighed),
targets AS (
  SELECT source, source_size,
         least(cap, weight * (SELECT max(level) FROM levels)) AS target
  FROM levels),
quotients AS (
  SELECT source, k, row_number() OVER (ORDER BY target / (2 * k + 1) DESC, source NULLS LAST, k) AS place
  FROM targets, LATERAL (SELECT unnest(range(0, (target / 32)::BIGINT + 40)) AS k) WHERE target > 0),
quotas AS (
  SELECT t.source, source_size, target, greatest(1, least(8192, ceil(source_size / 262144)))::BIGINT AS shards,
         (SELECT count(*) FROM quotients q WHERE q.source IS NOT DISTINCT FROM t.source
            AND q.place <= (SELECT round(sum(target) / 32) FROM targets))::BIGINT AS quota
  FROM targets t),
dealt AS (
  SELECT doc_id, s.source, size, place, source_size, target, quota,
         ('0x' || substr(reverse(place), 1, 12))::BIGINT % shards AS shard
  FROM sized s JOIN quotas q ON s.source IS NOT DISTINCT FROM q.source),
held AS (
  SELECT source, shard, sum(size)::BIGINT AS words, any_value(quota) AS seats FROM dealt GROUP BY source, shard),
held_quotients AS (
  SELECT source, shard, k, row_number() OVER (PARTITION BY source ORDER BY words / (2 * k + 1) DESC, shard, k) AS place
  FROM held, LATERAL (SELECT unnest(range(0, (seats + 1)::BIGINT)) AS k) WHERE words > 0),
held_quotas AS (
  SELECT source, shard, words, least(32 * (SELECT count(*) FROM held_quotients q
           WHERE q.source IS NOT DISTINCT FROM h.source AND q.shard = h.shard AND q.place <= h.seats), 2 * words)::BIGINT AS want,
         ('0x' || substr(md5(concat_ws('|', 'mix', coalesce(source, 'null'), shard::VARCHAR)), 1, 12))::BIGINT
           % greatest(ceil(words / 32)::BIGINT, 1) * 32 AS from_word
  FROM held h),
placed AS (
  SELECT d.*, h.words, h.from_word,
         CASE WHEN words > 0 THEN want // words ELSE 0 END AS passes,
         CASE WHEN words > 0 THEN want % words ELSE 0 END AS rest,
         sum(size) OVER (PARTITION BY d.source, d.shard ORDER BY place, doc_id NULLS LAST, size ROWS UNBOUNDED PRECEDING)::BIGINT AS after
  FROM dealt d JOIN held_quotas h ON d.source IS NOT DISTINCT FROM h.source AND d.shard = h.shard)
SELECT doc_id, size, source_size, target,
       (passes * size + greatest(0, least(after, from_word + rest) - greatest(after - size, from_word))
        + greatest(0, least(after + words, from_word + rest) - greatest(after - size + words, from_word)))::BIGINT AS taken
FROM placed
"""

_NEAREST = """
WITH usable AS (
  SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
    AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
pairs AS (
  SELECT q.vec_id AS query_id, c.vec_id,
         sqrt(list_reduce(list_transform(list_zip(q.v, c.v), lambda p: (p[1] - p[2]) * (p[1] - p[2])), lambda a, b: a + b)) AS score
  FROM usable q JOIN usable c ON q.vec_id <> c.vec_id AND len(q.v) = len(c.v) WHERE q.vec_id % 100 = 0)
SELECT query_id, rank::INTEGER AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score, vec_id) AS rank FROM pairs) WHERE rank <= 10
"""

_LINES = r"""
WITH lines AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos
  FROM documents),
keyed AS (
  SELECT *, translate(trim(line, E' \t\n\x0B\x0C\r'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
  FROM lines),
shared AS (
  SELECT key, max(doc_id) AS keeper FROM keyed WHERE length(key) >= 20 GROUP BY key HAVING count(DISTINCT doc_id) >= 3)
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (WHERE keeper IS NOT NULL AND keeper <> doc_id)::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE keeper IS NULL OR keeper = doc_id), '')) AS kept_sha256
FROM keyed LEFT JOIN shared USING (key) GROUP BY doc_id
"""

_WARC = """
WITH bodies AS (
  SELECT page_id, octet_length(encode(coalesce(html, '')))::BIGINT AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest FROM pages),
best AS (
  SELECT *, CASE WHEN payload_bytes >= 1000 THEN max(page_id) OVER (PARTITION BY payload_digest) ELSE page_id END AS original FROM bodies)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN original = page_id THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN original <> page_id THEN original END AS refers_to
FROM best
"""

_JACCARD = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w
  FROM documents),
shingles AS (
  SELECT DISTINCT doc_id, CASE WHEN len(w) < 3 THEN array_to_string(w, ' ') ELSE array_to_string(w[i:i + 2], ' ') END AS s
  FROM words, LATERAL (SELECT unnest(range(1, greatest(len(w) - 2, 1) + 1)) AS i) WHERE len(w) > 0),
sizes AS (SELECT doc_id, count(*)::BIGINT AS n FROM shingles GROUP BY doc_id),
common AS (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS m FROM shingles a JOIN shingles b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY 1, 2),
links AS (
  SELECT a, b FROM common JOIN sizes x ON a = x.doc_id JOIN sizes y ON b = y.doc_id WHERE 100 * m >= 90 * (x.n + y.n - m)),
reach AS (
  SELECT doc_id AS node, doc_id AS r FROM documents
  UNION
  SELECT reach.node, links.b FROM reach JOIN links ON reach.r = links.a)
SELECT node AS doc_id, coalesce(n, 0)::BIGINT AS n_shingles, min(r) AS component_id,
       (SELECT count(*) FROM links WHERE a = node)::BIGINT AS n_links
FROM reach LEFT JOIN sizes ON node = sizes.doc_id GROUP BY 1, 2
"""

_NEAR = r"""
WITH words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w
  FROM documents),
shingles AS (
  SELECT DISTINCT doc_id, CASE WHEN len(w) < 5 THEN array_to_string(w, ' ') ELSE array_to_string(w[i:i + 4], ' ') END AS s
  FROM words, LATERAL (SELECT unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS i) WHERE len(w) > 0),
sets AS (SELECT doc_id, count(*)::BIGINT AS n, md5(string_agg(s, chr(10) ORDER BY s)) AS k FROM shingles GROUP BY doc_id),
reps AS (SELECT min(doc_id) AS doc_id, any_value(n) AS n FROM sets GROUP BY k),
own AS (SELECT doc_id, s FROM shingles SEMI JOIN reps USING (doc_id)),
common AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS m FROM own x JOIN own y ON x.s = y.s AND x.doc_id < y.doc_id GROUP BY 1, 2)
SELECT a, b, round(m::DOUBLE / (x.n + y.n - m), 6) AS jaccard
FROM common JOIN reps x ON a = x.doc_id JOIN reps y ON b = y.doc_id WHERE m::DOUBLE / (x.n + y.n - m) >= 0.8
"""

ORACLES = {"near_pairs_minhash": _NEAR, "op3_sainte_lague_mix": _MIX, "op4_block_nearest": _NEAREST, "op5_line_dedup": _LINES, "op9_warc_transactions": _WARC, "op10_jaccard_groups": _JACCARD}
