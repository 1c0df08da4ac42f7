"""The queries of the training-data operators, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from symseek.llm import decontaminate, html_extract, langid, media_ts, ngram_join, quality, sharding, sp_sampling, substring_dedup, token_counts
from symseek.llm.common import crc_bucket, table, written


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held_out = crc_bucket(F.col("doc_id"), 3) == 1
    model = langid.train(docs, ~held_out)
    return langid.identify(docs, model, keep={"held_out": held_out}).select("doc_id", "held_out", "lang_pred", "score")


def op2_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    held_out = crc_bucket(F.col("doc_id"), 5) == 0
    model = quality.train(docs, labels, ~held_out)
    scored = quality.score(docs, model, keep={"held_out": held_out})
    return scored.select("doc_id", "held_out", "score", (F.col("score") >= quality.ACCEPT).cast("int").alias("predicted"))


def op3_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = sharding.assign_shards(table(spark, sf_dir, "documents"), [1.0] * 8)
    return rows.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per document and benchmark item that it holds."""
    rows = decontaminate.find_items(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return rows.select("doc_id", "item_id", "similarity", "bits_apart", "first_word", "n_words")


def op5_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extract(table(spark, sf_dir, "pages")).select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"), "n_differenced", "n_by_markup")


def op6_sentencepiece_sampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = sp_sampling.sample(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "draw", F.size("token_ids").alias("n_tokens"), F.xxhash64("token_ids").alias("ids_xxhash64"), "log_prob", "perturbed", "inclusion", "restored")


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Totals after three batches over all documents: all inserted; exact copies of a smaller doc_id deleted; of the
    rest, those that repeat a line revised to each line once. Every batch is committed twice, which must count once.

    Copies are counted by text, source and language before they are shuffled, so a large group of them is a few rows."""
    docs = table(spark, sf_dir, "documents")
    alive = written(token_counts.with_counts(docs.select("doc_id", "source", "lang", "text", F.md5(F.coalesce("text", F.lit("")).cast("binary")).alias("digest")), keep=("doc_id", "source", "lang", "digest")), "token-counts")
    groups = alive.groupBy("digest", "source", "lang", "n_tokens", "n_bytes").agg(F.count("doc_id").alias("n"), F.min("doc_id").alias("lowest"))
    first = groups.groupBy("digest").agg(F.min("lowest").alias("first_id"))
    extra = F.col("n") - (F.col("lowest") == F.col("first_id")).cast("long")
    copies = groups.join(first, "digest").where(extra > 0).withColumn("extra", extra)
    once = F.array_join(F.array_distinct(F.split("text", "\n")), "\n")
    new = token_counts.with_counts(docs.where(F.length("text") > F.length(once)).select("doc_id", "source", "lang", once.alias("text")))
    olds = alive.select("doc_id", "source", "lang", F.col("n_tokens").alias("old_tokens"), F.col("n_bytes").alias("old_bytes"))
    originals = new.select("doc_id", "n_tokens", "n_bytes").join(first.select(F.col("first_id").alias("doc_id")), "doc_id", "left_semi")
    renewed = written(olds.join(originals, "doc_id"), "token-revisions")
    old = renewed.select("doc_id", "source", "lang", F.col("old_tokens").alias("n_tokens"), F.col("old_bytes").alias("n_bytes"))
    rollup = token_counts.new_rollup(spark)
    batches = {"inserts": token_counts.changes(alive, +1), "copies": token_counts.changes(copies, -F.col("extra")), "lines-once": token_counts.revisions(old, renewed)}
    for batch_id, signed in batches.items():
        rollup.commit(batch_id, signed)
    for batch_id, signed in batches.items():
        rollup.commit(batch_id, signed)
    return rollup.totals()


def op8_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = substring_dedup.remove_repeats(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept").cast("binary"), 256).alias("kept_sha256"))


def op9_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    read = media_ts.read_media(media_ts.store_texts(table(spark, sf_dir, "documents")))
    feature = F.format_string("pts=%d..%d;pes=%d;rap=%d;packets=%d;cc=%d", F.col("timestamps")[0], F.element_at("timestamps", -1), F.size("timestamps"), F.size("random_access"), F.col("packets"), F.col("continuity_errors"))
    return read.select(
        "doc_id", "n_bytes", F.octet_length("payload").cast("long").alias("payload_bytes"), F.sha2("payload", 256).alias("payload_sha256"), "tail_crc32", "media_bytes", "media_sha256", feature.alias("feature")
    )


def op10_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.near_copies(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, f in globals().items() if name.startswith("op") and callable(f)}


#: op3: the same digests and ranks; the checksum of the text byte by byte from the reflected polynomial.
OP3_SQL = """
WITH RECURSIVE crc_bits AS (
  SELECT i AS b, i::BIGINT AS c, 0 AS step FROM range(256) t(i)
  UNION ALL
  SELECT b, CASE WHEN c & 1 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END, step + 1 FROM crc_bits WHERE step < 8
),
crc_table AS (SELECT list(c ORDER BY b) AS t FROM crc_bits WHERE step = 8),
draws AS (
  SELECT doc_id, s, -1.0 / ln((('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null') || ':' || s), 1, 13))::BIGINT + 0.5) / 4503599627370496.0) AS score
  FROM (SELECT DISTINCT doc_id FROM documents), range(9) r(s)
),
placed AS (
  SELECT doc_id, arg_max(s, score) FILTER (WHERE s < 8) AS shard, arg_max(s, score) AS grown_shard FROM draws GROUP BY doc_id
),
bytes AS (
  SELECT doc_id, strlen(coalesce(text, '')) AS n, hex(encode(coalesce(text, ''))) AS h FROM documents
),
sums AS (
  SELECT doc_id, n, xor(4294967295, list_reduce([4294967295::BIGINT] || list_transform(range(n), lambda i: ('0x' || substr(h, (2 * i + 1)::BIGINT, 2))::BIGINT),
         lambda c, b: xor(c >> 8, t[(xor(c, b) & 255) + 1]))) AS crc
  FROM bytes, crc_table
)
SELECT s.doc_id, (s.n + 1)::BIGINT AS size, s.crc::BIGINT AS text_crc32, 'key' AS law, p.shard::INTEGER AS shard,
       (row_number() OVER (PARTITION BY p.shard ORDER BY ('0x' || substr(md5(coalesce(s.doc_id::VARCHAR, 'null') || ':g'), 1, 8))::BIGINT % 4096, s.doc_id, s.crc, s.n) - 1)::BIGINT AS slot,
       p.grown_shard::INTEGER AS grown_shard
FROM sums s JOIN placed p ON s.doc_id = p.doc_id
"""


#: op8: every window as a string, its smallest document, and the words that no later document's window covers.
OP8_SQL = r"""
WITH w AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents
),
win AS (
  SELECT doc_id, i, array_to_string(ws[i : i + 49], ' ') AS s FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 48)) AS i FROM w)
),
firsts AS (SELECT s, min(doc_id) AS lo FROM win GROUP BY s HAVING count(DISTINCT doc_id) > 1),
covered AS (
  SELECT DISTINCT doc_id, unnest(range(i, i + 50)) AS pos FROM win JOIN firsts USING (s) WHERE lo < doc_id
),
words AS (SELECT doc_id, unnest(ws) AS word, unnest(range(1, len(ws) + 1)) AS pos FROM w),
kept AS (
  SELECT doc_id, count(*) AS n, string_agg(word, ' ' ORDER BY pos) AS text FROM words ANTI JOIN covered USING (doc_id, pos) GROUP BY doc_id
)
SELECT w.doc_id, len(ws)::BIGINT AS n_words, (len(ws) - coalesce(n, 0))::BIGINT AS n_removed, sha256(coalesce(text, '')) AS kept_sha256
FROM w LEFT JOIN kept ON w.doc_id = kept.doc_id
"""


#: op10: all pairs with a common shingle, and the smallest document reachable over links.
OP10_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents
),
grams AS (
  SELECT DISTINCT doc_id, array_to_string(ws[i : i + 2], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 1, 2))) AS i FROM w WHERE len(ws) > 0)
),
sizes AS (SELECT doc_id, count(*) AS n FROM grams GROUP BY doc_id),
links AS (
  SELECT a.doc_id AS x, b.doc_id AS y FROM grams a JOIN grams b ON a.g = b.g AND a.doc_id <> b.doc_id
  JOIN sizes m ON m.doc_id = a.doc_id JOIN sizes k ON k.doc_id = b.doc_id WHERE 100 * least(m.n, k.n) >= 90 * greatest(m.n, k.n)
  GROUP BY a.doc_id, b.doc_id, m.n, k.n HAVING 100 * count(*) >= 90 * (m.n + k.n - count(*))
),
reach AS (
  SELECT doc_id AS x, doc_id AS y FROM w UNION SELECT r.x, l.y FROM reach r JOIN links l ON r.y = l.x
)
SELECT w.doc_id, coalesce(s.n, 0)::BIGINT AS n_shingles, (SELECT min(y) FROM reach WHERE reach.x = w.doc_id) AS component_id
FROM w LEFT JOIN sizes s ON s.doc_id = w.doc_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op3_sharding": OP3_SQL, "op8_substring_dedup": OP8_SQL, "op10_ngram_jaccard_join": OP10_SQL}
