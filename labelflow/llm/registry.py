"""Queries and SQL of the training-data operators, each over its whole table with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from labelflow.llm import chat_format, decontaminate, exact_dedup, language_id, mixing, sharding, simhash, toxicity, web_archive, window_index
from labelflow.llm.common import doc_bucket, table

Query = Callable[[SparkSession, str], DataFrame]


def op1_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def op2_web_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    return web_archive.round_trip(table(spark, sf_dir, "pages")).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op3_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(table(spark, sf_dir, "documents"))


def op4_kd_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = sharding.kd_shards(table(spark, sf_dir, "documents"))
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op5_poisson_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.mix(table(spark, sf_dir, "documents"))  # whole rows are replicated and shuffled; the digest is taken after
    drawn = [F.round("_rate", 9).alias("rate"), F.col("_copies").cast("long").alias("n_copies"), F.col("_copy").cast("long").alias("copy"), F.col("_key").alias("shuffle_key")]
    return mixed.select("doc_id", "source", "lang", "n_chars", *drawn, F.octet_length("text").cast("long").alias("n_bytes"), F.sha2("text", 256).alias("text_sha256"))


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return window_index.substring_dedup(table(spark, sf_dir, "documents"))


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = language_id.train(docs)
    found = language_id.predict(docs.select("doc_id", "text"), model)
    return found.select("doc_id", (doc_bucket("doc_id", 3) == 1).alias("held_out"), F.col("_lang").alias("lang_pred"), F.col("_score").alias("score"))


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    scored = toxicity.score(docs, model)
    return scored.select("doc_id", (doc_bucket("doc_id", 4) == 2).alias("held_out"), F.col("_score").alias("score"), (F.col("_score") >= 0.3).cast("int").alias("predicted"))


def op9_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    odd = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-1, 0, "user", odd), (-1, 1, "assistant", odd)], "conv_id long, turn long, role string, text string")
    return chat_format.read_back(chat_format.format_conversations(rows.unionByName(extra)))


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


SQL_OP1 = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS words FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS words FROM benchmark),
q AS (SELECT DISTINCT item_id, least(10, len(words)) AS n, array_to_string(words[i:i + 9], ' ') AS g FROM (SELECT item_id, words, unnest(range(1, greatest(len(words) - 9, 1) + 1)) AS i FROM b WHERE len(words) > 0)),
sizes AS (SELECT DISTINCT n FROM q),
d AS (SELECT doc_id, n, i, array_to_string(words[i:i + n - 1], ' ') AS g FROM (SELECT doc_id, words, n, unnest(range(1, len(words) - n + 2)) AS i FROM w, sizes)),
hits AS (SELECT doc_id, d.n, i, item_id FROM d JOIN q ON d.g = q.g AND d.n = q.n),
covered AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM hits) GROUP BY doc_id),
items AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS list FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM hits) GROUP BY doc_id)
SELECT w.doc_id, len(words) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(list, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM w LEFT JOIN covered USING (doc_id) LEFT JOIN items USING (doc_id)
"""

SQL_OP2 = r"""
WITH p AS (SELECT page_id, coalesce(html, '') AS html, strlen(coalesce(html, '')) AS n FROM pages),
r AS (SELECT *, max(page_id) OVER (PARTITION BY html) AS first_id FROM p)
SELECT page_id, n AS payload_bytes, sha1(html) AS payload_digest, CASE WHEN n >= 1000 AND page_id <> first_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN n >= 1000 AND page_id <> first_id THEN first_id END AS refers_to FROM r
"""

SQL_OP3 = r"""
WITH n AS (SELECT doc_id, length(coalesce(text, '')) AS n_points, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS norm FROM documents),
r AS (SELECT *, row_number() OVER (PARTITION BY norm ORDER BY n_points DESC, doc_id) AS place, count(*) OVER (PARTITION BY norm) AS group_size,
             first_value(doc_id) OVER (PARTITION BY norm ORDER BY n_points DESC, doc_id) AS keep_id FROM n)
SELECT doc_id, keep_id, group_size, place = 1 AS kept, sha256(norm) AS text_sha256 FROM r
"""


SQL_OP5 = r"""
WITH n AS (SELECT source, count(*) AS n FROM documents GROUP BY source),
r AS (SELECT source, pow(n, 0.7) * (SELECT sum(n) / sum(pow(n, 0.7)) FROM n) / n AS rate FROM n),
s AS (SELECT source, rate, CAST(greatest(1, ceil(rate / 30.0)) AS INT) AS parts FROM r),
k AS (SELECT source, rate, parts, unnest(range(0, CAST(ceil(rate / parts + 12 * sqrt(rate / parts) + 20) AS INT) + 1)) AS k FROM s),
c AS (SELECT source, rate, parts, k, sum(exp(k * ln(rate / parts) - rate / parts - lgamma(k + 1))) OVER (PARTITION BY source ORDER BY k) AS c FROM k),
d AS (SELECT doc_id, source, unnest(range(0, parts)) AS part FROM documents JOIN s USING (source)),
u AS (SELECT doc_id, source, CAST('0x' || substr(md5('20240613:' || doc_id || ':' || part), 1, 13) AS BIGINT) / 4503599627370496.0 AS u FROM d),
m AS (SELECT u.doc_id, u.source, any_value(rate) AS rate, count(*) FILTER (WHERE c.c <= u.u) AS n_copies FROM u JOIN c ON u.source = c.source GROUP BY u.doc_id, u.source),
e AS (SELECT *, unnest(range(0, n_copies)) AS copy FROM m)
SELECT e.doc_id, e.source, t.lang, t.n_chars, round(rate, 9) AS rate, n_copies, copy, CAST('0x' || substr(md5('20240613/copy:' || e.doc_id || ':' || copy), 1, 15) AS BIGINT) AS shuffle_key,
       strlen(t.text) AS n_bytes, sha256(t.text) AS text_sha256
FROM e JOIN documents t ON e.doc_id = t.doc_id
"""

SQL_OP6 = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words FROM documents),
win AS (SELECT doc_id, i, array_to_string(words[i:i + 12], ' ') AS g FROM (SELECT doc_id, words, unnest(range(1, len(words) - 11)) AS i FROM w)),
firsts AS (SELECT g, min(doc_id) AS m FROM win GROUP BY g),
covered AS (SELECT DISTINCT doc_id, unnest(range(i, i + 13)) AS p FROM win JOIN firsts USING (g) WHERE doc_id > m),
each AS (SELECT doc_id, unnest(words) AS word, unnest(range(1, len(words) + 1)) AS p FROM w),
kept AS (SELECT e.doc_id, count(*) AS n, string_agg(word, ' ' ORDER BY p) AS kept FROM each e ANTI JOIN covered c USING (doc_id, p) GROUP BY e.doc_id)
SELECT w.doc_id, len(words) AS n_words, len(words) - coalesce(n, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM w LEFT JOIN kept USING (doc_id)
"""


SQL_OP9 = r"""
WITH t AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
           UNION ALL VALUES (-1, 0, 'user', '</s>[INST] ok [/INST]'), (-1, 1, 'assistant', '</s>[INST] ok [/INST]')),
e AS (SELECT *, CASE role WHEN 'user' THEN '[INST] ' WHEN 'assistant' THEN '<s>' WHEN 'system' THEN '<<SYS>>' ELSE '[TURN ' || hex(role) || ']' END AS a,
             CASE role WHEN 'user' THEN ' [/INST]' WHEN 'assistant' THEN '</s>' WHEN 'system' THEN '<</SYS>>' ELSE '[/TURN]' END AS b,
             regexp_replace(replace(text, '\', '\\'), '(\[|<)(/?INST\]|/?TURN[ \]]|/?s>|</?SYS>>)', '\1\\\2', 'g') AS safe FROM t),
g AS (SELECT conv_id, count(*) AS n_turns, string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text) AS told,
             string_agg(CASE WHEN role = 'assistant' THEN text ELSE '' END, '' ORDER BY turn, role, text) AS loss,
             list(a || text || b ORDER BY turn, role, text) AS plain, sum(length(a || safe || b)) AS safe_chars, bool_or(contains(text, '\')) AS quoted FROM e GROUP BY conv_id),
f AS (SELECT *, array_to_string(plain, '') AS whole FROM g)
SELECT conv_id, n_turns, sha256(told) AS turns_sha256, length(loss) AS loss_chars, sha256(loss) AS loss_sha256,
       CAST(CASE WHEN NOT quoted AND regexp_extract_all(whole, '(?s)\[INST\] .*? \[/INST\]|<s>.*?</s>|<<SYS>>.*?<</SYS>>|\[TURN [0-9A-F]*\].*?\[/TURN\]') = plain THEN length(whole) ELSE safe_chars END AS BIGINT) AS formatted_chars
FROM f
"""


def queries() -> dict[str, Query]:
    return {
        "op1_decontaminate": op1_decontaminate,
        "op2_web_archive": op2_web_archive,
        "op3_exact_dedup": op3_exact_dedup,
        "op4_kd_sharding": op4_kd_sharding,
        "op5_poisson_mix": op5_poisson_mix,
        "op6_substring_dedup": op6_substring_dedup,
        "op7_language_id": op7_language_id,
        "op8_toxicity": op8_toxicity,
        "op9_chat_format": op9_chat_format,
        "op10_simhash": op10_simhash,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op1_decontaminate": SQL_OP1,
        "op2_web_archive": SQL_OP2,
        "op3_exact_dedup": SQL_OP3,
        "op5_poisson_mix": SQL_OP5,
        "op6_substring_dedup": SQL_OP6,
        "op9_chat_format": SQL_OP9,
    }
