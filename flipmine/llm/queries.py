"""Queries over the given tables and, where SQL can express them, their DuckDB counterparts."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe_replay, chat_masks, decontaminate, jaccard_join, recurrent_lm, risk_rules, site_style_tree, toxicity, url_rules, warc_revisits

RANKS = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
CHAT_TOKENIZER = public_tokenizers.path("byte_bpe_50k.json")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_site_style_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return site_style_tree.extracted(table(spark, sf_dir, "pages"))


def op2_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.joined(table(spark, sf_dir, "documents"), size=3, percent=90)


OP2_SQL = r"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 2], ' ') AS g FROM d, unnest(generate_series(1, greatest(len(w) - 2, 1))) AS t(i) WHERE len(w) > 0),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS shared FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * shared >= 90 * (x.n + y.n - shared)),
e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
r(node, reached) AS (SELECT doc_id, doc_id FROM d UNION SELECT r.node, e.b FROM r JOIN e ON r.reached = e.a)
SELECT doc_id, coalesce(n, 0) AS n_shingles, component_id
FROM d LEFT JOIN n USING (doc_id) JOIN (SELECT node AS doc_id, min(reached) AS component_id FROM r GROUP BY node) USING (doc_id)
"""


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_replay.digests(table(spark, sf_dir, "documents"), RANKS, public_tokenizers.PATTERN)


def op4_warc_revisits(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc_revisits.archived(table(spark, sf_dir, "pages")).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


OP4_SQL = """
WITH p AS (SELECT page_id, strlen(coalesce(html, '')) AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages),
o AS (SELECT payload_digest, min(page_id) AS original FROM p WHERE payload_bytes >= 100 GROUP BY payload_digest)
SELECT page_id, payload_bytes, payload_digest,
  CASE WHEN page_id <> original THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN page_id <> original THEN original END AS refers_to
FROM p LEFT JOIN o USING (payload_digest)
"""


def url_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """url and block: whether ``labels`` calls the document that the url's number names toxic or of low quality; null if it names none."""
    pages = url_rules.parsed(table(spark, sf_dir, "pages").select("url"))
    named = pages.withColumn("doc_id", F.expr("try_cast(nullif(regexp_extract(path, '/([0-9]+)', 1), '') AS BIGINT)"))
    known = table(spark, sf_dir, "labels").groupBy("doc_id").agg(F.max((F.col("toxic") == 1) | (F.col("quality") == 0)).alias("block"))
    return named.join(known, "doc_id", "left").select("url", "block")


def op5_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_rules.judge(table(spark, sf_dir, "pages"), url_labels(spark, sf_dir)).drop("confidence")


OP5_SQL = r"""
WITH u AS (SELECT page_id, CASE WHEN contains(coalesce(url, ''), '://') THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
h AS (SELECT *, regexp_extract(rest, '^[^/?#]*') AS raw FROM u),
c AS (SELECT page_id, row_number() OVER () AS r, translate(raw, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    regexp_extract(substr(rest, length(raw) + 1), '^[^?#]*') AS path,
    translate(substr(rest, length(raw) + 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS tail FROM h),
tok AS (SELECT DISTINCT r, t FROM (
    SELECT r, 'h:' || unnest(regexp_split_to_array(host, '[.:-]+')) AS t FROM c UNION ALL SELECT r, 'p:' || unnest(regexp_split_to_array(tail, '[^a-z0-9_]+')) FROM c)
    WHERE length(t) > 2 AND NOT regexp_matches(substr(t, 3), '^[0-9]+$')),
lab AS (SELECT doc_id, max(CASE WHEN toxic = 1 OR quality = 0 THEN 1 ELSE 0 END) AS bad FROM labels GROUP BY doc_id),
known AS (SELECT r, bad FROM c JOIN lab ON lab.doc_id = TRY_CAST(nullif(regexp_extract(path, '/([0-9]+)', 1), '') AS BIGINT) WHERE r IN (SELECT r FROM tok)),
floor AS (SELECT greatest(20, ceil(0.002 * count(*))) AS least FROM known),
one AS (SELECT t FROM tok JOIN known USING (r) GROUP BY t HAVING sum(bad) >= (SELECT least FROM floor)),
k AS (SELECT r, t, bad FROM tok JOIN known USING (r) JOIN one USING (t)),
sets AS (SELECT [a.t] AS s, a.r, a.bad FROM k a
    UNION ALL SELECT [a.t, b.t], a.r, a.bad FROM k a JOIN k b ON a.r = b.r AND a.t < b.t
    UNION ALL SELECT [a.t, b.t, d.t], a.r, a.bad FROM k a JOIN k b ON a.r = b.r AND a.t < b.t JOIN k d ON a.r = d.r AND b.t < d.t
    UNION ALL SELECT [a.t, b.t, d.t, e.t], a.r, a.bad FROM k a JOIN k b ON a.r = b.r AND a.t < b.t JOIN k d ON a.r = d.r AND b.t < d.t JOIN k e ON a.r = e.r AND d.t < e.t),
mined AS (SELECT s FROM sets GROUP BY s HAVING sum(bad) >= (SELECT least FROM floor) AND sum(bad) >= 0.8 * count(*)),
own AS (SELECT r, list(t) AS ts FROM tok GROUP BY r),
hit AS (SELECT DISTINCT r FROM own JOIN mined ON list_has_all(ts, s)),
rules(verdict, rh, rp) AS (VALUES ('block', 'net', '/'), ('allow', 'example.net', '/en/'), ('block', 'example.com', '/de/'), ('allow', 'org', '/fr/')),
fit AS (SELECT r, arg_max(rh || rp, length(rh || rp)) AS rule, arg_max(verdict, length(rh || rp)) AS verdict
    FROM c JOIN rules ON (host = rh OR suffix(host, '.' || rh)) AND starts_with(path, rp) GROUP BY r)
SELECT page_id, host, path, rule, coalesce(verdict, CASE WHEN hit.r IS NULL THEN 'allow' ELSE 'block' END) AS verdict
FROM c LEFT JOIN fit USING (r) LEFT JOIN hit USING (r)
"""


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).drop("spans")


OP6_SQL = r"""
WITH d AS (SELECT doc_id, row_number() OVER () AS r,
    regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id,
    regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
win AS (SELECT DISTINCT item_id, least(len(w), 10) AS size, array_to_string(w[i:i + 9], ' ') AS text
    FROM b, unnest(generate_series(1, greatest(len(w) - 9, 1))) AS t(i) WHERE len(w) > 0),
sizes AS (SELECT DISTINCT size FROM win),
places AS (SELECT r, i, size, array_to_string(w[i:i + size - 1], ' ') AS text FROM d, sizes, unnest(generate_series(1, len(w) - size + 1)) AS t(i)),
hits AS (SELECT p.r, p.i, p.size, win.item_id FROM places p JOIN win ON p.size = win.size AND p.text = win.text),
words AS (SELECT r, count(DISTINCT i + k) AS n_hit FROM hits, unnest(generate_series(0, size - 1)) AS t(k) GROUP BY r),
items AS (SELECT r, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS names FROM (SELECT DISTINCT r, item_id::VARCHAR AS item FROM hits) GROUP BY r)
SELECT doc_id, len(w) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
  sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN words USING (r) LEFT JOIN items USING (r)
"""


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.classified(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op8_recurrent_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return recurrent_lm.scored(table(spark, sf_dir, "documents"))


def op9_risk_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = risk_rules.judged(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return rows.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op10_chat_masks(spark: SparkSession, sf_dir: str) -> DataFrame:
    odd = "</s>[INST] ok [/INST]"
    probe = spark.createDataFrame([(-7, 0, "user", odd), (-7, 1, "assistant", odd)], "conv_id long, turn long, role string, text string")
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(probe)
    return chat_masks.read_back(chat_masks.formatted(rows, CHAT_TOKENIZER))


OP10_SQL = r"""
WITH c AS (SELECT conv_id, turn, role, text FROM conversations
    UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
t AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM c),
e AS (SELECT *, length(role || text) + length(regexp_replace(role || text, '[^\\<\[]', '', 'g')) AS chars FROM t)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(CASE WHEN role = 'assistant' THEN text END, '' ORDER BY turn NULLS FIRST, role, text), '')) AS loss_sha256,
  (sum(chars) + 24 * count(*))::BIGINT AS formatted_chars
FROM e GROUP BY conv_id
"""

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_site_style_tree": op1_site_style_tree, "op2_jaccard_join": op2_jaccard_join, "op3_byte_bpe": op3_byte_bpe, "op4_warc_revisits": op4_warc_revisits,
    "op5_url_rules": op5_url_rules, "op6_decontamination": op6_decontamination, "op7_toxicity": op7_toxicity, "op8_recurrent_lm": op8_recurrent_lm,
    "op9_risk_rules": op9_risk_rules, "op10_chat_masks": op10_chat_masks,
}
ORACLES: dict[str, str] = {"op2_jaccard_join": OP2_SQL, "op4_warc_revisits": OP4_SQL, "op5_url_rules": OP5_SQL, "op6_decontamination": OP6_SQL, "op10_chat_masks": OP10_SQL}
