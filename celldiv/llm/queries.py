"""The thin queries over the given tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from celldiv.llm import chat, decontam, lm, packing, pii, quality, simhash, token_counts, toxicity, url_rules
from celldiv.llm.common import table

#: The surrogates' key in the queries; a deployment gives its own.
KEY = "query-key"


def op1_chat_collapse(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.collapse_and_render(table(spark, sf_dir, "conversations"))


def op2_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op3_pii_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.replace(table(spark, sf_dir, "documents").select("doc_id", "text"), KEY)


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality.judge(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op6_token_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.histogram(table(spark, sf_dir, "documents"))


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = simhash.classes(table(spark, sf_dir, "documents"))
    return got.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op8_lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm.scores(table(spark, sf_dir, "documents"))


def _learning(labels: DataFrame) -> DataFrame:
    return labels.where(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(3)) != 1)


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = toxicity.fit(docs, _learning(table(spark, sf_dir, "labels").select("doc_id", "toxic")))
    held_out = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(3)) == 1, F.lit(False))
    return toxicity.score(docs, model).select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= toxicity.LIMIT).cast("int").alias("predicted"), F.slice("evidence", 1, 3).alias("evidence"))


def op10_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = url_rules.judge(table(spark, sf_dir, "pages").select("page_id", "url"), url_rules.rule_table(spark, url_rules.RULES))
    repeated = judged.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))))
    return repeated.select("page_id", "host", "path", "rule", "verdict")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (
    op1_chat_collapse, op2_pack, op3_pii_surrogates, op4_quality_rules, op5_decontaminate, op6_token_lengths, op7_simhash, op8_lm_scores, op9_toxicity, op10_url_rules)}


_CHAT_SQL = """
WITH turns AS (SELECT DISTINCT conv_id, turn, role, text FROM conversations),
placed AS (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role NULLS FIRST, text NULLS FIRST) AS place FROM turns),
shown AS (SELECT conv_id, place, chr(31) || coalesce(role, chr(30)) || chr(31) || coalesce(text, chr(30)) AS s,
  '<|im_start|>' || coalesce(role, '') || chr(10) || coalesce(text, '') || '<|im_end|>' || chr(10) AS r FROM placed),
pre AS (SELECT conv_id, place, string_agg(s, '') OVER (PARTITION BY conv_id ORDER BY place ROWS UNBOUNDED PRECEDING) AS p,
  count(*) OVER (PARTITION BY conv_id) AS n FROM shown),
ends AS (SELECT p, n AS n_turns, min(conv_id) AS conv_id, count(*) AS n_copies FROM pre WHERE place = n GROUP BY p, n),
kept AS (SELECT * FROM ends WHERE NOT EXISTS (SELECT 1 FROM pre WHERE pre.place < pre.n AND pre.p = ends.p))
SELECT k.conv_id, CAST((place - 1) // 256 AS BIGINT) AS part, k.n_turns, k.n_copies, string_agg(r, '' ORDER BY place) AS text
FROM kept k JOIN shown s ON s.conv_id IS NOT DISTINCT FROM k.conv_id GROUP BY k.conv_id, k.n_turns, k.n_copies, (place - 1) // 256
"""

_STOPS = ", ".join(f"'{w}'" for w in dict.fromkeys(quality.STOP_WORDS))
_QUALITY_SQL = rf"""
WITH d AS (SELECT doc_id, row_number() OVER () AS row_no, coalesce(text, '') AS t FROM documents),
w AS (SELECT *, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS ws,
  list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM d),
win AS (SELECT row_no, i, array_to_string(ws[i:i + 7], ' ') AS g FROM w, unnest(range(1, len(ws) - 6)) AS r(i) WHERE len(ws) >= 8),
twice AS (SELECT row_no, i, count(*) OVER (PARTITION BY row_no, g) AS c FROM win),
cover AS (SELECT row_no, count(DISTINCT i + k) AS n FROM twice, unnest(range(0, 8)) AS q(k) WHERE c > 1 GROUP BY row_no),
m AS (SELECT doc_id, len(ws) AS n_words, coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0) AS word_chars,
  len(regexp_extract_all(t, '[#*$%&|<>]')) AS n_symbols, len(ls) AS n_lines, len(ls) - len(list_distinct(ls)) AS n_dup_lines,
  coalesce(cover.n, 0) AS n_repeat_words, len(regexp_extract_all(t, '!')) AS n_exclaims, len(regexp_extract_all(t, '[|]')) AS n_bar_words,
  len(list_filter(ws, lambda x: length(x) <= 4 AND lower(x) IN ({_STOPS}))) AS n_stop_words,
  len(list_filter(ws, lambda x, i: i > 1 AND x = ws[i - 1])) AS n_echo_words
  FROM w LEFT JOIN cover USING (row_no))
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(word_chars AS BIGINT) AS word_chars, CAST(n_symbols AS BIGINT) AS n_symbols,
  CAST(n_dup_lines AS BIGINT) AS n_dup_lines, CAST(n_repeat_words AS BIGINT) AS n_repeat_words,
  ({' OR '.join(r.sql() for r in quality.BASE_RULES)}) AS base_failed,
  NOT ({' OR '.join(r.sql() for r in (*quality.BASE_RULES, *quality.RULES))}) AS kept
FROM m
"""

_LOWERED = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_WORDS = rf"regexp_extract_all({_LOWERED}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
_DECONTAM_SQL = f"""
WITH d AS (SELECT doc_id, row_number() OVER () AS row_no, {_WORDS} AS ws FROM documents),
b AS (SELECT item_id, {_WORDS} AS ws FROM benchmark),
bw AS (SELECT DISTINCT CAST(item_id AS VARCHAR) AS item, least(10, len(ws)) AS n, array_to_string(ws[i:i + least(10, len(ws)) - 1], ' ') AS g
  FROM b, unnest(range(1, len(ws) - least(10, len(ws)) + 2)) AS r(i) WHERE len(ws) > 0),
sizes AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT row_no, n, i, array_to_string(ws[i:i + n - 1], ' ') AS g FROM d, sizes, unnest(range(1, len(ws) - n + 2)) AS r(i) WHERE len(ws) >= n),
hit AS (SELECT row_no, i, n, item FROM dw JOIN bw USING (n, g)),
cover AS (SELECT row_no, count(DISTINCT i + k) AS n_hit FROM (SELECT DISTINCT row_no, i, n FROM hit) h, unnest(range(0, h.n)) AS q(k) GROUP BY row_no),
its AS (SELECT row_no, count(DISTINCT item) AS n_items, string_agg(DISTINCT item, ',' ORDER BY item) AS names FROM hit GROUP BY row_no)
SELECT doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN cover USING (row_no) LEFT JOIN its USING (row_no)
"""

_URL_SQL = r"""
WITH rules(verdict, rhost, rpath) AS (VALUES ('block', 'com', '/en/'), ('allow', 'example.com', '/en/7'), ('allow', 'net', '/de/'), ('block', 'example.net', '/de/8'), ('block', 'org', '/es/')),
u AS (SELECT page_id, row_number() OVER () AS row_no,
  CASE WHEN contains(coalesce(url, ''), '://') THEN translate(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') ELSE '' END AS host,
  CASE WHEN contains(coalesce(url, ''), '://') THEN regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1) ELSE '' END AS path FROM pages),
fit AS (SELECT row_no, verdict, rhost || rpath AS rule, row_number() OVER (PARTITION BY row_no ORDER BY length(rhost || rpath) DESC, length(rhost) DESC) AS k
  FROM u JOIN rules ON (host = rhost OR ends_with(host, '.' || rhost)) AND starts_with(path, rpath))
SELECT page_id, host, path, rule, coalesce(verdict, 'allow') AS verdict FROM u LEFT JOIN (SELECT * FROM fit WHERE k = 1) USING (row_no)
"""

#: Surrogates, tokenizer ids, XXH64, mixture weights and nearest neighbours are beyond SQL; tests hold those against brute force.
ORACLE_SQL: dict[str, str] = {"op1_chat_collapse": _CHAT_SQL, "op4_quality_rules": _QUALITY_SQL, "op5_decontaminate": _DECONTAM_SQL, "op10_url_rules": _URL_SQL}
