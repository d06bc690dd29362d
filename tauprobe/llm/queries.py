"""The registered queries of the ten operators, each over its whole table with production parameters."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tauprobe.llm import byte_bpe, chat, decontaminate, language, lm_scoring, quality_classifier, quality_rules, simhash, token_files, url_filters
from tauprobe.llm.arrow_kernels import crc_rest
from tauprobe.session import scratch, table


#: Host and path rules of the URL filter.
URL_RULES = [("com/en/", "block"), ("example.com/en/7", "allow"), ("net/de/", "allow"), ("example.net/de/8", "block"), ("org/es/", "block")]


def op1_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words of all documents that lie in windows of benchmark items."""
    return decontaminate.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).withColumnRenamed("id", "doc_id")


def op2_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Formats all conversations and one that holds control strings; digests read back from the output."""
    given = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    said = "\\### Assistant: </turn> ok"
    own = spark.range(2).select(
        F.lit(-7).cast("bigint").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(said).alias("text")
    )
    return chat.digests(given.unionByName(own))


def op3_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Predicts the language of all documents; learns from labelled ones outside the held-out fifth."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = language.train(docs, learn_from=crc_rest("doc_id", 5) != 0)
    return language.predict(docs, model).select(F.col("id").alias("doc_id"), (crc_rest("id", 5) == 0).alias("held_out"), "lang_pred", "score", "ambiguous")


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Near-duplicate classes of all documents."""
    found = simhash.classes(table(spark, sf_dir, "documents"))
    return found.select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.col("component").alias("component_id"))


def op5_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Writes the ids of all documents to record files and reads them back."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    shards = token_files.write(docs, scratch(spark, "op5"), public_tokenizers.path("word_bpe_49k.json"), end_id=2)
    return token_files.read(spark, shards, ids=False).withColumnRenamed("id", "doc_id")


def op6_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encodes and decodes all documents."""
    return byte_bpe.round_trip(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Base rules and risk-controlled cutoffs for all documents."""
    judged = quality_rules.judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return judged.select(F.col("id").alias("doc_id"), "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op8_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores all documents with counts and a network learnt outside the held-out fifth."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = lm_scoring.fit_and_score(docs, learn_from=crc_rest("doc_id", 5) != 1)
    return scored.select(F.col("id").alias("doc_id"), (crc_rest("id", 5) == 1).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op9_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores the quality of all documents; learns from labels outside the held-out third."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = quality_classifier.train(docs, table(spark, sf_dir, "labels"), learn_from=crc_rest("doc_id", 3) != 1)
    return quality_classifier.score(docs, model).select(F.col("id").alias("doc_id"), (crc_rest("id", 3) == 1).alias("held_out"), "score", "predicted")


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Host and path rules, then mined token rules, for all pages."""
    return url_filters.judge(table(spark, sf_dir, "pages"), table(spark, sf_dir, "labels"), URL_RULES).withColumnRenamed("id", "page_id")


QUERIES = {"op1_decontaminate": op1_decontaminate, "op2_chat_format": op2_chat_format, "op3_language": op3_language, "op4_simhash": op4_simhash, "op5_token_files": op5_token_files, "op6_byte_bpe": op6_byte_bpe, "op7_quality_rules": op7_quality_rules, "op8_lm_scoring": op8_lm_scoring, "op9_quality_classifier": op9_quality_classifier, "op10_url_filter": op10_url_filter}

_CHAT_TURNS = r"""
WITH rows_ AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok' UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'
), sized AS (
  SELECT *, length(role) + len(regexp_extract_all(role, '\\|</turn>|###|:')) AS role_chars,
    length(text) + len(regexp_extract_all(text, '\\|</turn>|###|:')) AS text_chars
  FROM rows_
)
"""

_LOW = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

_CONTAMINATION = rf"""
WITH d AS (SELECT doc_id, regexp_extract_all({_LOW}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all({_LOW}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
bw AS (SELECT item_id, w, least(13, len(w)) AS n FROM b WHERE len(w) > 0),
windows AS (SELECT DISTINCT item_id, n, array_to_string(w[i:i + n - 1], ' ') AS g FROM (SELECT *, unnest(range(1, len(w) - n + 2)) AS i FROM bw)),
grams AS (SELECT doc_id, n, i, array_to_string(w[i:i + n - 1], ' ') AS g FROM (SELECT doc_id, n, w, unnest(range(1, len(w) - n + 2)) AS i FROM d, (SELECT DISTINCT n FROM windows) WHERE len(w) >= n)),
met AS (SELECT doc_id, item_id, i, n FROM grams JOIN windows USING (n, g)),
hits AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM met) GROUP BY doc_id),
names AS (SELECT doc_id, count(*) AS n_items, string_agg(name, ',' ORDER BY name) AS names FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS name FROM met) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(names, '')) AS items_sha256,
  coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN hits USING (doc_id) LEFT JOIN names USING (doc_id)
"""

_QUALITY = r"""
WITH t AS (SELECT doc_id, coalesce(lang, '') AS stratum, coalesce(text, '') AS t FROM documents),
w AS (SELECT *, regexp_extract_all(t, '[^ \t-\r]+') AS w, list_filter(string_split(t, chr(10)), lambda l: regexp_matches(l, '[^ \t-\r]')) AS l FROM t),
g AS (SELECT doc_id, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM w)),
r AS (SELECT doc_id, count(DISTINCT p) AS n_repeat_words FROM (SELECT doc_id, unnest(range(i, i + 3)) AS p FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, g) AS n FROM g) WHERE n > 1) GROUP BY doc_id),
f AS (SELECT doc_id, stratum, CAST(len(w) AS BIGINT) AS n_words, length(array_to_string(w, '')) AS word_chars, CAST(len(regexp_extract_all(t, '[#*$%&|<>]')) AS BIGINT) AS n_symbols,
  len(l) AS n_lines, CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words FROM w LEFT JOIN r USING (doc_id)),
v AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed, 1000 * n_symbols // greatest(word_chars, 1) AS symbols, 1000 * n_dup_lines // greatest(n_lines, 1) AS lines,
  1000 * n_repeat_words // greatest(n_words, 1) AS repeats, least(100 * word_chars // greatest(n_words, 1), 5000) AS long_words, 5000 - least(100 * word_chars // greatest(n_words, 1), 5000) AS short_words FROM f),
k AS (SELECT doc_id, min(quality) AS label FROM labels WHERE quality IN (0, 1) GROUP BY doc_id),
m AS (SELECT v.*, label FROM v JOIN k USING (doc_id) WHERE NOT base_failed),
long AS (SELECT stratum, label, rule, value FROM m UNPIVOT (value FOR rule IN (symbols, lines, repeats, long_words, short_words))),
bins AS (SELECT stratum, rule, value, sum(label) AS good, sum(1 - label) AS bad FROM long GROUP BY ALL),
tests AS (SELECT stratum, rule, sum(good) AS n, 0.05 / count(*) OVER () AS level FROM bins GROUP BY stratum, rule),
steps AS (SELECT stratum, rule, n, level, i, CASE WHEN i = 0 THEN n * ln(1 - 0.004) ELSE ln((n - i + 1) / i) + ln(0.004 / (1 - 0.004)) END AS step FROM (SELECT *, unnest(range(0, CAST(ceil(n * 0.004) AS BIGINT) + 1)) AS i FROM tests) WHERE i <= n),
terms AS (SELECT *, sum(step) OVER (PARTITION BY stratum, rule ORDER BY i) AS term FROM steps),
cdf AS (SELECT *, sum(exp(term)) OVER (PARTITION BY stratum, rule ORDER BY i) AS cdf FROM terms),
allowed AS (SELECT stratum, rule, coalesce(max(i) FILTER (cdf <= level), -1) AS k FROM cdf GROUP BY stratum, rule),
above AS (SELECT stratum, rule, value, coalesce(sum(good) OVER o, 0) AS good, coalesce(sum(bad) OVER o, 0) AS bad FROM bins WINDOW o AS (PARTITION BY stratum, rule ORDER BY value DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
cuts AS (SELECT stratum, rule, value AS cutoff FROM above JOIN allowed USING (stratum, rule) WHERE good <= k AND bad - 3 * good > 0 QUALIFY row_number() OVER (PARTITION BY stratum, rule ORDER BY bad - 3 * good DESC, value DESC) = 1),
wide AS (SELECT stratum, max(cutoff) FILTER (rule = 'symbols') AS c1, max(cutoff) FILTER (rule = 'lines') AS c2, max(cutoff) FILTER (rule = 'repeats') AS c3, max(cutoff) FILTER (rule = 'long_words') AS c4, max(cutoff) FILTER (rule = 'short_words') AS c5 FROM cuts GROUP BY stratum)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  NOT base_failed AND coalesce(symbols <= c1, true) AND coalesce(lines <= c2, true) AND coalesce(repeats <= c3, true) AND coalesce(long_words <= c4, true) AND coalesce(short_words <= c5, true) AS kept
FROM v LEFT JOIN wide USING (stratum)
"""

_URLS = r"""
WITH RECURSIVE p AS (SELECT page_id, url, translate(regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
  regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', 2) AS path, regexp_extract(coalesce(url, ''), '(?s)^.*?://[^?#]*\?([^#]*)', 1) AS query FROM pages),
t AS (SELECT page_id, url, host, path, list_sort(list_distinct(list_concat(list_transform(list_filter(string_split(host, '.'), lambda x: x <> ''), lambda x: 'h:' || x),
  list_transform(list_filter(string_split(path, '/'), lambda x: x <> ''), lambda x: 'p:' || x), list_transform(list_filter(list_transform(string_split(query, '&'), lambda x: string_split(x, '=')[1]), lambda x: x <> ''), lambda x: 'q:' || x)))) AS tokens FROM p),
ruled AS (SELECT *, CASE WHEN (host = 'example.net' OR ends_with(host, '.example.net')) AND starts_with(path, '/de/8') THEN 'example.net/de/8'
  WHEN (host = 'example.com' OR ends_with(host, '.example.com')) AND starts_with(path, '/en/7') THEN 'example.com/en/7'
  WHEN (host = 'org' OR ends_with(host, '.org')) AND starts_with(path, '/es/') THEN 'org/es/' WHEN (host = 'net' OR ends_with(host, '.net')) AND starts_with(path, '/de/') THEN 'net/de/'
  WHEN (host = 'com' OR ends_with(host, '.com')) AND starts_with(path, '/en/') THEN 'com/en/' END AS rule FROM t),
l AS (SELECT doc_id, max(coalesce(toxic = 1 OR quality = 0, false)) AS bad FROM labels WHERE doc_id IS NOT NULL GROUP BY doc_id),
known AS (SELECT row_number() OVER () AS r, tokens, bad FROM ruled JOIN l ON page_id = doc_id WHERE len(tokens) > 0 OR bad),
size AS (SELECT count(*) AS total, count(*) FILTER (bad) AS bad_total, ceil(greatest(0.002 * count(*), 20 - 0.5)) AS least FROM known),
frequent AS (SELECT tok FROM (SELECT unnest(tokens) AS tok FROM known) GROUP BY tok HAVING count(*) >= (SELECT least FROM size)),
sets AS (SELECT r, bad, tokens, CAST([] AS VARCHAR[]) AS s, 0 AS last FROM (SELECT r, bad, coalesce((SELECT list(tok ORDER BY tok) FROM frequent WHERE list_contains(tokens, tok)), []) AS tokens FROM known)
  UNION ALL SELECT r, bad, tokens, list_append(s, tokens[i]), i FROM (SELECT *, unnest(range(last + 1, len(tokens) + 1)) AS i FROM sets)),
counts AS (SELECT s, count(*) AS n, count(*) FILTER (bad) AS n_bad FROM sets WHERE len(s) > 0 GROUP BY s),
mined AS (SELECT s FROM counts, size WHERE n_bad >= least AND n_bad >= 0.8 * n AND n_bad * total >= 2.0 * n * bad_total)
SELECT page_id, host, path, rule, CASE WHEN rule IN ('com/en/', 'example.net/de/8', 'org/es/') THEN 'block' WHEN rule IS NOT NULL THEN 'allow'
  WHEN EXISTS (SELECT 1 FROM mined WHERE list_has_all(tokens, s)) THEN 'block' ELSE 'allow' END AS verdict
FROM ruled
"""

ORACLE_SQL = {
    "op1_decontaminate": _CONTAMINATION,
    "op7_quality_rules": _QUALITY,
    "op10_url_filter": _URLS,
    "op2_chat_format": _CHAT_TURNS
    + r"""
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(4 + role_chars + 2 + text_chars + 8) AS BIGINT) AS formatted_chars,
  regexp_full_match(string_agg(role || ',', '' ORDER BY turn, role, text), '(system,)*user,assistant,((user|tool),assistant,)*') AS valid
FROM sized GROUP BY conv_id
""",
}
