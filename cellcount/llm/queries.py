"""The registered queries of this subpackage, and their DuckDB SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, decontam, lm, neardup, packing, quality, rules, substring, toxicity, urls
from .common import table
from .labelled import held_out


#: The conversation that op1's contract adds: both turns hold the template's own control strings.
EXTRA_TURNS = [(-7, 0, "user", r"\### Assistant: </turn> ok"), (-7, 1, "assistant", r"\### Assistant: </turn> ok")]


def op1_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    rows = rows.unionByName(spark.createDataFrame(EXTRA_TURNS, "conv_id bigint, turn bigint, role string, text string"))
    turns = chat.canonicalise_json(chat.to_records(rows), "conv_id", "record")
    return chat.read_back(chat.render(turns, "conv_id"), "conv_id")


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(packing.pieces(table(spark, sf_dir, "documents")))


def op3_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = quality.fit(docs, table(spark, sf_dir, "labels"), ~held_out(5, 0))
    return quality.score(docs, model).select("doc_id", held_out(5, 0).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op4_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = lm.score(table(spark, sf_dir, "documents"))
    # Sums of many logarithms, in no fixed order: more digits would not be the same in every run.
    return out.withColumns({"log_score": F.round("log_score", 4), "log_per_word": F.round("log_per_word", 6)})


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"), ~held_out(3, 1))
    out = toxicity.score(docs, model).drop("flagged")
    return out.select("doc_id", held_out(3, 1).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op7_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")
    out = neardup.classes(items, 85, 100).select(F.col("id").alias("doc_id"), "n_shingles", F.col("component").alias("component_id"))
    return out.withColumn("kept", F.col("doc_id") == F.col("component_id"))


def op8_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring.repeats(table(spark, sf_dir, "documents")).drop("digest", "start", "n_chars")


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.report(decontam.hits(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")))


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    led = rules.apply_policy(rules.ledger(table(spark, sf_dir, "documents")), "quality-2")
    base = F.col("failed").bitwiseAND(F.lit(rules.mask("base-1")).cast("long")) != 0
    return led.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", base.alias("base_failed"), (F.col("kept") & ~base).alias("kept"), F.col("failed").alias("failed_bits"))


#: The rules that op10's contract fixes.
URL_RULES = (("net/", "block"), ("example.net/en/", "allow"), ("example.com/de/", "block"), ("org/fr/", "allow"))


def op10_url_reputation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge(table(spark, sf_dir, "pages"), URL_RULES).drop("p_bad")


QUERIES = {
    "op1_chat_formatting": op1_chat_formatting,
    "op2_packing": op2_packing,
    "op3_quality_classifier": op3_quality_classifier,
    "op4_lm_scoring": op4_lm_scoring,
    "op5_toxicity": op5_toxicity,
    "op7_minhash_dedup": op7_minhash_dedup,
    "op8_substring_dedup": op8_substring_dedup,
    "op9_decontamination": op9_decontamination,
    "op6_quality_rules": op6_quality_rules,
    "op10_url_reputation": op10_url_reputation,
}

ORACLE: dict[str, str] = {}

_SP = r"[\x20\x09-\x0D]+"
ORACLE["op6_quality_rules"] = r"""
WITH d AS (
  SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS t FROM documents
), w AS (
  SELECT rid, doc_id, t, list_filter(regexp_split_to_array(t, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws,
         list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls
  FROM d
), m AS (
  SELECT rid, doc_id, len(ws)::BIGINT AS n_words, length(array_to_string(ws, ''))::BIGINT AS word_chars,
         length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
         length(regexp_replace(t, '[^\p{Lu}]', '', 'g'))::BIGINT AS n_upper,
         len(ls)::BIGINT AS n_lines, (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines
  FROM w
), g AS (
  SELECT rid, i, ws[i] || ' ' || ws[i+1] || ' ' || ws[i+2] || ' ' || ws[i+3] || ' ' || ws[i+4] AS s
  FROM (SELECT rid, ws, unnest(range(1, len(ws) - 3)) AS i FROM w WHERE len(ws) >= 5)
), r AS (
  SELECT rid, count(DISTINCT p)::BIGINT AS n_repeat_words
  FROM (SELECT rid, unnest(range(i, i + 5)) AS p FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, s) AS c FROM g) WHERE c > 1)
  GROUP BY rid
), a AS (
  SELECT m.*, coalesce(r.n_repeat_words, 0) AS n_repeat_words FROM m LEFT JOIN r USING (rid)
), f AS (
  SELECT *, (CASE WHEN n_words < 10 THEN 1 ELSE 0 END + CASE WHEN 100 * n_repeat_words > 20 * n_words THEN 2 ELSE 0 END
    + CASE WHEN 100 * n_symbols > 15 * word_chars THEN 4 ELSE 0 END + CASE WHEN 2 * n_upper > word_chars THEN 8 ELSE 0 END
    + CASE WHEN n_lines > 3 AND 10 * n_dup_lines > 5 * n_lines THEN 16 ELSE 0 END
    + CASE WHEN n_words > 0 AND word_chars > 25 * n_words THEN 32 ELSE 0 END
    + CASE WHEN n_words > 0 AND word_chars < 2 * n_words THEN 64 ELSE 0 END
    + CASE WHEN 100 * n_symbols > 3 * word_chars THEN 128 ELSE 0 END)::BIGINT AS failed_bits
  FROM a
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       (failed_bits & 3) <> 0 AS base_failed, (failed_bits & 255) = 0 AS kept, failed_bits
FROM f
"""

ORACLE["op10_url_reputation"] = r"""
WITH p AS (
  SELECT page_id, html, translate(coalesce(CASE WHEN instr(url, '://') > 0 THEN regexp_extract(substr(url, instr(url, '://') + 3), '^([^/?#]*)', 1) END, ''),
                                  'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         coalesce(CASE WHEN instr(url, '://') > 0 THEN regexp_extract(substr(url, instr(url, '://') + 3), '^[^/?#]*([^?#]*)', 1) END, '') AS path
  FROM pages
), t AS (
  SELECT *, regexp_replace(coalesce(html, ''), '<[^>]*>', ' ', 'g') AS txt,
         array_to_string(string_split(host, '.')[-2:], '.') AS two
  FROM p
), l AS (
  SELECT *, CASE WHEN two IN ('ac.uk', 'co.uk', 'gov.uk', 'org.uk', 'com.au', 'net.au', 'org.au', 'co.in', 'co.jp', 'co.kr', 'co.nz', 'co.za', 'com.br', 'com.cn', 'com.mx', 'com.tr') THEN 2 ELSE 1 END AS labels FROM t
), e AS (
  SELECT *, array_to_string(string_split(host, '.')[-labels:], '.') AS suffix, array_to_string(string_split(host, '.')[-(labels + 1):], '.') AS domain FROM l
), o AS (
  SELECT *, CASE WHEN 50 * length(regexp_replace(txt, '[^#*$%|]', '', 'g')) > greatest(length(txt), 1)
                   OR 50 * length(regexp_replace(txt, '[^!]', '', 'g')) > greatest(length(txt), 1) THEN 1 ELSE 0 END AS bad
  FROM e
), hs AS (SELECT host, any_value(domain) AS domain, any_value(suffix) AS suffix, count(*)::DOUBLE AS n, sum(bad)::DOUBLE AS x FROM o GROUP BY host),
s0 AS (SELECT suffix, sum(n) AS n, sum(x) AS x, (SELECT (sum(x) + 1) / (sum(n) + 2) FROM hs) AS m FROM hs GROUP BY suffix),
s1 AS (SELECT suffix, (x + k * m) / (n + k) AS m FROM s0, (SELECT CASE WHEN sum(n * (n - 1) * m * (1 - m)) > 0 THEN 1 / least(greatest(sum((x - n * m) * (x - n * m) - n * m * (1 - m)) / sum(n * (n - 1) * m * (1 - m)), 1 / 1001.0::DOUBLE), 0.5::DOUBLE) - 1 ELSE 20 END AS k FROM s0)),
d0 AS (SELECT domain, sum(n) AS n, sum(x) AS x, any_value(m) AS m FROM hs JOIN s1 USING (suffix) GROUP BY domain, suffix),
d1 AS (SELECT domain, (x + k * m) / (n + k) AS m FROM d0, (SELECT CASE WHEN sum(n * (n - 1) * m * (1 - m)) > 0 THEN 1 / least(greatest(sum((x - n * m) * (x - n * m) - n * m * (1 - m)) / sum(n * (n - 1) * m * (1 - m)), 1 / 1001.0::DOUBLE), 0.5::DOUBLE) - 1 ELSE 20 END AS k FROM d0)),
h0 AS (SELECT host, n, x, m FROM hs JOIN d1 USING (domain)),
h AS (SELECT host, x + k * m AS a, n - x + k * (1 - m) AS b FROM h0, (SELECT CASE WHEN sum(n * (n - 1) * m * (1 - m)) > 0 THEN 1 / least(greatest(sum((x - n * m) * (x - n * m) - n * m * (1 - m)) / sum(n * (n - 1) * m * (1 - m)), 1 / 1001.0::DOUBLE), 0.5::DOUBLE) - 1 ELSE 20 END AS k FROM h0)),
v AS (SELECT host, (j >= 256) AS above, (a - 1) * ln((j + 0.5::DOUBLE) / 512) + (b - 1) * ln(1 - (j + 0.5::DOUBLE) / 512) AS y FROM h, (SELECT unnest(range(512)) AS j)),
w AS (SELECT host, above, exp(y - max(y) OVER (PARTITION BY host)) AS y FROM v),
b AS (SELECT host, sum(y) FILTER (above) / sum(y) AS p_bad FROM w GROUP BY host),
r AS (
  SELECT page_id, o.host, path, p_bad,
    CASE WHEN (o.host = 'example.net' OR o.host LIKE '%.example.net') AND starts_with(path, '/en/') THEN 'example.net/en/'
         WHEN (o.host = 'example.com' OR o.host LIKE '%.example.com') AND starts_with(path, '/de/') THEN 'example.com/de/'
         WHEN (o.host = 'org' OR o.host LIKE '%.org') AND starts_with(path, '/fr/') THEN 'org/fr/'
         WHEN (o.host = 'net' OR o.host LIKE '%.net') AND starts_with(path, '/') THEN 'net/' END AS rule
  FROM o JOIN b USING (host)
)
SELECT page_id, host, path, rule,
  CASE rule WHEN 'net/' THEN 'block' WHEN 'example.net/en/' THEN 'allow' WHEN 'example.com/de/' THEN 'block' WHEN 'org/fr/' THEN 'allow'
       ELSE CASE WHEN p_bad >= 0.95 THEN 'block' ELSE 'allow' END END AS verdict
FROM r
"""

ORACLE["op1_chat_formatting"] = r"""
WITH r AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok' UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'
), e AS (
  SELECT *, length(role) + length(regexp_replace(role, '[^\\<>\n]', '', 'g')) + length(text) + length(regexp_replace(text, '[^\\<>]', '', 'g')) AS escaped FROM r
)
SELECT conv_id, count(*) AS n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
       coalesce(sum(CASE WHEN role = 'assistant' THEN length(text) END), 0)::BIGINT AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
       sum(escaped + length('<turn ') + 2 + 9)::BIGINT AS formatted_chars
FROM e GROUP BY conv_id
"""

ORACLE["op9_decontamination"] = r"""
WITH d AS (
  SELECT row_number() OVER () AS rid, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents
), b AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark
), bw AS (
  SELECT DISTINCT item_id, n, array_to_string(ws[i:i + n - 1], ' ') AS s
  FROM (SELECT item_id, ws, least(13, len(ws)) AS n, unnest(range(1, len(ws) - least(13, len(ws)) + 2)) AS i FROM b WHERE len(ws) > 0)
), dw AS (
  SELECT rid, i, n, array_to_string(ws[i:i + n - 1], ' ') AS s
  FROM (SELECT rid, ws, n, unnest(range(1, len(ws) - n + 2)) AS i FROM d, (SELECT DISTINCT n FROM bw) WHERE len(ws) >= n)
), h AS (
  SELECT rid, i, n, item_id FROM dw JOIN bw USING (n, s)
), c AS (
  SELECT rid, count(DISTINCT p)::BIGINT AS n_hit FROM (SELECT rid, unnest(range(i, i + n)) AS p FROM h) GROUP BY rid
), k AS (
  SELECT rid, count(DISTINCT item_id)::BIGINT AS n_items, string_agg(DISTINCT item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS ids FROM h GROUP BY rid
)
SELECT doc_id, len(ws)::BIGINT AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(ws) AS contaminated
FROM d LEFT JOIN c USING (rid) LEFT JOIN k USING (rid)
"""


ORACLE["op7_minhash_dedup"] = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents
), s AS (
  SELECT DISTINCT doc_id, hash(array_to_string(ws[i:i + least(5, len(ws)) - 1], ' ')) AS g
  FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - least(5, len(ws)) + 2)) AS i FROM d WHERE len(ws) > 0)
), n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
e AS (
  SELECT a, b FROM (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM s x JOIN s y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY ALL)
  JOIN n p ON p.doc_id = a JOIN n q ON q.doc_id = b WHERE 100 * c >= 85 * (p.n + q.n - c)
), r(a, b) AS (SELECT doc_id, doc_id FROM d UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, min(r.b) AS component_id, d.doc_id = min(r.b) AS kept
FROM d JOIN r ON r.a = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id GROUP BY d.doc_id, n.n
"""


ORACLE["op8_substring_dedup"] = r"""
WITH RECURSIVE t AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS k FROM documents
), p AS (
  SELECT doc_id, row_number() OVER (PARTITION BY doc_id ORDER BY k) - 1 AS para_no, len(ws)::BIGINT AS n_words, ws, array_to_string(ws, ' ') AS w
  FROM (SELECT *, list_filter(regexp_split_to_array(translate(line, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM t) WHERE len(ws) > 0
), u AS (
  SELECT w, any_value(ws) AS ws FROM p GROUP BY w
), s AS (
  SELECT DISTINCT w, array_to_string(ws[i:i + 4], ' ') AS g FROM (SELECT w, ws, unnest(range(1, len(ws) - 3)) AS i FROM u WHERE len(ws) >= 32)
), n AS (SELECT w, count(*) AS n FROM s GROUP BY w),
e AS (
  SELECT a, b FROM (SELECT x.w AS a, y.w AS b, count(*) AS c FROM s x JOIN s y ON x.g = y.g AND x.w <> y.w GROUP BY ALL)
  JOIN n q ON q.w = a JOIN n r ON r.w = b WHERE 100 * c >= 80 * (q.n + r.n - c)
), r(a, b) AS (SELECT w, w FROM u UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a),
c AS (SELECT a AS w, min(b) AS cluster FROM r GROUP BY a),
m AS (
  SELECT *, min(doc_id) OVER z AS d0, max(doc_id) OVER z AS d1, min({'d': doc_id, 'p': para_no}) OVER z AS f FROM p JOIN c USING (w) WINDOW z AS (PARTITION BY cluster)
), k AS (SELECT *, f.d = doc_id AND f.p = para_no AS keeps FROM m WHERE d0 < d1),
g AS (SELECT *, para_no - row_number() OVER (PARTITION BY doc_id ORDER BY para_no) AS run FROM k WHERE NOT keeps),
h AS (SELECT *, sum(n_words) OVER (PARTITION BY doc_id, run) AS rw FROM g)
SELECT 'paragraph' AS unit, doc_id, para_no AS place, n_words, f.d AS first_doc_id, true AS removed FROM h WHERE rw >= 50
UNION ALL
SELECT 'paragraph', doc_id, para_no, n_words, f.d, false FROM k WHERE keeps AND cluster IN (SELECT cluster FROM h WHERE rw >= 50)
UNION ALL
SELECT 'passage', * FROM (
  WITH a AS (
    SELECT doc_id, list_filter(regexp_split_to_array(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents
  ), x AS (
    SELECT doc_id, i - 1 AS i, hash(array_to_string(ws[i:i + 23], ' ')) AS g FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 22)) AS i FROM a WHERE len(ws) >= 24)
  ), y AS (
    SELECT g, min(doc_id) AS f FROM x GROUP BY g HAVING min(doc_id) < max(doc_id)
  ), z AS (
    SELECT doc_id, i, f, f < doc_id AS removed, CASE WHEN i - lag(i) OVER (PARTITION BY doc_id, f < doc_id ORDER BY i) <= 26 THEN 0 ELSE 1 END AS fresh FROM x JOIN y USING (g)
  ), v AS (SELECT *, sum(fresh) OVER (PARTITION BY doc_id, removed ORDER BY i) AS run FROM z)
  SELECT doc_id, min(i)::BIGINT AS place, (max(i) - min(i) + 24)::BIGINT AS n_words, min(f) AS first_doc_id, removed
  FROM v GROUP BY doc_id, removed, run HAVING max(i) - min(i) + 24 >= 50
)
"""

ORACLE["op4_lm_scoring"] = r"""
WITH d AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents
), t AS (
  SELECT doc_id, i, ws[i] AS w, CASE WHEN i > 1 THEN ws[i - 1] END AS v FROM (SELECT doc_id, ws, unnest(range(1, len(ws) + 1)) AS i FROM d)
), u AS (SELECT w, count(*) AS c FROM t GROUP BY w),
n AS (SELECT count(*) AS n FROM t),
b AS (SELECT v, w, count(*) AS c FROM t WHERE i > 1 GROUP BY v, w),
o AS (SELECT doc_id, v, w, count(*) AS k FROM t WHERE i > 1 GROUP BY doc_id, v, w),
s AS (
  SELECT doc_id, o.k * CASE WHEN b.c > o.k THEN ln((b.c - o.k)::DOUBLE) - ln(x.c::DOUBLE) ELSE ln(0.4::DOUBLE) + ln(y.c::DOUBLE) - ln(n.n::DOUBLE) END AS s
  FROM o JOIN b USING (v, w) JOIN u x ON x.w = o.v JOIN u y ON y.w = o.w CROSS JOIN n
  UNION ALL SELECT doc_id, ln(u.c::DOUBLE) - ln(n.n::DOUBLE) FROM t JOIN u USING (w) CROSS JOIN n WHERE i = 1
)
SELECT doc_id, n_words, round(l, 4) AS log_score, round(CASE WHEN n_words > 0 THEN l / n_words ELSE 0 END, 6) AS log_per_word
FROM (SELECT d.doc_id, len(ws)::BIGINT AS n_words, coalesce(l, 0::DOUBLE) AS l FROM d LEFT JOIN (SELECT doc_id, sum(s) AS l FROM s GROUP BY doc_id) USING (doc_id))
"""
