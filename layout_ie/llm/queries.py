"""The registered queries of this subpackage, each over its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import chat, decontaminate, html_text, mixing, quality_model, quality_rules, simhash, suffix_dedup, token_store, warc
from .common import read_table


def op1_quality_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_model.grade_documents(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def op2_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(read_table(spark, sf_dir, "documents"))


def op3_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(read_table(spark, sf_dir, "pages"))


def op4_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = suffix_dedup.remove_repeats(read_table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")


def op5_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(read_table(spark, sf_dir, "pages")).drop("path")


def op6_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(read_table(spark, sf_dir, "documents"))


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = quality_rules.apply_rules(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op8_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = chat.canonical_rows(read_table(spark, sf_dir, "conversations"))
    return chat.digests(chat.format_turns(rows.unionByName(chat.probe(spark))))


def op9_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_store.stage(read_table(spark, sf_dir, "documents"))


def op10_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.report(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark")).drop("spans")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_quality_model, op2_simhash_near_dedup, op3_html_text, op4_suffix_dedup, op5_warc, op6_source_mixing, op7_quality_rules, op8_chat_format, op9_token_store, op10_benchmark_decontamination)
}
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _quality_sql(risk: float = 0.05, level: float = 0.05) -> str:
    """Metrics by window tables; each cutoff tested by the binomial sum with log-gamma."""
    rules = quality_rules.RULES
    metric = {"symbols": "n_symbols / greatest(n_words, 1)", "repeats": "n_repeat_words / greatest(n_words, 1)", "lines": "n_dup_lines / greatest(n_lines, 1)", "long_words": "word_chars / greatest(n_words, 1)", "capitals": "n_capitals / greatest(word_chars, 1)"}
    ladder = ", ".join(f"('{r.name}', {i}, CAST({c} AS DOUBLE))" for r in rules for i, c in enumerate(r.ladder))
    values = " UNION ALL ".join(f"SELECT doc_id, lang, '{n}' AS rule, 1.0 * {e} AS v FROM m" for n, e in metric.items())
    each = risk / len(rules)
    return rf"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, lang, coalesce(text, '') AS t FROM documents),
w AS (SELECT k, unnest(l) AS w, unnest(range(1, len(l) + 1)) AS i FROM (SELECT k, regexp_extract_all(t, '[^ \t\n\x0B\f\r]+') AS l FROM d)),
tri AS (SELECT k, i, w || chr(0) || lead(w) OVER o || chr(0) || lead(w, 2) OVER o AS g FROM w WINDOW o AS (PARTITION BY k ORDER BY i)),
twice AS (SELECT k, i FROM (SELECT k, i, count(*) OVER (PARTITION BY k, g) AS n FROM tri WHERE g IS NOT NULL) WHERE n > 1),
rep AS (SELECT k, count(DISTINCT i + o) AS n FROM twice, (VALUES (0), (1), (2)) x(o) GROUP BY 1),
ln AS (SELECT k, count(*) AS n, count(*) - count(DISTINCT l) AS dup FROM (SELECT k, unnest(string_split(t, chr(10))) AS l FROM d) WHERE regexp_matches(l, '[^ \t\n\x0B\f\r]') GROUP BY 1),
wc AS (SELECT k, count(*) AS n, sum(length(w)) AS c FROM w GROUP BY 1),
m AS (SELECT d.k, d.doc_id, d.lang, coalesce(wc.n, 0) AS n_words, CAST(coalesce(wc.c, 0) AS BIGINT) AS word_chars, length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS n_symbols,
  length(t) - length(regexp_replace(t, '[A-Z]', '', 'g')) AS n_capitals, coalesce(ln.n, 0) AS n_lines, coalesce(ln.dup, 0) AS n_dup_lines, coalesce(rep.n, 0) AS n_repeat_words
  FROM d LEFT JOIN wc USING (k) LEFT JOIN ln USING (k) LEFT JOIN rep USING (k)),
b AS (SELECT *, n_words < {quality_rules.MIN_WORDS} OR 100 * n_repeat_words > {quality_rules.MAX_REPEAT_PERCENT} * n_words AS base_failed FROM m),
good AS (SELECT doc_id FROM labels WHERE doc_id IS NOT NULL GROUP BY 1 HAVING min(quality) = 1 AND coalesce(max(toxic), 0) = 0),
held AS (SELECT v.* FROM ({values}) v JOIN b ON b.doc_id = v.doc_id AND b.lang = v.lang WHERE NOT b.base_failed AND v.lang IS NOT NULL AND v.doc_id IN (SELECT doc_id FROM good)),
lad(rule, i, c) AS (VALUES {ladder}),
cnt AS (SELECT h.lang, l.rule, l.i, l.c, count(*) AS n, count(*) FILTER (h.v > l.c) AS bad FROM held h JOIN lad l ON l.rule = h.rule GROUP BY ALL),
tst AS (SELECT *, bad <= {each} * n AND (SELECT sum(exp(lgamma(n + 1) - lgamma(j + 1) - lgamma(n - j + 1) + j * ln({each}) + (n - j) * ln(1 - {each}))) FROM range(0, bad + 1) r(j)) <= {level} / ((SELECT count(DISTINCT lang) FROM cnt) * {len(rules)}) AS ok FROM cnt),
fst AS (SELECT *, bool_and(ok) OVER (PARTITION BY lang, rule ORDER BY i) AS all_ok FROM tst),
cut AS (SELECT lang, rule, min(c) AS c FROM fst WHERE all_ok GROUP BY 1, 2),
bad AS (SELECT DISTINCT v.k FROM (SELECT m.k, x.rule, x.v, m.lang FROM m, LATERAL (VALUES {", ".join(f"('{n}', 1.0 * {e})" for n, e in metric.items())}) x(rule, v)) v JOIN cut ON cut.lang = v.lang AND cut.rule = v.rule AND v.v > cut.c)
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, word_chars, CAST(n_symbols AS BIGINT) AS n_symbols, CAST(n_dup_lines AS BIGINT) AS n_dup_lines, CAST(n_repeat_words AS BIGINT) AS n_repeat_words, base_failed,
  NOT base_failed AND b.k NOT IN (SELECT k FROM bad) AS kept FROM b"""


_REPEATS_SQL = f"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
pc AS (SELECT k, 1000 * p AS o, substr(h, 2000 * p + 1, 2 * (1000 + {suffix_dedup.LENGTH} - 1)) AS t FROM (SELECT k, h, unnest(range(0, length(h) // 2000 + 1)) AS p FROM d)),
w AS MATERIALIZED (SELECT k, o + i AS i, hash(substr(t, 2 * i + 1, 2 * {suffix_dedup.LENGTH})) AS g FROM (SELECT k, o, t, unnest(range(0, least(1000, length(t) // 2 - {suffix_dedup.LENGTH} + 1))) AS i FROM pc WHERE length(t) >= 2 * {suffix_dedup.LENGTH})),
r AS (SELECT k, i FROM w WHERE g IN (SELECT g FROM w GROUP BY g HAVING count(*) > 1)),
s AS (SELECT k, i, sum(CASE WHEN i - p <= {suffix_dedup.LENGTH} THEN 0 ELSE 1 END) OVER (PARTITION BY k ORDER BY i) AS b FROM (SELECT k, i, coalesce(lag(i) OVER (PARTITION BY k ORDER BY i), -1000) AS p FROM r)),
sp AS (SELECT k, min(i) AS lo, max(i) + {suffix_dedup.LENGTH} AS hi FROM s GROUP BY k, b),
kp AS (SELECT k, lo, hi, coalesce(lag(hi) OVER (PARTITION BY k ORDER BY lo), 0) AS before FROM sp),
ag AS (SELECT d.k, count(kp.k) AS n, coalesce(sum(kp.hi - kp.lo), 0) AS gone, coalesce(max(kp.hi), 0) AS last, coalesce(string_agg(substr(d.h, 2 * kp.before + 1, 2 * (kp.lo - kp.before)), '' ORDER BY kp.lo), '') AS front FROM d LEFT JOIN kp ON kp.k = d.k GROUP BY d.k)
SELECT d.doc_id, CAST(length(h) // 2 AS BIGINT) AS n_bytes, CAST(gone AS BIGINT) AS n_removed, CAST(n AS BIGINT) AS n_spans, sha256(unhex(front || substr(h, 2 * last + 1))) AS kept_sha256 FROM d JOIN ag USING (k)"""

_WARC_SQL = f"""
WITH p AS (SELECT page_id, url, octet_length(encode(coalesce(html, ''))) AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest FROM pages),
g AS (SELECT payload_digest, max(page_id) AS first FROM p WHERE payload_bytes >= {warc.REVISIT_BYTES} GROUP BY 1)
SELECT page_id, url, payload_bytes, payload_digest, CASE WHEN page_id < first THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN page_id < first THEN first END AS refers_to FROM p LEFT JOIN g USING (payload_digest)"""

_CHAT_SQL = rf"""
WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, t, r, '</s>[INST] ok [/INST]' FROM (VALUES (0, 'user'), (1, 'assistant')) v(t, r)),
e AS (SELECT *, length(regexp_replace(text, '(<|\[)(\\*)(\||/?s>|/?INST\]|</?SYS>>|/?system>|/?user>|/?assistant>)', '\1\\\2\3', 'g')) AS n FROM c)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars, sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum({len(chat.START)} + length(role) + 1 + n + {len(chat.END)}) AS BIGINT) AS formatted_chars
  FROM e GROUP BY conv_id, CASE WHEN conv_id IS NULL THEN row(turn, role, text) END"""

_LEAK_SQL = rf"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[0-9a-z\x{{80}}-\x{{10FFFF}}]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(text, '{_UPPER}', '{_LOWER}'), '[0-9a-z\x{{80}}-\x{{10FFFF}}]+') AS w FROM benchmark WHERE item_id IS NOT NULL AND text IS NOT NULL),
win AS (SELECT DISTINCT item_id, least(len(w), {decontaminate.WINDOW}) AS n, array_to_string(w[i:i + {decontaminate.WINDOW} - 1], ' ') AS g FROM (SELECT *, unnest(range(1, greatest(1, len(w) - {decontaminate.WINDOW} + 1) + 1)) AS i FROM b WHERE len(w) > 0)),
sz AS (SELECT DISTINCT n FROM win),
dg AS (SELECT k, n, i, array_to_string(w[i:i + n - 1], ' ') AS g FROM (SELECT d.k, d.w, sz.n, unnest(range(1, len(d.w) - sz.n + 2)) AS i FROM d, sz WHERE len(d.w) >= sz.n)),
hit AS (SELECT dg.k, dg.i, dg.n, win.item_id FROM dg JOIN win ON win.g = dg.g AND win.n = dg.n),
nh AS (SELECT k, count(DISTINCT p) AS n FROM (SELECT k, unnest(range(i, i + n)) AS p FROM hit) GROUP BY 1),
ni AS (SELECT k, count(*) AS n, string_agg(s, ',' ORDER BY s) AS s FROM (SELECT DISTINCT k, CAST(item_id AS VARCHAR) AS s FROM hit) GROUP BY 1)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(nh.n, 0) AS n_hit, coalesce(ni.n, 0) AS n_items, sha256(coalesce(ni.s, '')) AS items_sha256, coalesce(nh.n, 0) > 0 AS contaminated FROM d LEFT JOIN nh USING (k) LEFT JOIN ni USING (k)"""

ORACLES: dict[str, str] = {
    "op4_suffix_dedup": _REPEATS_SQL,
    "op5_warc": _WARC_SQL,
    "op7_quality_rules": _quality_sql(),
    "op8_chat_format": _CHAT_SQL,
    "op10_benchmark_decontamination": _LEAK_SQL,
}
