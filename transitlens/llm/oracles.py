"""DuckDB texts of those corpus queries that SQL can express."""

from __future__ import annotations

from .url_filters import DAMPING, RULES, STEPS, UNIT

_W = r"[^\x20\x09-\x0D]+"

QUALITY_RULES = rf"""
WITH d AS (SELECT doc_id, source, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '{_W}') AS words FROM documents),
win AS (SELECT doc_id, i, list_slice(words, i, i + 7) AS w FROM (SELECT doc_id, words, unnest(range(1, len(words) - 6)) AS i FROM d WHERE len(words) >= 8)),
twice AS (SELECT doc_id, unnest(list(i)) AS i FROM win GROUP BY doc_id, w HAVING count(*) > 1),
rep AS (SELECT doc_id, count(DISTINCT p) AS n_repeat_words FROM (SELECT doc_id, unnest(range(i, i + 8)) AS p FROM twice) GROUP BY 1),
m AS (
  SELECT d.doc_id, source, CAST(len(words) AS BIGINT) AS n_words, CAST(length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g')) AS BIGINT) AS word_chars,
         CAST(length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
         CAST(len(list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '{_W}'))) - len(list_distinct(list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '{_W}')))) AS BIGINT) AS n_dup_lines,
         CAST(coalesce(n_repeat_words, 0) AS BIGINT) AS n_repeat_words
  FROM d LEFT JOIN rep USING (doc_id)),
f AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM m),
failed AS (SELECT source, r.rule, CAST(r.bad AS BIGINT) AS bad FROM (SELECT source, unnest([
  {{'rule': 1, 'bad': n_words < 20}}, {{'rule': 2, 'bad': 100 * n_repeat_words > 30 * n_words}}, {{'rule': 3, 'bad': 10 * n_symbols > word_chars}}, {{'rule': 4, 'bad': 20 * n_dup_lines > n_words}}]) AS r FROM m)),
h AS (SELECT source, rule, count(*) AS n, sum(bad) AS bad FROM failed GROUP BY 1, 2),
a AS (SELECT rule, CAST(sum(bad) AS DOUBLE) / sum(n) AS mean, sum(CAST(bad AS DOUBLE) * bad / n) / sum(n) - (CAST(sum(bad) AS DOUBLE) / sum(n)) ** 2 AS spread, count(*) AS k, sum(n) AS total FROM h GROUP BY 1),
b AS (SELECT rule, mean, spread - mean * (1 - mean) * (k - 1) / total AS between_hosts FROM a),
p AS (SELECT rule, mean, CASE WHEN between_hosts <= 0 THEN 1e6 ELSE least(1e6, greatest(1.0, mean * (1 - mean) / between_hosts - 1)) END AS weight FROM b),
e AS (SELECT source, n + weight AS docs, (bad + mean * weight) / (n + weight) AS rate FROM h JOIN p USING (rule)),
v AS (SELECT source, bool_or(rate - 1.645 * sqrt(rate * (1 - rate) / (docs + 1)) > 0.5) AS rejected FROM e GROUP BY 1)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND NOT rejected AS kept
FROM f JOIN v ON f.source IS NOT DISTINCT FROM v.source"""

TOPK_SEARCH = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * CAST(x AS DOUBLE))) AS q FROM embeddings
  WHERE vec_id IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT a.vec_id AS query_id, b.vec_id, CAST(list_dot_product(a.q, b.q) AS BIGINT) AS score FROM v a JOIN v b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id)
SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s
QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) <= 5"""

JACCARD_JOIN = rf"""
WITH RECURSIVE d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_W}') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, list_slice(w, i, i + 4) AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(2, len(w) - 3))) AS i FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
common AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
link AS (SELECT a, b FROM common JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 80 * (x.n + y.n - c)),
edge AS (SELECT a, b FROM link UNION ALL SELECT b, a FROM link),
reach AS (SELECT a, b FROM edge UNION SELECT r.a, e.b FROM reach r JOIN edge e ON r.b = e.a)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, least(d.doc_id, coalesce(r.low, d.doc_id)) AS component_id
FROM d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN (SELECT a, min(b) AS low FROM reach GROUP BY 1) r ON r.a = d.doc_id"""


def _steps(name: str, verdict: str, src: str, dst: str) -> str:
    """The propagation, a table expression for each step, as long as there are links."""
    text = f"""{name}_n AS (SELECT host, count(*) AS n FROM p WHERE ruled = '{verdict}' AND host <> '' GROUP BY 1),
{name}_seed AS (SELECT host, n * {UNIT} // (SELECT sum(n) FROM {name}_n) AS r FROM {name}_n),
{name}_out AS (SELECT {src} AS s, {dst} AS d, n, sum(n) OVER (PARTITION BY {src}) AS total FROM link),
{name}_0 AS (SELECT host, CAST(r AS BIGINT) AS r FROM {name}_seed)"""
    for i in range(STEPS):
        text += f""",
{name}_{i + 1} AS (SELECT host, CAST(sum(r) AS BIGINT) AS r FROM (
  SELECT d AS host, sum(r * n // total) * {DAMPING} // 100 AS r FROM {name}_out JOIN {name}_{i} ON host = s GROUP BY d
  UNION ALL SELECT host, r * (CASE WHEN (SELECT count(*) FROM link) = 0 THEN 100 ELSE {100 - DAMPING} END) // 100 FROM {name}_seed) GROUP BY 1)"""
    return text


def url_filters() -> str:
    cases = {"rule": "", "ruled": ""}
    for what, r in sorted(RULES, key=lambda x: (-len(x[1]), x[1])):
        host, path = r.split("/", 1)
        fits = f"WHEN (host = '{host}' OR ends_with(host, '.{host}')) AND starts_with(path, '/{path}') THEN"
        cases["rule"] += f" {fits} '{r}'"
        cases["ruled"] += f" {fits} '{what}'"
    low = "'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'"
    return rf"""
WITH u AS (SELECT page_id, html, CASE WHEN contains(url, '://') THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
hp AS (SELECT page_id, html, translate(regexp_extract(rest, '^[^/?#]*'), {low}) AS host, regexp_extract(substr(rest, length(regexp_extract(rest, '^[^/?#]*')) + 1), '^[^?#]*') AS path FROM u),
p AS (SELECT *, CASE {cases["rule"]} END AS rule, CASE {cases["ruled"]} END AS ruled FROM hp),
target AS (SELECT host AS src, translate(unnest(regexp_extract_all(coalesce(html, ''), '(?i)(?:href|src)\s*=\s*["'']?(?:[a-z][a-z0-9+.-]*:)?//([^/?#"''>\s]+)', 1)), {low}) AS dst FROM p),
link AS (SELECT src, dst, count(*) AS n FROM target WHERE src <> '' AND dst <> '' AND src <> dst GROUP BY 1, 2),
{_steps("t", "allow", "src", "dst")},
{_steps("b", "block", "dst", "src")}
SELECT page_id, p.host, path, rule, coalesce(ruled, CASE WHEN coalesce(y.r, 0) > 2 * coalesce(x.r, 0) THEN 'block' ELSE 'allow' END) AS verdict,
       coalesce(x.r, 0) AS trust, coalesce(y.r, 0) AS distrust
FROM p LEFT JOIN t_{STEPS} x ON x.host = p.host LEFT JOIN b_{STEPS} y ON y.host = p.host"""
