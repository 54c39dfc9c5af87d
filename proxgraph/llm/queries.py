"""Driver queries of the operators and their DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import context_mixing, decontaminate, host_quality, jaccard_join, license_scan, line_dedup, mixing, substring_dedup, url_filter, word_pieces
from .common import load


#: Vocabulary file of the word-piece query.
VOCABULARY = "/opt/tokenizers/word_bpe_49k.json"


def op1_context_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return context_mixing.score_documents(load(spark, sf_dir, "documents"))


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = line_dedup.dedup_lines(load(spark, sf_dir, "documents"), min_words=line_dedup.PASSAGE_WORDS)
    return out.select("doc_id", "n_lines", "n_removed_lines", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = substring_dedup.dedup_substrings(load(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def op4_host_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = host_quality.judge(load(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "host_verdict")


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(load(spark, sf_dir, "documents"))


def op6_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = decontaminate.decontaminate(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark"))
    return out.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"), "contaminated")


def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.filter_urls(load(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict")


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_licenses(load(spark, sf_dir, "documents"))


def op9_word_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return word_pieces.count_pieces(load(spark, sf_dir, "documents"), VOCABULARY)


def op10_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.near_duplicates(load(spark, sf_dir, "documents"))


def queries() -> dict:
    found = (op1_context_mixing, op2_line_dedup, op3_substring_dedup, op4_host_quality, op5_mixing, op6_decontaminate, op7_url_filter, op8_license_scan, op9_word_pieces, op10_jaccard_join)
    return {f.__name__: f for f in found}


_ALPHA = "'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'"
_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
_LOW_WORDS = rf"regexp_extract_all(translate(coalesce(text, ''), {_ALPHA}), '[^\x20\x09-\x0D]+')"
_NORMAL = rf"regexp_extract_all(translate(coalesce(text, ''), {_ALPHA}), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

_SQL2 = r"""
WITH a AS (SELECT doc_id, text, string_split(text, chr(10)) AS ls FROM documents),
l AS (SELECT doc_id, i, ls[i] AS x FROM (SELECT doc_id, ls, unnest(range(1, len(ls) + 1)) AS i FROM a)),
f AS (SELECT doc_id, i, x, row_number() OVER (PARTITION BY doc_id ORDER BY i) AS p FROM l WHERE regexp_matches(x, '[^\x20\x09-\x0D]')),
w AS (SELECT doc_id, p, x, lead(x) OVER (PARTITION BY doc_id ORDER BY p) AS y FROM f),
later AS (SELECT doc_id, p FROM (SELECT doc_id, p, row_number() OVER (PARTITION BY x, y ORDER BY doc_id, p) AS k FROM w WHERE y IS NOT NULL) WHERE k > 1),
long AS (SELECT doc_id, i, row_number() OVER (PARTITION BY x ORDER BY doc_id, i) AS k FROM l WHERE len(regexp_extract_all(x, '[^\x20\x09-\x0D]+')) >= 50),
gone AS (SELECT doc_id, i FROM f JOIN (SELECT doc_id, unnest([p, p + 1]) AS p FROM later) USING (doc_id, p) UNION SELECT doc_id, i FROM long WHERE k > 1),
k AS (SELECT l.doc_id, string_agg(l.x, chr(10) ORDER BY l.i) AS kept FROM l LEFT JOIN gone g ON g.doc_id = l.doc_id AND g.i = l.i WHERE g.i IS NULL GROUP BY 1)
SELECT a.doc_id, coalesce(n.c, 0) AS n_lines, coalesce(r.c, 0) AS n_removed_lines, sha256(coalesce(k.kept, '')) AS kept_sha256
FROM a LEFT JOIN k USING (doc_id) LEFT JOIN (SELECT doc_id, count(*) AS c FROM f GROUP BY 1) n USING (doc_id)
LEFT JOIN (SELECT doc_id, count(*) AS c FROM gone GROUP BY 1) r USING (doc_id)"""

_SQL3 = rf"""
WITH a AS (SELECT doc_id, {_WORDS} AS ws FROM documents),
w AS (SELECT doc_id, i, hash(array_to_string(ws[i:i+49], ' ')) AS g FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 48)) AS i FROM a)),
later AS (SELECT doc_id, i FROM (SELECT doc_id, i, min(doc_id) OVER (PARTITION BY g) AS f FROM w) WHERE f < doc_id),
gone AS (SELECT DISTINCT doc_id, unnest(range(i, i + 50)) AS p FROM later),
n AS (SELECT doc_id, count(*) AS c FROM gone GROUP BY 1),
k AS (SELECT x.doc_id, string_agg(x.w, ' ' ORDER BY x.p) AS kept FROM (SELECT doc_id, unnest(ws) AS w, unnest(range(1, len(ws) + 1)) AS p FROM a) x
      LEFT JOIN gone g ON g.doc_id = x.doc_id AND g.p = x.p WHERE g.p IS NULL GROUP BY 1)
SELECT a.doc_id, len(ws)::BIGINT AS n_words, coalesce(n.c, 0)::BIGINT AS n_removed, sha256(coalesce(k.kept, '')) AS kept_sha256
FROM a LEFT JOIN n USING (doc_id) LEFT JOIN k USING (doc_id)"""

_SQL4 = rf"""
WITH a AS (SELECT doc_id, source, coalesce(text, '') AS text, {_WORDS} AS ws FROM documents),
g AS (SELECT doc_id, i, ws[i] || ' ' || ws[i+1] || ' ' || ws[i+2] AS k FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 1)) AS i FROM a)),
rep AS (SELECT doc_id, count(DISTINCT p) AS c FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS p FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, k) AS m FROM g) WHERE m > 1) GROUP BY 1),
ln AS (SELECT doc_id, sum(m) AS n_lines, sum(m - 1) AS dup FROM (SELECT doc_id, x, count(*) AS m FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS x FROM a) WHERE regexp_matches(x, '[^\x20\x09-\x0D]') GROUP BY 1, 2) GROUP BY 1),
b AS (SELECT a.doc_id, a.source, len(ws)::BIGINT AS n_words, length(regexp_replace(text, '[\x20\x09-\x0D]+', '', 'g'))::BIGINT AS word_chars,
      (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols, coalesce(ln.n_lines, 0)::BIGINT AS n_lines,
      coalesce(ln.dup, 0)::BIGINT AS n_dup_lines, coalesce(rep.c, 0)::BIGINT AS n_repeat_words FROM a LEFT JOIN ln USING (doc_id) LEFT JOIN rep USING (doc_id)),
j AS (SELECT *, (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed, 10 * n_symbols > n_words AS r1, 10 * n_dup_lines > 3 * n_lines AS r2,
      (word_chars < 3 * n_words OR word_chars > 10 * n_words) AS r3 FROM b),
h AS (SELECT source, count(*) AS n, unnest([0, 1, 2, 3]) AS r, unnest([sum(base_failed::INT), sum(r1::INT), sum(r2::INT), sum(r3::INT)]) AS f FROM j GROUP BY source),
m AS (SELECT r, least(greatest(avg(f / n), 1e-4), 1 - 1e-4) AS mu, var_pop(f / n) AS v FROM h GROUP BY r),
s AS (SELECT r, mu, CASE WHEN v > 0 THEN least(greatest(mu * (1 - mu) / v - 1, 1), 1000) ELSE 1000 END AS k FROM m),
p AS (SELECT source, max(CASE WHEN r = 0 THEN (f + mu * k) / (n + k) END) AS hard, max(CASE WHEN r > 0 THEN (f + mu * k) / (n + k) END) AS soft FROM h JOIN s USING (r) GROUP BY source),
q AS (SELECT source, CASE WHEN hard > 0.9 THEN 'blocked' WHEN soft > 0.5 THEN 'strict' ELSE 'open' END AS host_verdict FROM p)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, host_verdict,
       (NOT base_failed AND host_verdict <> 'blocked' AND NOT (host_verdict = 'strict' AND (r1 OR r2 OR r3))) AS kept
FROM j JOIN q ON j.source IS NOT DISTINCT FROM q.source"""

_SQL6 = rf"""
WITH it AS (SELECT item_id, {_NORMAL} AS ws FROM benchmark),
iw AS (SELECT DISTINCT item_id, k, array_to_string(ws[i:i+k-1], ' ') AS g FROM (SELECT item_id, ws, least(10, len(ws)) AS k, unnest(range(1, len(ws) - least(10, len(ws)) + 2)) AS i FROM it WHERE len(ws) > 0)),
d AS (SELECT doc_id, {_NORMAL} AS ws FROM documents),
dw AS (SELECT doc_id, i, k, array_to_string(ws[i:i+k-1], ' ') AS g FROM (SELECT doc_id, ws, k, unnest(range(1, len(ws) - k + 2)) AS i FROM d, (SELECT DISTINCT k FROM iw) WHERE len(ws) >= k)),
hit AS (SELECT DISTINCT doc_id, i, k, item_id FROM dw JOIN iw USING (k, g)),
c AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + k)) AS p FROM hit) GROUP BY 1),
t AS (SELECT doc_id, count(*) AS n, string_agg(x, ',' ORDER BY x) AS s FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS x FROM hit) GROUP BY 1)
SELECT d.doc_id, len(ws)::BIGINT AS n_words, coalesce(c.n, 0)::BIGINT AS n_hit, coalesce(t.n, 0)::BIGINT AS n_items, sha256(coalesce(t.s, '')) AS items_sha256, coalesce(c.n, 0) > 0 AS contaminated
FROM d LEFT JOIN c USING (doc_id) LEFT JOIN t USING (doc_id)"""


def _sql7() -> str:
    import re

    rules = sorted(url_filter.RULES, key=lambda r: -len(r[1]) - len(r[2]))
    fits = [(v, h + p, f"(host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}')") for v, h, p in rules]
    signs = lambda g: re.findall(r"\\.|.", g, re.S)
    as_regex = lambda g: "(?s)" + "".join(".*" if c == "*" else "." if c == "?" else re.escape(c[-1]) for c in signs(g))
    any_of = lambda verdict: " OR ".join(f"regexp_full_match(canonical, '{as_regex(g)}')" for v, g in url_filter.GLOBS if v == verdict)
    return rf"""
WITH u AS (SELECT page_id, translate(regexp_extract(coalesce(url, ''), '://([^/?#]*)', 1), {_ALPHA}) AS host, regexp_extract(coalesce(url, ''), '://[^/?#]*([^?#]*)', 1) AS path,
           regexp_extract(coalesce(url, ''), '://[^?#]*(\?[^#]*)', 1) AS query FROM pages),
c AS (SELECT *, host || path || query AS canonical FROM u)
SELECT page_id, host, path, CASE {" ".join(f"WHEN {f} THEN '{r}'" for _, r, f in fits)} END AS rule,
       CASE {" ".join(f"WHEN {f} THEN '{v}'" for v, _, f in fits)} WHEN {any_of("allow")} THEN 'allow' WHEN {any_of("block")} THEN 'block' ELSE 'allow' END AS verdict FROM c"""


_SQL10 = rf"""
WITH RECURSIVE a AS (SELECT doc_id, {_LOW_WORDS} AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, g FROM (SELECT doc_id, array_to_string(ws[i:i+4], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 3, 2))) AS i FROM a WHERE len(ws) > 0))),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
o AS (SELECT x.doc_id AS d, y.doc_id AS e, count(*) AS k FROM s x JOIN s y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY 1, 2),
l AS (SELECT d, e FROM o JOIN n p ON p.doc_id = d JOIN n q ON q.doc_id = e WHERE 100 * k >= 80 * (p.n + q.n - k)),
r AS (SELECT doc_id AS d, doc_id AS e FROM documents UNION SELECT r.d, l.e FROM r JOIN l ON r.e = l.d)
SELECT a.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, (SELECT min(r.e) FROM r WHERE r.d = a.doc_id) AS component_id FROM a LEFT JOIN n USING (doc_id)"""


def oracle_sql() -> dict[str, str]:
    return {"op2_line_dedup": _SQL2, "op3_substring_dedup": _SQL3, "op4_host_quality": _SQL4, "op6_decontaminate": _SQL6, "op7_url_filter": _sql7(), "op10_jaccard_join": _SQL10}
