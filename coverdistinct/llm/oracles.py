"""DuckDB SQL for the operators that SQL can express, written apart from their Spark plans."""

from __future__ import annotations

from . import mixing, quality, urlfilter

_WORDS = r"regexp_extract_all({}, '[^\x20\x09-\x0D]+')"
_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

NEAR_DUPLICATES = f"""
WITH RECURSIVE d AS (SELECT doc_id, {_WORDS.format(_LOWER)} AS w FROM documents),
s AS (SELECT doc_id, unnest(list_distinct(CASE WHEN len(w) >= 3 THEN list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END)) AS g FROM d),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 85 * (x.n + y.n - c)),
e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
r AS (SELECT doc_id AS id, doc_id AS seen FROM documents UNION SELECT r.id, e.b FROM r JOIN e ON e.a = r.seen),
m AS (SELECT id, min(seen) AS component_id FROM r GROUP BY id)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, m.component_id, d.doc_id = m.component_id AS kept FROM d LEFT JOIN n ON n.doc_id = d.doc_id JOIN m ON m.id = d.doc_id
"""

REPEATS = """
WITH b AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
p AS (SELECT doc_id, h, unnest(range(0, len(h) // 2 - 99)) AS i FROM b WHERE len(h) >= 200),
w AS (SELECT doc_id, i, md5(substr(h, 2 * i + 1, 200)) AS k FROM p),
r AS (SELECT doc_id, i FROM (SELECT doc_id, i, row_number() OVER (PARTITION BY k ORDER BY doc_id, i) AS n FROM w) WHERE n > 1),
g AS (SELECT doc_id, i, sum(CASE WHEN i - prev <= 100 THEN 0 ELSE 1 END) OVER (PARTITION BY doc_id ORDER BY i) AS run FROM (SELECT *, lag(i) OVER (PARTITION BY doc_id ORDER BY i) AS prev FROM r)),
t AS (SELECT doc_id, run, min(i) AS a, max(i) + 100 AS z FROM g GROUP BY ALL),
c AS (SELECT doc_id, coalesce(lag(z) OVER (PARTITION BY doc_id ORDER BY a), 0) AS f, a AS e FROM t UNION ALL SELECT doc_id, max(z), NULL FROM t GROUP BY doc_id),
k AS (SELECT doc_id, string_agg(CASE WHEN e IS NULL THEN substr(h, 2 * f + 1) ELSE substr(h, 2 * f + 1, 2 * (e - f)) END, '' ORDER BY f) AS k FROM c JOIN b USING (doc_id) GROUP BY doc_id),
x AS (SELECT doc_id, sum(z - a) AS n_removed, count(*) AS n_spans FROM t GROUP BY doc_id)
SELECT b.doc_id, len(h) // 2 AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, coalesce(n_spans, 0) AS n_spans, sha256(unhex(coalesce(k, h))) AS kept_sha256
FROM b LEFT JOIN k USING (doc_id) LEFT JOIN x USING (doc_id)
"""


def _cases(column: str, weights: dict[str, float]) -> str:
    return "CASE " + " ".join(f"WHEN {column} = '{k}' THEN {v}::DOUBLE" for k, v in weights.items()) + " ELSE 1.0::DOUBLE END" if weights else "1.0::DOUBLE"


def _fill(children: str, parent: str, level: str, weights: dict) -> str:
    """Children with ``given`` and ``room`` -> with ``budget``: in order of filling up."""
    part = f"PARTITION BY {parent} " if parent else ""
    a = f"SELECT *, {_cases(level, weights.get(level, {}))} AS weight FROM ({children})"
    b = f"SELECT *, room / weight AS full_at FROM ({a})"
    c = (f"SELECT *, coalesce(sum(room) OVER ({part}ORDER BY full_at, {level} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + full_at * sum(weight) OVER ({part}ORDER BY full_at, {level} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) <= given AS is_full FROM ({b})")
    d = f"SELECT *, coalesce(sum(room) FILTER (is_full) OVER ({part}), 0) AS taken, sum(weight) FILTER (NOT is_full) OVER ({part}) AS heavy FROM ({c})"
    return f"SELECT * EXCLUDE (weight, full_at, is_full, taken, heavy), greatest(CASE WHEN is_full THEN room ELSE floor((given - taken) * weight / heavy) END, 0) AS budget FROM ({d})"


def _mixing(share: float = mixing.SHARE, epochs: int = mixing.EPOCHS, weights: dict = mixing.WEIGHTS, seed: int = mixing.SEED) -> str:
    number = r"CAST(nullif(regexp_extract(source, '^src(\d{1,9})$', 1), '') AS INT)"
    rows = (f"SELECT doc_id, CASE WHEN {number} < 10 THEN 'web' WHEN {number} < 15 THEN 'books' WHEN {number} < 20 THEN 'forum' ELSE 'other' END AS domain, coalesce(lang, '{mixing.NONE}') AS language, source, "
            f"len({_WORDS.format('text')}) AS n_tokens FROM (SELECT doc_id, lang, coalesce(text, '') AS text, coalesce(source, '{mixing.NONE}') AS source FROM documents)")
    top = _fill("SELECT domain, sum(room) AS room, any_value(given) AS given FROM leaf, total GROUP BY domain", "", "domain", weights)
    mid = _fill("SELECT leaf.domain, language, sum(leaf.room) AS room, any_value(top.budget) AS given FROM leaf JOIN top ON leaf.domain = top.domain GROUP BY ALL", "domain", "language", weights)
    low = _fill("SELECT leaf.*, mid.budget AS given FROM leaf JOIN mid ON leaf.domain = mid.domain AND leaf.language = mid.language", "domain, language", "source", weights)
    return f"""
WITH d AS ({rows}), leaf AS (SELECT domain, language, source, CAST(sum(n_tokens) AS BIGINT) AS tokens, CAST(sum(n_tokens) * {epochs} AS DOUBLE) AS room FROM d GROUP BY ALL),
total AS (SELECT floor(coalesce(sum(tokens), 0) * {share!r}::DOUBLE)::DOUBLE AS given FROM leaf), top AS ({top}), mid AS ({mid}), low AS ({low}),
plan AS (SELECT domain, language, source, CASE WHEN tokens > 0 THEN CAST(floor(budget / greatest(tokens, 1)) AS BIGINT) ELSE 0 END AS epochs, CAST(budget AS BIGINT) AS budget, tokens FROM low),
o AS (SELECT d.*, epochs, budget - epochs * tokens AS rest, md5(coalesce(CAST(doc_id AS VARCHAR), '{mixing.NONE}') || '|' || n_tokens || '|' || epochs || '|{seed}') AS place FROM d JOIN plan USING (domain, language, source)),
u AS (SELECT *, sum(n_tokens) OVER (PARTITION BY domain, language, source ORDER BY place, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto FROM o),
c AS (SELECT *, epochs + CASE WHEN rest > 0 AND upto <= rest THEN 1 ELSE 0 END AS copies FROM u)
SELECT doc_id, domain, language, source, CAST(n_tokens AS BIGINT) AS n_tokens, CAST(unnest(range(0, copies)) AS INT) AS epoch FROM c WHERE copies > 0
"""


def _quality(risk: float = quality.RISK / len(quality.GRID), level: float = quality.LEVEL) -> str:
    w = _WORDS.format("text")
    grid = " UNION ALL ".join(f"SELECT '{rule}' AS rule, {i} AS i, {cut}::DOUBLE AS cutoff" for rule, cuts in quality.GRID.items() for i, cut in enumerate(cuts))
    rates = ", ".join(f"{c} / greatest(n_words, 1)::DOUBLE AS {r}" for r, c in (("symbols_per_word", "n_symbols"), ("dup_lines_per_word", "n_dup_lines"), ("repeat_share", "n_repeat_words"), ("word_length", "word_chars")))
    long_ = " UNION ALL ".join(f"SELECT doc_id, lang, '{r}' AS rule, {r} AS x FROM rated" for r in quality.GRID)
    return rf"""
WITH d AS (SELECT doc_id, lang, text, {w} AS w FROM (SELECT doc_id, lang, coalesce(text, '') AS text FROM documents)),
win AS (SELECT doc_id, i, array_to_string(w[i:i + 7], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM d WHERE len(w) > 8)),
rep AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM win) WHERE c > 1),
cov AS (SELECT doc_id, CAST(sum(8 - greatest(0, coalesce(8 - (i - prev), 0))) AS BIGINT) AS n FROM (SELECT *, lag(i) OVER (PARTITION BY doc_id ORDER BY i) AS prev FROM rep) GROUP BY doc_id),
m AS (SELECT d.doc_id, lang, CAST(len(w) AS BIGINT) AS n_words, CAST(length(regexp_replace(text, '[\x20\x09-\x0D]', '', 'g')) AS BIGINT) AS word_chars, CAST(length(text) - length(translate(text, '#*$%&|<>', '')) AS BIGINT) AS n_symbols,
  CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines, coalesce(cov.n, 0) AS n_repeat_words
  FROM (SELECT *, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines FROM d) d LEFT JOIN cov ON cov.doc_id = d.doc_id),
rated AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed, {rates} FROM m),
long AS ({long_}), grid AS ({grid}),
good AS (SELECT doc_id FROM labels GROUP BY doc_id HAVING max(quality) = 1),
t AS (SELECT lang, rule, i, cutoff, count(*) AS n, count(*) FILTER (x > cutoff) AS k FROM long JOIN grid USING (rule) WHERE doc_id IN (SELECT doc_id FROM good) AND doc_id IN (SELECT doc_id FROM rated WHERE NOT base_failed) GROUP BY ALL),
tail AS (SELECT *, CASE WHEN k <= n * {risk!r}::DOUBLE THEN list_sum(list_transform(range(0, k + 1), lambda j: exp(lgamma(n + 1) - lgamma(j + 1) - lgamma(n - j + 1) + j * ln({risk!r}::DOUBLE) + (n - j) * ln(1 - {risk!r}::DOUBLE)))) ELSE 1.0 END AS p FROM t),
ok AS (SELECT *, p <= {level!r}::DOUBLE / ({len(quality.GRID)} * (SELECT count(DISTINCT coalesce(lang, '~null')) FROM t)) AS passes FROM tail),
cut AS (SELECT lang, rule, max(i) AS i FROM (SELECT *, min(CASE WHEN NOT passes THEN i END) OVER (PARTITION BY lang, rule) AS stop FROM ok) WHERE i < coalesce(stop, 1000) GROUP BY ALL),
bad AS (SELECT DISTINCT long.doc_id FROM long JOIN cut ON long.lang IS NOT DISTINCT FROM cut.lang AND long.rule = cut.rule JOIN grid ON grid.rule = cut.rule AND grid.i = cut.i WHERE long.x > grid.cutoff)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND doc_id NOT IN (SELECT doc_id FROM bad) AS kept FROM rated
"""


ORACLE_SQL = {
    "op2_minhash_neardup": NEAR_DUPLICATES,
    "op3_suffix_dedup": REPEATS,
    "op4_url_filters": urlfilter.SQL,
    "op8_mixing": _mixing(),
    "op10_quality_rules": _quality(),
}
