"""SQL twins of the operators that SQL can express."""

from __future__ import annotations

from stagefilter.llm.quality import SYMBOLS, LineRules

_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
_WORDS = r"'[^\x20\x09-\x0D]+'"
_RULES = LineRules()
_WS = r"'[\x09-\x0D]'"

JACCARD = f"""WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_UPPER.lower()}'), {_WORDS}) AS w FROM documents),
i AS (SELECT doc_id, w, unnest(generate_series(1, greatest(1, len(w) - 2))) AS i FROM w WHERE len(w) > 0),
s AS (SELECT DISTINCT doc_id, CASE WHEN len(w) < 3 THEN array_to_string(w, ' ') ELSE w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] END AS g FROM i),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT x, y FROM p JOIN n m ON m.doc_id = x JOIN n k ON k.doc_id = y WHERE 100 * c >= 90 * (m.n + k.n - c)),
e AS (SELECT x, y FROM l UNION ALL SELECT y, x FROM l),
r(doc_id, other) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.doc_id, e.y FROM r JOIN e ON e.x = r.other)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, (SELECT min(other) FROM r WHERE r.doc_id = d.doc_id) AS component_id FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id"""


def _not_in(x: str, chars: str) -> str:
    return f"length(translate({x}, '{chars}', ''))"


_PHRASES = " OR ".join(f"contains(lower(x), '{p}')" for p in _RULES.boilerplate)
_LINE_FAILS = f"""((NOT right(x, 1) IN ({', '.join("'" + c.replace("'", "''") + "'" for c in '.!?:;,…"”’»)]' + "'")}) AND k < {_RULES.short_words})
OR length(x) - {_not_in('x', '!?')} > k * {_RULES.shouting} OR length(x) - {_not_in('x', '|»•>')} >= {_RULES.separators} OR (({_PHRASES}) AND k <= {_RULES.boilerplate_words}))"""

QUALITY = rf"""WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, t, regexp_extract_all(t, {_WORDS}) AS w FROM d),
g AS (SELECT doc_id, i, w[i:i + 4] AS g FROM (SELECT doc_id, w, unnest(generate_series(1, len(w) - 4)) AS i FROM w WHERE len(w) >= 5)),
c AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS n FROM g),
r AS (SELECT doc_id, count(DISTINCT i + k) AS n_repeat FROM c CROSS JOIN generate_series(0, 4) v(k) WHERE n > 1 GROUP BY doc_id),
ln AS (SELECT doc_id, raw, trim(regexp_replace(raw, {_WS}, ' ', 'g'), ' ') AS x FROM (SELECT doc_id, unnest(string_split(t, chr(10))) AS raw FROM d)),
lk AS (SELECT doc_id, raw, x, len(regexp_extract_all(x, {_WORDS})) AS k FROM ln WHERE x <> ''),
a AS (SELECT doc_id, count(*) - count(DISTINCT raw) AS dup, sum(length(x)) AS al, sum(CASE WHEN {_LINE_FAILS} THEN length(x) ELSE 0 END) AS lost FROM lk GROUP BY doc_id),
b AS (SELECT w.doc_id, len(w) AS n_words, CAST(coalesce(list_sum(list_transform(w, lambda z: length(z))), 0) AS BIGINT) AS word_chars, length(t) - {_not_in('t', SYMBOLS)} AS n_symbols, coalesce(dup, 0) AS n_dup_lines,
      coalesce(n_repeat, 0) AS n_repeat_words, coalesce(CAST(lost AS DOUBLE) / CAST(al AS DOUBLE), 0.0) AS lost_share FROM w LEFT JOIN r USING (doc_id) LEFT JOIN a USING (doc_id))
SELECT *, n_words < {_RULES.least_words} OR 100 * n_repeat_words > 20 * n_words AS base_failed, NOT (n_words < {_RULES.least_words} OR 100 * n_repeat_words > 20 * n_words) AND lost_share <= {_RULES.most_lost} AS kept FROM b"""
