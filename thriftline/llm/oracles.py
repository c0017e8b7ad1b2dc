"""DuckDB definitions of those operators that SQL can express."""

from __future__ import annotations

from thriftline.llm.quality_rules import STOP_WORDS, SYMBOLS, TABLE

_SPACE = "[ \\t\\n\\x0b\\x0c\\r]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _words(text: str) -> str:
    return f"list_filter(string_split_regex(coalesce({text}, ''), '{_SPACE}'), lambda x: x <> '')"


NEAR_DEDUP = f"""WITH RECURSIVE d AS (SELECT doc_id, {_words(f"translate(text, '{_UPPER}', '{_LOWER}')")} AS w FROM documents),
 s AS (SELECT DISTINCT doc_id, sh FROM (SELECT doc_id, unnest(CASE WHEN len(w) >= 3 THEN list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS sh FROM d)),
 n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
 p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM s a JOIN s b ON a.sh = b.sh AND a.doc_id < b.doc_id GROUP BY 1, 2),
 l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * i >= 85 * (x.n + y.n - i)),
 e AS (SELECT a, b FROM l UNION SELECT b, a FROM l),
 r AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a)
 SELECT doc_id, coalesce(n, 0) AS n_shingles, component_id, doc_id = component_id AS kept FROM (SELECT a AS doc_id, min(b) AS component_id FROM r GROUP BY 1) LEFT JOIN n USING (doc_id)"""

SUBSTRING = f"""WITH d AS (SELECT doc_id, {_words("text")} AS w FROM documents), p AS (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM d),
 x AS (SELECT doc_id, i, w[i] AS word, CASE WHEN i + 19 <= len(w) THEN array_to_string(w[i:i + 19], ' ') END AS win FROM p),
 y AS (SELECT doc_id, i, word, CASE WHEN win IS NOT NULL AND row_number() OVER (PARTITION BY win ORDER BY doc_id, i) > 1 THEN 1 ELSE 0 END AS again FROM x),
 z AS (SELECT doc_id, i, word, max(again) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN 19 PRECEDING AND CURRENT ROW) AS gone FROM y),
 g AS (SELECT doc_id, count(*) AS n, sum(gone) AS m, string_agg(word, ' ' ORDER BY i) FILTER (gone = 0) AS kept FROM z GROUP BY 1)
 SELECT doc_id, CAST(coalesce(n, 0) AS BIGINT) AS n_words, CAST(coalesce(m, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM documents LEFT JOIN g USING (doc_id)"""


def _rules() -> str:
    out = []
    for rule in TABLE:
        for bound, sign in ((rule.low, "<"), (rule.high, ">")):
            if bound is not None:
                out.append(f"(n_words >= {rule.words} AND {rule.scale} * {rule.measure} {sign} {bound} * {rule.base})")
    return " OR ".join(out)


QUALITY_RULES = f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS t, {_words("text")} AS w, list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: length(regexp_replace(x, '{_SPACE}', '', 'g')) > 0) AS lines FROM documents),
 p AS (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM d), x AS (SELECT doc_id, i, CASE WHEN i + 7 <= len(w) THEN array_to_string(w[i:i + 7], ' ') END AS win FROM p),
 y AS (SELECT doc_id, i, CASE WHEN win IS NOT NULL AND count(*) OVER (PARTITION BY doc_id, win) > 1 THEN 1 ELSE 0 END AS again FROM x),
 z AS (SELECT doc_id, max(again) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN 7 PRECEDING AND CURRENT ROW) AS hit FROM y), r AS (SELECT doc_id, CAST(sum(hit) AS BIGINT) AS n_repeat_words FROM z GROUP BY 1),
 m AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(regexp_replace(t, '{_SPACE}', '', 'g')) AS BIGINT) AS word_chars, CAST(length(t) - length(translate(t, '{SYMBOLS}', '')) AS BIGINT) AS n_symbols,
  CAST(length(t) - length(translate(t, '0123456789', '')) AS BIGINT) AS n_digits, CAST(len(lines) AS BIGINT) AS n_lines, CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines,
  CAST(len(list_filter(w, lambda x: list_contains([{", ".join(f"'{s}'" for s in sorted(set(STOP_WORDS)))}], lower(x)))) AS BIGINT) AS n_stop_words, coalesce(n_repeat_words, 0) AS n_repeat_words FROM d LEFT JOIN r USING (doc_id)),
 b AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM m)
 SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND NOT ({_rules()}) AS kept FROM b"""

_ALNUM = "[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+"


def _alnum(text: str) -> str:
    return f"regexp_extract_all(translate(coalesce({text}, ''), '{_UPPER}', '{_LOWER}'), '{_ALNUM}')"


DECONTAMINATE = f"""WITH b AS (SELECT CAST(item_id AS VARCHAR) AS item, {_alnum("text")} AS w FROM benchmark), bw AS (SELECT item, w, least(len(w), 10) AS n, unnest(range(1, len(w) - least(len(w), 10) + 2)) AS s FROM b WHERE len(w) > 0),
 win AS (SELECT DISTINCT item, n, array_to_string(w[s:s + n - 1], ' ') AS t FROM bw), sizes AS (SELECT DISTINCT n FROM win),
 d AS (SELECT doc_id, {_alnum("text")} AS w FROM documents), dw AS (SELECT doc_id, n, w, unnest(range(1, len(w) - n + 2)) AS s FROM d, sizes WHERE len(w) >= n),
 hit AS (SELECT doc_id, s, dw.n, item FROM (SELECT doc_id, s, n, array_to_string(w[s:s + n - 1], ' ') AS t FROM dw) dw JOIN win ON win.t = dw.t AND win.n = dw.n),
 pos AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS p FROM hit) GROUP BY 1),
 it AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, item FROM hit) GROUP BY 1)
 SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items, sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated FROM d LEFT JOIN pos USING (doc_id) LEFT JOIN it USING (doc_id)"""

PACK_CONVERSATIONS = f"""WITH w AS (SELECT conv_id, role, len({_words("text")}) AS n FROM conversations),
 e AS (SELECT conv_id, CAST(sum(n) AS BIGINT) AS n_tokens, CAST(sum(CASE WHEN role = 'assistant' THEN n ELSE 0 END) AS BIGINT) AS n_loss FROM w GROUP BY 1)
 SELECT conv_id, n_tokens, n_loss, n_tokens <= 4096 AND n_loss <= 2048 AS fits, true AS kept_limits FROM e"""
