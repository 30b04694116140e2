"""DuckDB SQL with the rows of the training-data queries that SQL can express."""

from __future__ import annotations

from graphrefresh.llm import mixing, quality

_WORDS = r"list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> '')"

OP1 = r"""
WITH c AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok' UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'
), t AS (
  SELECT *, lag(role) OVER (PARTITION BY conv_id ORDER BY turn, role, text) AS prev,
    replace(replace(replace(text, '\', '\\'), '### ', '#\## '), '</turn>', '<\/turn>') AS esc
  FROM c
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  sum(length(esc) + CASE role WHEN 'user' THEN 10 WHEN 'system' THEN 12 WHEN 'assistant' THEN 15 ELSE 11 + 2 + length(role) END + 9)::BIGINT AS formatted_chars,
  bool_and(CASE role WHEN 'system' THEN prev IS NULL WHEN 'user' THEN coalesce(prev, 'system') IN ('system', 'assistant') WHEN 'assistant' THEN prev = 'user' ELSE false END IS TRUE)
    AND arg_max(role, (turn, role, text)) = 'assistant' AS valid
FROM t GROUP BY conv_id
"""

OP2 = rf"""
WITH d AS (
  SELECT row_number() OVER () AS r, doc_id, source, coalesce(text, '') AS text, {_WORDS} AS w,
    list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines
  FROM documents
), win AS (
  SELECT r, i, w[i] AS a, w[i + 1] AS b, w[i + 2] AS c FROM (SELECT r, w, unnest(range(1, len(w) - 1)) AS i FROM d WHERE len(w) > 2)
), twice AS (
  SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, a, b, c) AS n FROM win) WHERE n > 1
), rep AS (
  SELECT r, count(DISTINCT p) AS n_repeat_words FROM (SELECT r, unnest([i, i + 1, i + 2]) AS p FROM twice) GROUP BY r
), l AS (
  SELECT r, source, text, x AS line, trim(regexp_replace(regexp_replace(lower(x), '[0-9]', '0', 'g'), '[\x20\x09-\x0D]+', ' ', 'g')) AS norm FROM (SELECT r, source, text, unnest(lines) AS x FROM d)
), hosts AS (SELECT source, count(DISTINCT text) AS docs FROM d GROUP BY source
), hot AS (
  SELECT f.source, f.norm FROM (SELECT source, norm, count(DISTINCT text) AS n FROM l GROUP BY source, norm) f JOIN hosts h ON f.source IS NOT DISTINCT FROM h.source
  WHERE f.n >= {quality.MIN_DOCS} AND f.n >= {quality.SHARE} * h.docs
), lost AS (
  SELECT r, sum(len(regexp_extract_all(line, '[^\x20\x09-\x0D]+'))) AS lost_words FROM l WHERE EXISTS (SELECT 1 FROM hot WHERE hot.source IS NOT DISTINCT FROM l.source AND hot.norm = l.norm) GROUP BY r
), b AS (
  SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars,
    len(regexp_extract_all(text, '[#*$%&|<>]'))::BIGINT AS n_symbols, (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines,
    coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words, coalesce(lost_words, 0)::BIGINT AS lost_words
  FROM d LEFT JOIN rep USING (r) LEFT JOIN lost USING (r)
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_words < {quality.MIN_WORDS} OR 100 * n_repeat_words > 50 * n_words AS base_failed, lost_words,
  NOT (n_words < {quality.MIN_WORDS} OR 100 * n_repeat_words > 50 * n_words) AND n_words - lost_words >= {quality.KEEP_SHARE} * n_words AS kept
FROM b
"""


def _weights(level: str) -> str:
    return f"(CASE {level} " + " ".join(f"WHEN '{k}' THEN {v}" for k, v in mixing.WEIGHTS[level].items()) + " ELSE 1 END)"


def _deal(name: str, source: str, parents: list[str], level: str) -> str:
    by = f"PARTITION BY {', '.join(parents)}" if parents else ""
    keys = ", ".join([*parents, level])
    return f"""{name}_w AS (
  SELECT *, {_weights(level)} AS w, coalesce(sum(cap) OVER ({by} ORDER BY cap / {_weights(level)}, {level} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS cb,
    sum({_weights(level)}) OVER ({by}) - coalesce(sum({_weights(level)}) OVER ({by} ORDER BY cap / {_weights(level)}, {level} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS wl
  FROM {source}
), {name}_f AS (SELECT *, cap * wl <= w * greatest(given - cb, 0) AS is_full FROM {name}_w
), {name}_o AS (SELECT *, min(CASE WHEN NOT is_full THEN {{'cb': cb, 'wl': wl}} END) OVER ({by}) AS o FROM {name}_f
), {name} AS (SELECT {keys}, CASE WHEN is_full THEN cap ELSE (w * greatest(given - o.cb, 0)) // o.wl END AS budget FROM {name}_o)"""


OP8 = rf"""
WITH d AS (
  SELECT doc_id, 'd' || (coalesce(try_cast(nullif(regexp_extract(coalesce(source, ''), '([0-9]{{1,9}})', 1), '') AS BIGINT), 0) % 3) AS domain, coalesce(lang, '') AS lang, coalesce(source, '') AS source,
    len({_WORDS})::BIGINT AS tokens, md5(coalesce(text, '')) AS content FROM documents
), cap AS (SELECT domain, lang, source, sum(tokens) AS available, sum(tokens) * 2 AS cap FROM d GROUP BY ALL
), top AS (SELECT domain, sum(cap) AS cap, (sum(sum(available)) OVER () * 3) // 5 AS given FROM cap GROUP BY domain
), {_deal("n1", "top", [], "domain")}, c2 AS (SELECT domain, lang, sum(cap) AS cap, any_value(n1.budget) AS given FROM cap JOIN n1 USING (domain) GROUP BY domain, lang
), {_deal("n2", "c2", ["domain"], "lang")}, c3 AS (SELECT domain, lang, source, cap, n2.budget AS given FROM cap JOIN n2 USING (domain, lang)
), {_deal("n3", "c3", ["domain", "lang"], "source")}, plan AS (
  SELECT domain, lang, source, CASE WHEN available = 0 THEN 0 ELSE budget // available END AS whole, budget - CASE WHEN available = 0 THEN 0 ELSE budget // available END * available AS rest FROM n3 JOIN cap USING (domain, lang, source)
), r AS (SELECT *, md5('{mixing.SEED}|' || whole::BIGINT || '|' || coalesce(doc_id::VARCHAR, '')) AS h FROM d JOIN plan USING (domain, lang, source)
), s AS (SELECT *, sum(tokens) OVER (PARTITION BY domain, lang, source ORDER BY h, content ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto FROM r
)
SELECT doc_id, domain, lang, source, tokens, (whole + CASE WHEN upto <= rest THEN 1 ELSE 0 END)::BIGINT AS epochs FROM s WHERE whole + CASE WHEN upto <= rest THEN 1 ELSE 0 END > 0
"""

#: Every window of every text against every item of its size, by shingles alone; items here have five words or more.
OP5 = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w FROM documents
), it AS (SELECT item_id, list_filter(regexp_split_to_array(lower(text), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w FROM benchmark
), ig AS (SELECT item_id, len(w) AS m, unnest(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) AS g, unnest(range(0, len(w) - 4)) AS p FROM it
), dg AS (SELECT doc_id, unnest(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) AS g, unnest(range(0, len(w) - 4)) AS p FROM d
), pl AS (SELECT DISTINCT doc_id, item_id, m, greatest(dg.p - ig.p, 0) AS start FROM dg JOIN ig USING (g)
), a AS (SELECT doc_id, item_id, m, start, array_to_string(d.w[q + 1:q + 5], ' ') AS g, count(*) AS n FROM (SELECT pl.*, unnest(range(start, start + m - 4)) AS q FROM pl) x JOIN d USING (doc_id) WHERE q + 5 <= len(d.w) GROUP BY ALL
), b AS (SELECT item_id, g, count(*) AS n FROM ig GROUP BY ALL
), na AS (SELECT doc_id, item_id, m, start, sum(n) AS n FROM a GROUP BY ALL
), nb AS (SELECT item_id, sum(n) AS n FROM b GROUP BY ALL
), sh AS (SELECT doc_id, item_id, m, start, sum(least(a.n, b.n)) AS s FROM a JOIN b USING (item_id, g) GROUP BY ALL
), sim AS (SELECT doc_id, item_id, m, start, s / (na.n + nb.n - s) AS similarity FROM sh JOIN na USING (doc_id, item_id, m, start) JOIN nb USING (item_id) WHERE 5 * s >= 4 * (na.n + nb.n - s)
), best AS (SELECT doc_id, item_id, max({'similarity': similarity, 's': -start, 'm': m}) AS x FROM sim GROUP BY ALL)
SELECT doc_id, item_id, x.similarity AS similarity, (-x.s)::INT AS start_word, least(x.m, len(d.w) + x.s)::INT AS window_words FROM best JOIN d USING (doc_id)
"""

ORACLES = {"op5_decontamination": OP5, "op1_chat_formatting": OP1, "op2_quality_rules": OP2, "op8_mixing": OP8}
