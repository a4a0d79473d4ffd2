"""DuckDB SQL for the queries of this subpackage that SQL can express.

The others (fingerprints with XXH64, Markov models, byte-level BPE, fitted language models,
a particular packing) are compared with brute force in ``tests/llm``.
"""

from __future__ import annotations

from .quality import POLICIES, PRODUCTION, RULES, Policy

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_WORDS = r"regexp_extract_all({}, '[^\x20\x09-\x0D]+')"

LM = rf"""
WITH d AS (SELECT row_number() OVER () AS row, doc_id, {_WORDS.format(f"translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}')")} AS w FROM documents),
t AS (SELECT row, unnest(range(1, len(w) + 1)) AS i, w FROM d),
g AS (SELECT row, i, w[i] AS c, CASE WHEN i > 1 THEN w[i - 1] END AS b, CASE WHEN i > 2 THEN w[i - 2] END AS a FROM t),
c1 AS (SELECT c, count(*) AS n FROM g GROUP BY ALL),
c2 AS (SELECT b, c, count(*) AS n FROM g WHERE b IS NOT NULL GROUP BY ALL),
c3 AS (SELECT a, b, c, count(*) AS n FROM g WHERE a IS NOT NULL GROUP BY ALL),
total AS (SELECT count(*) AS n FROM g),
s AS (
  SELECT g.row, g.i, c3.n AS n3, context2.n AS m3, c2.n AS n2, context1.n AS m2, c1.n AS n1, total.n AS m1
  FROM g CROSS JOIN total JOIN c1 ON c1.c = g.c
  LEFT JOIN c2 ON c2.b = g.b AND c2.c = g.c
  LEFT JOIN c3 ON c3.a = g.a AND c3.b = g.b AND c3.c = g.c
  LEFT JOIN c2 AS context2 ON context2.b = g.a AND context2.c = g.b
  LEFT JOIN c1 AS context1 ON context1.c = g.b),
v AS (
  SELECT row, CASE WHEN i > 2 AND n3 >= 2 THEN 3 WHEN i > 1 AND n2 >= 2 THEN 2 ELSE 1 END AS level, least(i, 3) AS most,
    CASE level WHEN 3 THEN n3 / m3 WHEN 2 THEN n2 / m2 ELSE n1 / m1 END AS p
  FROM s),
r AS (
  SELECT row, sum(floor((ln(p) + (most - level) * ln(0.4)) * 1000000 + 0.5)::BIGINT) AS score,
    count(*) FILTER (level = 3) AS n3, count(*) FILTER (level = 2) AS n2, count(*) FILTER (level = 1) AS n1
  FROM v GROUP BY row)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(score, 0)::BIGINT AS score_micro, coalesce(n3, 0)::BIGINT AS n_order3,
  coalesce(n2, 0)::BIGINT AS n_order2, coalesce(n1, 0)::BIGINT AS n_order1
FROM d LEFT JOIN r USING (row)
"""


def _mask(rules: tuple[str, ...]) -> int:
    return sum(1 << i for i, (name, _) in enumerate(RULES) if name in rules)


def _rejects(policy: Policy, without: str | None = None) -> str:
    hard = _mask(tuple(r for r in policy.hard if r != without))
    soft = _mask(tuple(r for r in policy.soft if r != without))
    return f"((bits & {hard}) <> 0 OR bit_count(bits & {soft}) > {policy.allowed})"


_BITS = " + ".join(f"CASE WHEN {condition} THEN {1 << i} ELSE 0 END" for i, (_, condition) in enumerate(RULES))
_LEDGER = rf"""
WITH d AS (SELECT row_number() OVER () AS row, doc_id, coalesce(text, '') AS text, {_WORDS.format("coalesce(text, '')")} AS w FROM documents),
lines AS (SELECT row, unnest(range(1, len(string_split(text, chr(10))) + 1)) AS i, string_split(text, chr(10)) AS l FROM d),
worded AS (SELECT row, l[i] AS line FROM lines WHERE len({_WORDS.format("l[i]")}) > 0),
dup AS (SELECT row, count(*) AS n, count(*) - count(DISTINCT line) AS dup FROM worded GROUP BY row),
win AS (SELECT row, unnest(range(1, len(w) - 6)) AS i, w FROM d WHERE len(w) > 7),
twice AS (SELECT row, i FROM win QUALIFY count(*) OVER (PARTITION BY row, w[i:i + 7]) > 1),
covered AS (SELECT row, count(*) AS n FROM (SELECT DISTINCT row, unnest(range(i, i + 8)) AS at FROM twice) GROUP BY row),
m AS (
  SELECT row, doc_id, len(w)::BIGINT AS n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars,
    (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
    coalesce(dup.dup, 0)::BIGINT AS n_dup_lines, coalesce(covered.n, 0)::BIGINT AS n_repeat_words, coalesce(dup.n, 0)::BIGINT AS n_lines,
    len(list_filter(w, lambda x: regexp_matches(x, '[A-Za-z]|[^\x00-\x7F]')))::BIGINT AS n_alpha_words,
    len(list_filter(w, lambda x: strlen(x) > 1 AND regexp_matches(x, '[A-Z]') AND NOT regexp_matches(x, '[a-z]')))::BIGINT AS n_upper_words
  FROM d LEFT JOIN dup USING (row) LEFT JOIN covered USING (row)),
ledger AS (SELECT *, ({_BITS})::BIGINT AS bits FROM m)
"""
QUALITY = (
    _LEDGER
    + f"""SELECT doc_id, bits, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines, n_alpha_words, n_upper_words,
  {_rejects(POLICIES[0])} AS base_failed, NOT {_rejects(PRODUCTION)} AND NOT {_rejects(POLICIES[0])} AS kept FROM ledger"""
)
ABLATIONS = _LEDGER + " UNION ALL ".join(
    f"""SELECT '{p.name}' AS policy, {p.version}::INTEGER AS version, {f"'{w}'" if w else 'NULL'}::VARCHAR AS without,
  (count(*) FILTER ({_rejects(p, w)}))::BIGINT AS rejected,
  (count(*) FILTER ({_rejects(p)}) - count(*) FILTER ({_rejects(p, w)}))::BIGINT AS alone FROM ledger"""
    for p in POLICIES
    for w in (None, *p.hard, *p.soft)
)

TOPK = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)::BIGINT) AS v FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, r.vec_id, list_sum(list_transform(range(1, len(q.v) + 1), lambda i: q.v[i] * r.v[i]))::BIGINT AS score
  FROM v AS q JOIN v AS r ON q.vec_id % 20 = 0 AND q.vec_id <> r.vec_id)
SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank, vec_id, score FROM s
QUALIFY rank <= 20
"""

WARC = """
WITH p AS (SELECT page_id, coalesce(html, '') AS body, sha1(coalesce(html, '')) AS hex FROM pages),
f AS (SELECT *, min(page_id) OVER (PARTITION BY body) AS first FROM p)
SELECT page_id, strlen(body)::BIGINT AS payload_bytes,
  list_aggregate(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    1 + ((('0x' || substr(hex, 1 + 5 * (i // 4), 5))::BIGINT >> (15 - 5 * (i % 4))) & 31), 1)), 'string_agg', '') AS payload_digest,
  CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id <> first THEN first END AS refers_to
FROM f
"""

CHAT = """
WITH t AS (SELECT DISTINCT conv_id, turn, role, text FROM conversations WHERE conv_id IS NOT NULL),
c AS (SELECT conv_id, list(struct_pack(r := role, t := text) ORDER BY turn) AS l, count(*) AS n FROM t GROUP BY conv_id),
m AS (SELECT l, n, min(conv_id) AS conv_id, count(*) AS copies FROM c GROUP BY l, n),
shorter AS (SELECT DISTINCT l[1:k] AS l FROM (SELECT l, unnest(range(1, n)) AS k FROM c)),
kept AS (SELECT * FROM m ANTI JOIN shorter ON m.l = shorter.l),
s AS (SELECT *, unnest(range(0, (n + 63) // 64)) AS segment FROM kept)
SELECT conv_id, segment::BIGINT AS segment, n::BIGINT AS n_turns, copies::BIGINT AS copies,
  list_aggregate(list_transform(l[segment * 64 + 1:segment * 64 + 64],
    lambda x: '<|' || coalesce(x.r, 'unknown') || '|>' || chr(10) || coalesce(x.t, '') || '<|end|>' || chr(10)), 'string_agg', '') AS rendered
FROM s
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_lm_scores": LM, "op2_quality": QUALITY, "op2_ablations": ABLATIONS, "op4_topk": TOPK, "op8_warc": WARC, "op9_chat": CHAT}
