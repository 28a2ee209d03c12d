"""DuckDB SQL for the text queries that SQL can express on whole tables."""

from __future__ import annotations

from frontfill.llm import quality_rules as q

_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"

OP9 = r"""
WITH n AS (
  SELECT doc_id, length(coalesce(text, '')) AS size,
         sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g')) AS text_sha256
  FROM documents),
g AS (
  SELECT *, count(*) OVER (PARTITION BY text_sha256) AS group_size,
         first_value(doc_id) OVER (PARTITION BY text_sha256 ORDER BY size DESC, doc_id) AS keep_id
  FROM n)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, text_sha256 FROM g
"""

OP5 = rf"""
WITH w AS (SELECT doc_id, {_WORDS} AS ws FROM documents),
p AS (SELECT doc_id, unnest(range(1, len(ws) - 33)) AS i, ws FROM w WHERE len(ws) >= 35),
h AS (SELECT doc_id, i, hash(array_to_string(ws[i:i+34], ' ')) AS a, hash(array_to_string(ws[i:i+34], '|')) AS b FROM p),
r AS (SELECT doc_id, i FROM h QUALIFY count(*) OVER (PARTITION BY a, b) > 1),
gone AS (SELECT DISTINCT doc_id, unnest(range(i, i + 35)) AS k FROM r),
k AS (SELECT doc_id, list(k) AS ks FROM gone GROUP BY doc_id),
o AS (
  SELECT w.doc_id, len(ws)::BIGINT AS n_words, coalesce(len(ks), 0)::BIGINT AS n_removed,
         array_to_string([x.w FOR x IN [{{'w': ws[j], 'j': j}} FOR j IN range(1, len(ws) + 1)]
                          IF NOT list_contains(coalesce(ks, []), x.j)], ' ') AS kept
  FROM w LEFT JOIN k USING (doc_id))
SELECT doc_id, n_words, n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM o
"""

OP2 = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
                                    '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (
  SELECT doc_id, array_to_string(ws[i:i+3], ' ') AS g
  FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 3, 1) + 1)) AS i FROM w WHERE len(ws) > 0)
  GROUP BY ALL),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
c AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
e AS (SELECT x, y FROM c JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y WHERE 100 * k >= 80 * (p.n + q.n - k)),
r(x, y) AS (SELECT x, y FROM e UNION SELECT r.x, e.y FROM r JOIN e ON r.y = e.x),
m AS (SELECT x AS doc_id, min(least(x, y)) AS m FROM r GROUP BY x)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, coalesce(m.m, d.doc_id) AS component_id,
       coalesce(m.m, d.doc_id) = d.doc_id AS kept
FROM documents d LEFT JOIN n USING (doc_id) LEFT JOIN m USING (doc_id)
"""

OP6 = r"""
WITH RECURSIVE src AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
t AS (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text) - 1 AS i FROM src),
m AS (SELECT *, len(regexp_extract_all(text, '\p{L}{1,4}|\p{N}{1,3}|[^\x09-\x0D\x20\p{L}\p{N}]')) + 3 AS tok,
             length(replace(replace(role, '\', '\\'), '<|', '<\|')) + length(replace(replace(text, '\', '\\'), '<|', '<\|')) + 15 AS len FROM t),
c AS (SELECT *, sum(tok) OVER (PARTITION BY conv_id ORDER BY i)::BIGINT - tok AS before FROM m),
p AS (
  SELECT x.conv_id, x.i, r.k, x.before - y.before AS past,
         x.before - y.before + CASE WHEN f.role = 'system' AND x.i > r.k THEN f.tok ELSE 0 END AS cost, x.tok
  FROM c x, range(0, 3) r(k) JOIN c y ON y.conv_id IS NOT DISTINCT FROM x.conv_id AND y.i = x.i - r.k
  JOIN c f ON f.conv_id IS NOT DISTINCT FROM x.conv_id AND f.i = 0 WHERE x.i > 0),
h AS (SELECT conv_id, i, max(k) AS k, arg_max(cost, k) AS cost FROM p WHERE k = 0 OR (past <= 128 AND cost + tok <= 512) GROUP BY conv_id, i),
g(conv_id, i, cur, base) AS (
  SELECT conv_id, 0::BIGINT, 0::BIGINT, 0::BIGINT FROM c WHERE i = 0
  UNION ALL
  SELECT c.conv_id, c.i, CASE WHEN c.before + c.tok - base > 512 THEN c.i ELSE cur END, CASE WHEN c.before + c.tok - base > 512 THEN c.before - h.cost ELSE base END
  FROM g JOIN c ON c.conv_id = g.conv_id AND c.i = g.i + 1 JOIN h ON h.conv_id = c.conv_id AND h.i = c.i),
w AS (SELECT DISTINCT conv_id, cur AS lo FROM g WHERE cur > 0),
b AS (SELECT w.conv_id, lo, lo - k AS back FROM w JOIN h ON h.conv_id = w.conv_id AND h.i = lo),
again AS (
  SELECT b.conv_id, sum(c.len + 9) AS chars FROM b JOIN c ON c.conv_id = b.conv_id AND ((c.i >= back AND c.i < lo) OR (c.i = 0 AND c.role = 'system' AND back > 0)) GROUP BY b.conv_id),
o AS (
  SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY i)) AS turns_sha256,
         coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
         sha256(coalesce(string_agg(text, '' ORDER BY i) FILTER (role = 'assistant'), '')) AS loss_sha256, sum(len + 8) AS chars
  FROM c GROUP BY conv_id)
SELECT o.conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, (o.chars + coalesce(again.chars, 0))::BIGINT AS formatted_chars
FROM o LEFT JOIN again USING (conv_id)
"""

OP1 = rf"""
WITH w AS (SELECT doc_id, lang, coalesce(text, '') AS text, {_WORDS} AS ws FROM documents),
l AS (SELECT doc_id, [x FOR x IN string_split(text, chr(10)) IF regexp_matches(x, '[^\x20\x09-\x0D]')] AS ls FROM w),
g AS (SELECT doc_id, unnest(range(1, len(ws) - 1)) AS i, ws FROM w WHERE len(ws) >= 3),
t AS (SELECT doc_id, i FROM g QUALIFY count(*) OVER (PARTITION BY doc_id, ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2]) > 1),
r AS (SELECT doc_id, count(DISTINCT k) AS n FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS k FROM t) GROUP BY doc_id),
m AS (
  SELECT w.doc_id, lang, len(ws)::BIGINT AS n_words, length(array_to_string(ws, ''))::BIGINT AS word_chars,
         length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
         (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines, coalesce(r.n, 0)::BIGINT AS n_repeat_words
  FROM w JOIN l USING (doc_id) LEFT JOIN r USING (doc_id)),
b AS (SELECT *, n_words < {q.MIN_WORDS} OR 100 * n_repeat_words > {q.MAX_REPEAT_PERCENT} * n_words AS base_failed FROM m),
s AS (
  SELECT doc_id, lang, base_failed, unnest([{", ".join(f"{{'s': '{k}', 'v': {e}}}" for k, e in q.SCORES.items())}], recursive := true) FROM b),
good AS (SELECT doc_id FROM labels WHERE quality IS NOT NULL GROUP BY doc_id HAVING min(quality) = 1),
cuts AS (SELECT unnest({list(q.GRID)}) AS cut, unnest(range({len(q.GRID)})) AS pos),
c AS (
  SELECT s.lang, s.s, pos, cut, count(*) AS n, count(*) FILTER (v > cut) AS k
  FROM s JOIN good USING (doc_id), cuts WHERE NOT base_failed GROUP BY ALL),
d AS (SELECT count(*) AS strata FROM (SELECT DISTINCT lang FROM c)),
-- the chance of k or fewer of n at the rate that must not be passed
f AS (
  SELECT *, list_sum([exp(lgamma(n + 1.0) - lgamma(i + 1.0) - lgamma(n - i + 1.0) + i * ln({q.ALPHA / len(q.SCORES)}) + (n - i) * ln({1 - q.ALPHA / len(q.SCORES)})) FOR i IN range(k + 1)])
            > {q.DELTA} / (strata * {len(q.SCORES)}) AS fails
  FROM c, d),
z AS (SELECT lang, s, min(cut) AS cut FROM (SELECT *, bool_or(fails) OVER (PARTITION BY lang, s ORDER BY pos) AS stopped FROM f) WHERE NOT stopped GROUP BY lang, s),
x AS (SELECT DISTINCT s.doc_id FROM s JOIN z ON s.lang IS NOT DISTINCT FROM z.lang AND s.s = z.s WHERE s.v > z.cut)
SELECT b.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND x.doc_id IS NULL AS kept
FROM b LEFT JOIN x USING (doc_id)
"""

ORACLES = {
    "op1_quality_rules": OP1,
    "op2_minhash_dedup": OP2,
    "op5_substring_dedup": OP5,
    "op6_chat_format": OP6,
    "op9_exact_dedup": OP9,
}
