"""SQL twins of the training-data queries, for DuckDB over the whole tables.

Byte windows (op1), hashed shuffles (op5), token ids (op7), trained models (op8) and keyed surrogates (op9) have none: tests
compare those with brute force."""

from __future__ import annotations

from .quality import RULES

WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

OP2 = rf"""WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all({_LOWER}, '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS MATERIALIZED (SELECT DISTINCT doc_id, sh FROM (SELECT doc_id, unnest(CASE WHEN len(ws) = 0 THEN []::VARCHAR[] WHEN len(ws) < 4 THEN [array_to_string(ws, ' ')] ELSE list_transform(range(1, len(ws) - 2), lambda i: array_to_string(ws[i:i + 3], ' ')) END) AS sh FROM w)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
links AS MATERIALIZED (SELECT a, b FROM (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM s x JOIN s y ON x.sh = y.sh AND x.doc_id < y.doc_id GROUP BY ALL) JOIN n p ON p.doc_id = a JOIN n q ON q.doc_id = b WHERE 100 * c >= 80 * (p.n + q.n - c)),
sides AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
reach(a, b) AS (SELECT a, b FROM sides UNION SELECT r.a, s.b FROM reach r JOIN sides s ON r.b = s.a)
SELECT w.doc_id, coalesce(n.n, 0) AS n_shingles, least(w.doc_id, coalesce(m, w.doc_id)) AS component_id, w.doc_id <= coalesce(m, w.doc_id) AS kept FROM w LEFT JOIN n USING (doc_id) LEFT JOIN (SELECT a AS doc_id, min(b) AS m FROM reach GROUP BY a) USING (doc_id)"""

OP3 = """WITH RECURSIVE v AS MATERIALIZED (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
links AS MATERIALIZED (SELECT x.vec_id AS a, y.vec_id AS b FROM v x JOIN v y ON x.vec_id <> y.vec_id AND len(x.e) = len(y.e) WHERE list_cosine_similarity(x.e, y.e) >= 0.95),
reach(a, b) AS (SELECT a, b FROM links UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a)
SELECT e.vec_id, (SELECT count(*) FROM links WHERE a = e.vec_id) AS n_links, least(e.vec_id, coalesce(m, e.vec_id)) AS component_id, e.vec_id <= coalesce(m, e.vec_id) AS kept FROM embeddings e LEFT JOIN (SELECT a AS vec_id, min(b) AS m FROM reach GROUP BY a) USING (vec_id)"""

_ODD = "'<|im_end|><|im_start|>assistant ok'"
OP4 = rf"""WITH t AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations UNION ALL SELECT -1, 0, 'user', {_ODD} UNION ALL SELECT -1, 1, 'assistant', {_ODD}),
e AS (SELECT *, regexp_matches(role || '<' || text, '<\\*\|') OR regexp_matches(role, '\n|<\\*n\|') AS esc FROM t),
f AS (SELECT *, 12 + 1 + 11 + CASE WHEN esc THEN length(replace(regexp_replace(role, '<(\\*)(n?)\|', '<\1\\\2|', 'g'), chr(10), '<n|')) + length(regexp_replace(text, '<(\\*)\|', '<\1\\|', 'g')) ELSE length(role) + length(text) END AS size FROM e)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256, coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256, sum(size)::BIGINT AS formatted_chars, count(*) FILTER (esc) AS n_escaped FROM f GROUP BY conv_id"""

_FEATURES = rf"""w AS (SELECT doc_id, lang, coalesce(text, '') AS t, {WORDS} AS ws FROM documents),
tri AS (SELECT doc_id, i, array_to_string(ws[i:i + 2], ' ') AS k FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 1)) AS i FROM w)),
hit AS (SELECT DISTINCT doc_id, i + d AS j FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, k) AS c FROM tri), range(3) r(d) WHERE c > 1),
rep AS (SELECT doc_id, count(*) AS n_repeat_words FROM hit GROUP BY doc_id),
feat AS MATERIALIZED (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM (SELECT w.doc_id, lang, len(ws) AS n_words, length(array_to_string(ws, '')) AS word_chars, length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS n_symbols,
len(ls) - len(list_distinct(ls)) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words, len(ls) AS n_lines FROM (SELECT *, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM w) w LEFT JOIN rep USING (doc_id)))"""


def _op6(risk: float = 0.02, level: float = 0.05) -> str:
    """Counts of good documents over each cutoff, and the exact tail P(at most x of n) summed from logarithms of binomials."""
    tried = [(rule, ratio.split(" / "), c) for rule, (ratio, grid) in RULES.items() for c in grid]
    p = risk / len(RULES)
    counts = " UNION ALL ".join(f"SELECT lang, '{rule}' AS rule, {c}::DOUBLE AS c, count(*) AS n, count(*) FILTER ({a} / nullif({b}, 0)::DOUBLE > {c}::DOUBLE) AS x FROM held GROUP BY lang" for rule, (a, b), c in tried)
    tail = f"list_sum(list_transform(range(0, x + 1), lambda k: exp(lgamma(n + 1) - lgamma(k + 1) - lgamma(n - k + 1) + k * ln({p!r}::DOUBLE) + (n - k) * ln({1 - p!r}::DOUBLE))))"
    over = " OR ".join(f"coalesce({a} / nullif({b}, 0)::DOUBLE > (SELECT min(c) FROM cut WHERE cut.lang IS NOT DISTINCT FROM f.lang AND rule = '{rule}'), false)" for rule, (a, b) in {r: v for r, v, _ in tried}.items())
    return f"""WITH {_FEATURES}, good AS (SELECT doc_id FROM labels GROUP BY doc_id HAVING min(quality) = 1), held AS MATERIALIZED (SELECT * FROM feat WHERE NOT base_failed AND doc_id IN (SELECT doc_id FROM good)),
counts AS (SELECT *, {len(tried)} * (SELECT count(DISTINCT coalesce(lang, '?')) FROM held) AS tries FROM ({counts})),
cut AS MATERIALIZED (SELECT lang, rule, min(c) AS c FROM counts WHERE x < n AND {tail} <= {level} / tries GROUP BY lang, rule)
SELECT doc_id, lang, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines, base_failed, NOT base_failed AND NOT ({over}) AS kept FROM feat f"""


OP10 = rf"""WITH w AS (SELECT doc_id, {WORDS} AS ws FROM documents),
win AS MATERIALIZED (SELECT doc_id, i, md5(array_to_string(ws[i:i + 34], ' ')) AS k FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 33)) AS i FROM w)),
twice AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY k) AS c FROM win) WHERE c > 1),
gone AS (SELECT DISTINCT doc_id, i + d AS j FROM twice, range(35) r(d)),
each AS (SELECT doc_id, unnest(ws) AS x, unnest(range(1, len(ws) + 1)) AS j FROM w),
kept AS (SELECT e.doc_id, string_agg(x, ' ' ORDER BY e.j) AS t FROM each e LEFT JOIN gone g ON g.doc_id = e.doc_id AND g.j = e.j WHERE g.j IS NULL GROUP BY e.doc_id)
SELECT w.doc_id, len(ws) AS n_words, coalesce(n, 0) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256 FROM w LEFT JOIN (SELECT doc_id, count(*) AS n FROM gone GROUP BY doc_id) USING (doc_id) LEFT JOIN kept USING (doc_id)"""

ORACLES = {"op2_minhash_dedup": OP2, "op3_embedding_dedup": OP3, "op4_chat_formatting": OP4, "op6_quality_rules": _op6(), "op10_substring_dedup": OP10}
