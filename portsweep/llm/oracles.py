"""SQL for the queries that SQL can express: places from the gaps between matches, self-joins in place of windows and indexes."""

from __future__ import annotations

_DOCS = "d AS (SELECT doc_id, coalesce(text, '') text FROM documents)"


def _found(kinds: list[tuple[str, str, str]]) -> str:
    """f(doc_id, k, s, e, m): the matches of (name, pattern, condition on m), numbered by kind."""
    parts = []
    for k, (_, pattern, keep) in enumerate(kinds):
        p = pattern.replace("'", "''")
        parts.append(f"""SELECT doc_id, {k} k, s, s + length(m) e, m FROM (
  SELECT doc_id, i, ms[i] m, CAST(coalesce(list_sum(list_transform(gaps[1:i], lambda g: length(g))), 0) + coalesce(list_sum(list_transform(ms[1:i - 1], lambda g: length(g))), 0) AS BIGINT) s
  FROM (SELECT *, unnest(range(1, len(ms) + 1)) i FROM (SELECT doc_id, regexp_extract_all(text, '{p}') ms, regexp_split_to_array(text, '{p}') gaps FROM d) WHERE len(ms) > 0)) WHERE {keep}""")
    return "f AS (" + " UNION ALL ".join(parts) + ")"


_ASSIGN = r"""(?i:password|passwd|secret|token|api_?key)["']? *[:=] *["']?[A-Za-z0-9+/_.=-]+"""
_VALUE = r"""^(?i:password|passwd|secret|token|api_?key)["']? *[:=] *["']?([A-Za-z0-9+/_.=-]+)$""".replace("'", "''")
_SECRETS = [
    ("assign", _ASSIGN, f"length(regexp_extract(m, '{_VALUE}', 1)) >= 6"), ("access", "AKIA[A-Z0-9]{16,}", "true"), ("hex", "[0-9a-f]{24,}", "true"),
    ("ident", r"""(?i:client|user|account|app|tenant)[_-]?(?i:id|name)["']? *[:=] *["']?[A-Za-z0-9._@-]{4,}""", "true"),
    ("opaque", "[A-Za-z0-9+/_-]{20,}={0,2}", "regexp_matches(m, '[0-9]') AND regexp_matches(m, '[A-Za-z]')"),
    ("endpoint", r"""(?i:https?|jdbc|amqp|redis|mongodb|postgres(?:ql)?)(?::[a-z0-9]+)?://[^ \t\n\x0b\f\r"'<>]+""", "true"),
]
_NEAR = "EXISTS (SELECT 1 FROM f o WHERE o.doc_id = f.doc_id AND o.k IN ({}) AND o.e >= f.s - 400 AND o.s <= f.e + 400)"
_IDENT, _SECRET = _NEAR.format("1, 3"), _NEAR.format("0, 2, 4")
_NAMES = "['assign', 'access', 'hex', 'ident', 'opaque', 'endpoint']"

OP1 = f"""WITH {_DOCS}, {_found(_SECRETS)},
told AS (SELECT doc_id, k, s, e FROM f WHERE k < 3 OR (NOT EXISTS (SELECT 1 FROM f o WHERE o.doc_id = f.doc_id AND o.k < 3 AND o.s < f.e AND f.s < o.e)
  AND CASE k WHEN 3 THEN {_SECRET} WHEN 4 THEN {_IDENT} ELSE {_IDENT} AND {_SECRET} END)),
said AS (SELECT doc_id, k, s, {_NAMES}[k + 1] || ':' || s || ':' || e x FROM told)
SELECT d.doc_id, count(*) FILTER (k = 0) n_assign, count(*) FILTER (k = 1) n_access, count(*) FILTER (k = 2) n_hex,
  sha256(coalesce(string_agg(x, ',' ORDER BY s, k) FILTER (k < 3), '')) base_sha256, coalesce(string_agg(x, ',' ORDER BY s, k), '') spans, count(*) FILTER (k >= 3) n_linked
FROM d LEFT JOIN said USING (doc_id) GROUP BY d.doc_id"""

_DIGITS = "regexp_replace({}, '[^0-9]', '', 'g')"
_LUHN = "list_sum(list_transform(range(1, length(x) + 1), lambda i: CASE WHEN i % 2 = 1 THEN CAST(x[length(x) - i + 1] AS INT) WHEN 2 * CAST(x[length(x) - i + 1] AS INT) > 9 THEN 2 * CAST(x[length(x) - i + 1] AS INT) - 9 ELSE 2 * CAST(x[length(x) - i + 1] AS INT) END)) % 10 = 0"
_CARD = f"length({_DIGITS.format('m')}) BETWEEN 16 AND 19 AND {_LUHN.replace('x', _DIGITS.format('m'))}"
_PERSONAL = [
    ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+", "true"),
    ("ip", r"[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+", "len(list_filter(string_split(m, '.'), lambda x: TRY_CAST(x AS HUGEINT) IS NULL OR CAST(x AS HUGEINT) > 255)) = 0"),
    ("card", r"[0-9](?:[ -]?[0-9])+", _CARD), ("phone", r"\+[0-9][ ().0-9-]+[0-9]", f"length({_DIGITS.format('m')}) BETWEEN 8 AND 15"),
]
_MARKS = "['email', 'ip', 'card', 'phone', 'term', 'number']"

OP2 = f"""WITH {_DOCS}, {_found(_PERSONAL)},
ents AS (SELECT DISTINCT doc_id, unnest(CASE k WHEN 0 THEN ['0' || lower(m), 'a' || split_part(lower(m), '@', 1), 'd' || split_part(lower(m), '@', 2)]
  WHEN 1 THEN ['1' || m, 'n' || array_to_string(string_split(m, '.')[1:3], '.')] ELSE [k || ':' || {_DIGITS.format('m')}] END) ent FROM f),
near AS (SELECT doc_id, regexp_extract_all(text, '[\\p{{L}}\\p{{N}}]+') ms, regexp_split_to_array(text, '[\\p{{L}}\\p{{N}}]+') gaps FROM d WHERE doc_id IN (SELECT doc_id FROM f)),
each AS (SELECT doc_id, i, m, g FROM (SELECT doc_id, unnest(range(1, len(ms) + 1)) i, unnest(ms) m, unnest(gaps[1:len(ms)]) g FROM near)),
placed AS (SELECT doc_id, m, lower(m) term, CAST(sum(length(g) + length(m)) OVER (PARTITION BY doc_id ORDER BY i) AS BIGINT) e FROM each),
held AS (SELECT ent, count(*) e_docs FROM ents GROUP BY ent), terms AS (SELECT DISTINCT doc_id, term FROM placed),
pair AS (SELECT ent, term, count(*) b_docs FROM ents JOIN terms USING (doc_id) GROUP BY ALL),
every AS (SELECT term, count(*) t_docs FROM (SELECT doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '[\\p{{L}}\\p{{N}}]+'))) term FROM d) GROUP BY term),
bad AS (SELECT ent, term FROM pair JOIN held USING (ent) JOIN every USING (term), (SELECT count(*) n FROM d) WHERE n > e_docs AND log2(n * b_docs / (e_docs * t_docs)) >= 0.8::DOUBLE * log2(n / e_docs)),
hits AS (SELECT DISTINCT doc_id, term FROM ents JOIN bad USING (ent) JOIN terms USING (doc_id, term)),
told AS (SELECT doc_id, k, s, e FROM f UNION ALL SELECT doc_id, CASE WHEN regexp_full_match(m, '\\p{{N}}+') THEN 5 ELSE 4 END, e - length(m), e FROM placed p JOIN hits USING (doc_id, term)
  WHERE NOT EXISTS (SELECT 1 FROM f WHERE f.doc_id = p.doc_id AND f.s < p.e AND p.e - length(p.m) < f.e)),
said AS (SELECT doc_id, k, s, {_MARKS}[k + 1] || ':' || s || ':' || e x FROM told)
SELECT d.doc_id, count(*) FILTER (k = 0) n_email, count(*) FILTER (k = 1) n_ip, count(*) FILTER (k = 2) n_card, count(*) FILTER (k = 3) n_phone,
  sha256(coalesce(string_agg(x, ',' ORDER BY k, s) FILTER (k < 4), '')) base_sha256, coalesce(string_agg(x, ',' ORDER BY k, s), '') spans, count(*) FILTER (k >= 4) n_terms
FROM d LEFT JOIN said USING (doc_id) GROUP BY d.doc_id"""

_ENDS = """[.!?]+["''»”)]*(?:\\s+|$)|\\n\\s*"""
OP3 = f"""WITH {_DOCS},
cut AS (SELECT doc_id, string_split(regexp_replace(text, '({_ENDS})', '\\1' || chr(1), 'g'), chr(1)) parts FROM d),
sent AS (SELECT doc_id, i, part, regexp_extract_all(part, '[^\\s]+') words FROM (SELECT doc_id, unnest(range(0, len(parts))) i, unnest(parts) part FROM cut) WHERE part <> ''),
line AS (SELECT doc_id, i, array_to_string(words, ' ') t, len(words) w, row_number() OVER (PARTITION BY doc_id ORDER BY i) n FROM sent WHERE len(words) > 0),
seen AS (SELECT *, lead(t) OVER x t2, lead(w) OVER x w2, lead(i) OVER x i2, lead(t, 2) OVER x t3, lead(w, 2) OVER x w3, lead(i, 2) OVER x i3 FROM line WINDOW x AS (PARTITION BY doc_id ORDER BY n)),
span AS (SELECT doc_id, i, i last, '1|' || t h FROM seen WHERE w >= 50
  UNION ALL SELECT doc_id, i, i2, '2|' || t || chr(2) || t2 FROM seen WHERE w2 IS NOT NULL AND w + w2 >= 20 AND NOT (w >= 50 AND w2 >= 50)
  UNION ALL SELECT doc_id, i, i3, '3|' || t || chr(2) || t2 || chr(2) || t3 FROM seen WHERE w3 IS NOT NULL AND NOT ((w + w2 >= 20) AND (w2 + w3 >= 20))),
first AS (SELECT h, min(struct_pack(doc_id := doc_id, i := i)) o FROM span GROUP BY h HAVING count(*) > 1),
gone AS (SELECT DISTINCT s.doc_id, x.i FROM span s JOIN first USING (h) JOIN sent x ON x.doc_id = s.doc_id AND x.i BETWEEN s.i AND s.last WHERE struct_pack(doc_id := s.doc_id, i := s.i) <> o)
SELECT d.doc_id, CASE WHEN n_removed = 0 THEN text ELSE rtrim(coalesce(kept, ''), ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)) END text, n_sentences, n_removed
FROM d JOIN (SELECT d.doc_id, CAST(count(s.i) AS INT) n_sentences, CAST(count(g.i) AS INT) n_removed, string_agg(s.part, '' ORDER BY s.i) FILTER (g.i IS NULL) kept
  FROM d LEFT JOIN sent s ON s.doc_id = d.doc_id LEFT JOIN gone g ON g.doc_id = s.doc_id AND g.i = s.i GROUP BY d.doc_id) USING (doc_id)"""

OP4 = """WITH v AS (SELECT row_number() OVER () r, vec_id, list_transform(embedding, lambda c: floor(256 * CAST(c AS DOUBLE))) x FROM embeddings
  WHERE vec_id IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda c: c IS NULL OR NOT isfinite(c))) = 0),
s AS (SELECT q.r, q.vec_id query_id, c.vec_id, CAST(list_inner_product(q.x, c.x) AS BIGINT) score FROM v q JOIN v c ON q.r <> c.r WHERE q.vec_id % 50 = 0)
SELECT query_id, CAST(rank AS INT) rank, vec_id, score FROM (SELECT *, row_number() OVER (PARTITION BY r ORDER BY score DESC, vec_id) rank FROM s) WHERE rank <= 5"""

OP9 = """WITH RECURSIVE w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[ \\t\\n\\x0b\\f\\r]+'), lambda x: x <> '') words FROM documents),
g AS (SELECT doc_id, CASE WHEN len(words) = 0 THEN [] WHEN len(words) < 3 THEN [array_to_string(words, ' ')] ELSE list_distinct(list_transform(range(1, len(words) - 1), lambda i: words[i] || ' ' || words[i + 1] || ' ' || words[i + 2])) END grams FROM w),
e AS (SELECT doc_id, unnest(grams) gram FROM g), n AS (SELECT doc_id, len(grams) n FROM g),
pair AS (SELECT a.doc_id a, b.doc_id b, count(*) c FROM e a JOIN e b ON a.gram = b.gram AND a.doc_id < b.doc_id GROUP BY ALL),
link AS (SELECT a, b FROM pair JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 90 * (x.n + y.n - c)),
two AS (SELECT a, b FROM link UNION ALL SELECT b, a FROM link),
reach(v, u) AS (SELECT doc_id, doc_id FROM n UNION SELECT r.v, l.b FROM reach r JOIN two l ON l.a = r.u)
SELECT doc_id, CAST(n AS BIGINT) n_shingles, component_id FROM n JOIN (SELECT v doc_id, min(u) component_id FROM reach GROUP BY v) USING (doc_id)"""

SQL = {"op1_secret_scan": OP1, "op2_pii": OP2, "op3_substring_dedup": OP3, "op4_topk_search": OP4, "op9_jaccard_join": OP9}
