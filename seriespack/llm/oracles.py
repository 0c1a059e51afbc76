"""The same results in DuckDB's SQL, where SQL can express them."""

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _spans(kind: str, pattern: str, keep: str) -> str:
    """Rows (doc_id, start, kind number, span) of one kind: places follow from the pieces between matches."""
    return f"""
  SELECT doc_id, s AS start, '{kind}' AS kind, s + length(m) AS stop FROM (
    SELECT doc_id, m, list_sum([length(x) for x in gaps[1:i]]) + coalesce(list_sum([length(x) for x in matches[1:i - 1]]), 0) AS s
    FROM (SELECT doc_id, gaps, matches, unnest(matches) AS m, generate_subscripts(matches, 1) AS i FROM (
      SELECT doc_id, regexp_extract_all(text, '{pattern}') AS matches, regexp_split_to_array(text, '{pattern}') AS gaps FROM texts)))
  WHERE {keep}"""


_ASSIGN = "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in "(password|passwd|secret|token|api_?key)") + """["'']?\\x20*[:=]\\x20*["'']?([A-Za-z0-9+/_.=-]+)"""

OP1 = f"""
WITH texts AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
spans AS ({_spans("assign", _ASSIGN, f"length(regexp_extract(m, '{_ASSIGN}', 2)) >= 8")}
  UNION ALL {_spans("access", "AKIA[A-Z0-9]+", "length(m) >= 16")}
  UNION ALL {_spans("hex", "[0-9a-f]+", "length(m) >= 32")}),
found AS (
  SELECT doc_id, count(*) FILTER (kind = 'assign') AS a, count(*) FILTER (kind = 'access') AS b, count(*) FILTER (kind = 'hex') AS c,
    string_agg(concat_ws(':', kind, CAST(start AS BIGINT), CAST(stop AS BIGINT)), ',' ORDER BY start, CASE kind WHEN 'assign' THEN 1 WHEN 'access' THEN 2 ELSE 3 END) AS spans
  FROM spans GROUP BY doc_id)
SELECT doc_id, coalesce(a, 0) AS n_assign, coalesce(b, 0) AS n_access, coalesce(c, 0) AS n_hex, sha256(coalesce(spans, '')) AS base_sha256, coalesce(spans, '') AS spans
FROM texts LEFT JOIN found USING (doc_id)
"""

_WORD = "[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+"

OP9 = f"""
WITH words AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '{_WORD}') AS w FROM documents),
items AS (SELECT item_id, w, least(10, len(w)) AS n FROM (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '{_WORD}') AS w FROM benchmark) WHERE len(w) > 0),
grams AS (SELECT DISTINCT item_id, n, array_to_string(w[i:i + n - 1], ' ') AS gram FROM (SELECT item_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM items)),
sizes AS (SELECT DISTINCT n FROM items),
places AS (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM words, sizes WHERE len(w) >= n),
found AS (SELECT doc_id, item_id, p.n, i FROM (SELECT doc_id, n, i, array_to_string(w[i:i + n - 1], ' ') AS gram FROM places) p JOIN grams USING (n, gram)),
hit AS (SELECT doc_id, count(DISTINCT k) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS k FROM found) GROUP BY doc_id),
who AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS ids FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM found) GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM words LEFT JOIN hit USING (doc_id) LEFT JOIN who USING (doc_id)
"""

#: A link by all pairs of distinct sets that share a shingle; components by label spreading.
OP2 = f"""
WITH RECURSIVE words AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
sets AS (SELECT doc_id, list_sort(list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
  ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END)) AS s FROM words),
classes AS (SELECT s, min(doc_id) AS id, len(s) AS n FROM sets WHERE len(s) > 0 GROUP BY s),
grams AS (SELECT id, n, unnest(s) AS g FROM classes),
common AS (SELECT a.id AS u, b.id AS v, a.n AS n, b.n AS m, count(*) AS c FROM grams a JOIN grams b ON a.g = b.g AND a.id < b.id GROUP BY ALL),
edges AS (SELECT u, v FROM common WHERE 100 * c >= 75 * (n + m - c) UNION SELECT v, u FROM common WHERE 100 * c >= 75 * (n + m - c)),
reach(id, other) AS (SELECT id, id FROM classes UNION SELECT r.id, e.v FROM reach r JOIN edges e ON r.other = e.u),
named AS (SELECT id, min(other) AS component_id FROM reach GROUP BY id)
SELECT d.doc_id, CAST(len(d.s) AS BIGINT) AS n_shingles, coalesce(m.component_id, d.doc_id) AS component_id, coalesce(m.component_id, d.doc_id) = d.doc_id AS kept
FROM sets d LEFT JOIN classes c ON d.s = c.s LEFT JOIN named m ON m.id = c.id
"""

#: Fixed value: the alphabet of base32.
_BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"

OP7 = f"""
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
d AS (SELECT page_id, html, CAST(octet_length(encode(html)) AS BIGINT) AS payload_bytes, sha1(html) || '0' AS h FROM p),
f AS (SELECT html, min(page_id) AS original FROM p GROUP BY html)
SELECT page_id, payload_bytes,
  array_to_string(list_transform(range(0, 32), lambda i: substr('{_BASE32}', 1 + CAST(((CAST('0x' || substr(h, 1 + (5 * i) // 4, 2) AS INTEGER) >> (3 - (5 * i) % 4)) & 31) AS INTEGER), 1)), '') AS payload_digest,
  CASE WHEN page_id > original THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN page_id > original THEN original END AS refers_to
FROM d JOIN f USING (html)
"""

def _level(name: str, parent: str, keys: list[str], node: str, weight: str) -> str:
    """Budgets of the children of each node of ``parent``, capped and spread over siblings."""
    by = f"PARTITION BY {', '.join(keys)}" if keys else ""
    on = f"JOIN {parent} USING ({', '.join(keys)})" if keys else f", {parent}"
    path = ", ".join([*keys, node])
    return f"""
{name}_c AS (SELECT {path}, w, CASE WHEN w > 0 THEN cap ELSE 0 END AS cap, have FROM (SELECT {path}, {weight} AS w, CAST(sum(cap) AS BIGINT) AS cap FROM leaves GROUP BY {path}) {on}),
{name}_o AS (SELECT *, row_number() OVER ({by} ORDER BY cap * 1000 // greatest(w, 1), {node}) AS i,
  have - coalesce(sum(cap) OVER ({by} ORDER BY cap * 1000 // greatest(w, 1), {node} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS rem,
  sum(w) OVER ({by} ORDER BY cap * 1000 // greatest(w, 1), {node} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rest FROM {name}_c),
{name}_f AS (SELECT *, min(CASE WHEN cap * rest > rem * w THEN i END) OVER ({by}) AS f FROM {name}_o),
{name}_b AS (SELECT *, CAST(CASE WHEN f IS NULL OR i < f THEN cap ELSE least(cap, greatest(0, (max(CASE WHEN i = f THEN rem END) OVER ({by}) * w) // greatest(1, max(CASE WHEN i = f THEN rest END) OVER ({by})))) END AS BIGINT) AS low FROM {name}_f),
{name} AS (SELECT {path}, CAST(low + CASE WHEN w > 0 AND low < cap AND row_number() OVER ({by} ORDER BY CASE WHEN w > 0 AND low < cap THEN 0 ELSE 1 END, i) <= have - sum(low) OVER ({by}) THEN 1 ELSE 0 END AS BIGINT) AS have FROM {name}_b)"""


def mixing_sql(documents: str, share: tuple[int, int], epochs: int, seed: int, weights: dict[str, int], domains: int) -> str:
    """CTEs ending in ``mixed``: doc_id, domain, n, epochs, more (tokens of the partial epoch)."""
    lang = "CASE lang " + " ".join(f"WHEN '{k}' THEN {v}" for k, v in weights.items()) + " ELSE 1 END"
    return f"""docs AS (SELECT doc_id, coalesce(lang, '?') AS lang, coalesce(source, '?') AS source, 'domain' || CAST(CAST('0x' || substr(md5(coalesce(source, '?')), 1, 1) AS INTEGER) % {domains} AS VARCHAR) AS domain,
  CAST(len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) AS BIGINT) AS n FROM {documents}),
leaves AS (SELECT domain, lang, source, CAST(sum(n) AS BIGINT) AS held, CAST(sum(n) * {epochs} AS BIGINT) AS cap FROM docs GROUP BY ALL),
root AS (SELECT CAST(coalesce(sum(held), 0) * {share[0]} // {share[1]} AS BIGINT) AS have FROM leaves),
{_level("d1", "root", [], "domain", "1")},
{_level("d2", "d1", ["domain"], "lang", lang)},
{_level("d3", "d2", ["domain", "lang"], "source", "1")},
plan AS (SELECT domain, lang, source, coalesce(have // nullif(held, 0), 0) AS epochs, have - coalesce(have // nullif(held, 0), 0) * held AS more FROM d3 JOIN leaves USING (domain, lang, source)),
placed AS (SELECT doc_id, domain, n, epochs, more, sum(n) OVER (PARTITION BY domain, lang, source ORDER BY md5('{seed}:' || epochs || ':' || coalesce(CAST(doc_id AS VARCHAR), '?')), doc_id) - n AS before FROM docs JOIN plan USING (domain, lang, source)),
mixed AS (SELECT doc_id, domain, n, CAST(epochs AS BIGINT) AS epochs, CAST(least(n, greatest(0, more - before)) AS BIGINT) AS more FROM placed)"""


OP5 = "WITH " + mixing_sql("documents", (6, 10), 2, 17, {"en": 4, "fr": 2, "de": 2, "es": 2}, 4) + """
SELECT doc_id, domain, n AS n_tokens, epochs, epochs * n + more AS tokens_taken FROM mixed
"""

ORACLES = {"op5_mixing": OP5, "op1_secrets": OP1, "op2_near_duplicates": OP2, "op7_warc": OP7, "op9_decontamination": OP9}
