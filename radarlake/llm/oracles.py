"""DuckDB SQL for the text operators' queries, written apart from the operators."""

from __future__ import annotations

_BASE = {
    "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "true"),
    "ip": (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "list_bool_and([ltrim(p, '0') = '' OR (length(ltrim(p, '0')) <= 3 AND CAST(ltrim(p, '0') AS BIGINT) <= 255) FOR p IN string_split(m, '.')])"),
    "card": (r"[0-9]([\x20-]?[0-9])+", "length(digits) BETWEEN 16 AND 19 AND luhn"),
    "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", "length(digits) BETWEEN 8 AND 15"),
    "iban": (r"[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?", "length(replace(m, ' ', '')) BETWEEN 15 AND 34 AND mod97"),
}
_SUPPORT = {"email": "mail|contact|write|address", "ip": "host|server|address|login|client", "card": "card|visa|pay|credit|debit", "phone": "phone|call|tel|mobile|fax|dial", "iban": "iban|account|bank|transfer"}


def _pii() -> str:
    kinds = []
    for order, (kind, (pattern, _)) in enumerate(_BASE.items()):
        kinds.append(f"SELECT doc_id, t, {order} AS o, '{kind}' AS kind, regexp_extract_all(t, '{pattern}') AS ms, string_split_regex(t, '{pattern}') AS ps FROM d")
    tests = " ".join(f"WHEN '{kind}' THEN {test}" for kind, (_, test) in _BASE.items())
    support = " ".join(f"WHEN '{kind}' THEN '{words}'" for kind, words in _SUPPORT.items())
    counts = ", ".join(f"count(*) FILTER (kind = '{kind}') AS n_{kind}" for kind in _BASE)
    return f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
found AS ({' UNION ALL '.join(kinds)}),
each_one AS (SELECT doc_id, t, o, kind, unnest(ms) AS m, unnest(range(1, len(ms) + 1)) AS i, ms, ps FROM found WHERE len(ms) > 0),
placed AS (
  SELECT doc_id, t, o, kind, m, regexp_replace(m, '[^0-9]', '', 'g') AS digits,
    CAST(list_sum([length(x) FOR x IN ps[1:i]]) + coalesce(list_sum([length(x) FOR x IN ms[1:i-1]]), 0) AS BIGINT) AS s FROM each_one),
checked AS (
  SELECT *, s + length(m) AS e,
    list_sum([CASE WHEN k % 2 = 0 THEN CAST(digits[length(digits) - k] AS BIGINT) ELSE CAST(digits[length(digits) - k] AS BIGINT) * 2 - CASE WHEN CAST(digits[length(digits) - k] AS BIGINT) > 4 THEN 9 ELSE 0 END END FOR k IN range(0, length(digits))]) % 10 = 0 AS luhn,
    kind = 'iban' AND list_reduce(list_prepend(CAST(0 AS HUGEINT), [CASE WHEN c >= 'A' THEN ascii(c) - 55 ELSE ascii(c) - 48 END FOR c IN string_split(substr(replace(m, ' ', ''), 5) || substr(replace(m, ' ', ''), 1, 4), '')]), lambda a, v: (a * CASE WHEN v > 9 THEN 100 ELSE 10 END + v) % 97) = 1 AS mod97 FROM placed),
kept AS (SELECT * FROM checked WHERE CASE kind {tests} END),
scored AS (
  SELECT doc_id, o, kind, s, e, round(0.7 + CASE WHEN regexp_matches(near, CASE kind {support} END) THEN 0.2 ELSE 0.0 END - CASE WHEN regexp_matches(near, 'example|sample|version|dummy|order no|invoice no') THEN 0.2 ELSE 0.0 END, 2) AS score
  FROM (SELECT *, lower(substr(t, greatest(s - 40, 0) + 1, s - greatest(s - 40, 0)) || ' ' || substr(t, e + 1, 40)) AS near FROM kept)),
summed AS (
  SELECT doc_id, {counts},
    string_agg(kind || ':' || s || ':' || e, ',' ORDER BY o, s) FILTER (kind <> 'iban') AS base,
    string_agg(kind || ':' || s || ':' || e, ',' ORDER BY o, s) AS spans,
    string_agg(kind || ':' || s || ':' || e || ':' || CAST(CAST(score AS DOUBLE) AS VARCHAR), ',' ORDER BY o, s) AS scored,
    count(*) FILTER (score >= 0.7) AS n_strong
  FROM scored GROUP BY doc_id)
SELECT doc_id, {', '.join(f'coalesce(n_{kind}, 0) AS n_{kind}' for kind in _BASE)}, sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans, coalesce(scored, '') AS scored, coalesce(n_strong, 0) AS n_strong
FROM d LEFT JOIN summed USING (doc_id)"""


_WARC = """
WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, ''))) AS n, sha1(coalesce(html, '')) AS h FROM pages),
f AS (SELECT *, min(page_id) OVER (PARTITION BY h, n) AS first FROM p)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes,
  array_to_string([substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST((CAST('0x' || substr(h, CAST(i // 4 AS INT) * 5 + 1, 5) AS INT) >> CAST(15 - 5 * (i % 4) AS INT)) & 31 AS INT) + 1, 1) FOR i IN range(32)], '') AS payload_digest,
  CASE WHEN first = page_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN first <> page_id THEN first END AS refers_to
FROM f"""

_LOWER = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_WORDS = r"regexp_extract_all({}, '[^\x20\x09-\x0D]+')"


def near_duplicates(n: int, percent: int, table: str = "documents") -> str:
    """doc_id, n_shingles, component_id and kept, by an inverted index of all shingles."""
    words = _WORDS.format(_LOWER.format("coalesce(text, '')"))
    return f"""
WITH RECURSIVE w AS (SELECT doc_id, {words} AS w FROM {table}),
sets AS (SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < {n} THEN [array_to_string(w, ' ')] ELSE list_distinct([array_to_string(w[i:i+{n - 1}], ' ') FOR i IN range(1, len(w) - {n - 2})]) END AS s FROM w),
one AS (SELECT doc_id, unnest(s) AS x FROM sets),
pairs AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS common FROM one a JOIN one b ON a.x = b.x AND a.doc_id <> b.doc_id GROUP BY ALL),
links AS (SELECT a, b FROM pairs JOIN sets x ON x.doc_id = a JOIN sets y ON y.doc_id = b WHERE 100 * common >= {percent} * (len(x.s) + len(y.s) - common)),
reach AS (SELECT doc_id AS id, doc_id AS far FROM {table} UNION SELECT r.id, l.b FROM reach r JOIN links l ON l.a = r.far)
SELECT s.doc_id, CAST(len(s.s) AS BIGINT) AS n_shingles, c.component AS component_id, s.doc_id = c.component AS kept
FROM sets s JOIN (SELECT id, min(far) AS component FROM reach GROUP BY id) c ON c.id = s.doc_id"""


def passages(overlap: float = 0.8, table: str = "documents") -> str:
    """Every lay of every test item over every document that shares a word with it."""
    tokens = lambda t, k: f"SELECT {k}, unnest(w) AS w, unnest(range(len(w))) AS i, len(w) AS n FROM (SELECT {k}, {_WORDS.format(_LOWER.format('text'))} AS w FROM {t})"
    return f"""
WITH d AS ({tokens(table, 'doc_id')}), b AS ({tokens('benchmark', 'item_id')}),
lays AS (SELECT doc_id, item_id, d.i - b.i AS place, b.n AS n_item, count(*) AS n_matched FROM d JOIN b ON d.w = b.w GROUP BY ALL HAVING count(*) >= {overlap} * b.n),
best AS (SELECT *, row_number() OVER (PARTITION BY doc_id, item_id ORDER BY n_matched DESC, place) AS r FROM lays)
SELECT doc_id, item_id, n_matched, CAST(n_item AS BIGINT) AS n_item, CAST(place AS BIGINT) AS place, n_matched / n_item AS overlap FROM best WHERE r = 1"""


_REPEATS = """
WITH d AS (SELECT doc_id, regexp_extract_all(hex(encode(coalesce(text, ''))), '..') AS x FROM documents),
bytes AS (SELECT doc_id, unnest(x) AS x, unnest(range(len(x))) AS i, len(x) AS n FROM d),
starts AS (SELECT doc_id, i, n, x, string_agg(x, '') OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND 49 FOLLOWING) AS w FROM bytes),
firsts AS (SELECT w, min(doc_id) AS first FROM starts WHERE i + 50 <= n GROUP BY w HAVING count(*) > 1),
hits AS (SELECT s.doc_id, s.i, s.x, CASE WHEN f.first < s.doc_id AND s.i + 50 <= s.n THEN 1 ELSE 0 END AS hit FROM starts s LEFT JOIN firsts f ON f.w = s.w),
marked AS (SELECT doc_id, i, x, max(hit) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN 49 PRECEDING AND CURRENT ROW) = 1 AS gone FROM hits),
runs AS (SELECT *, gone AND NOT coalesce(lag(gone) OVER (PARTITION BY doc_id ORDER BY i), false) AS opens FROM marked),
summed AS (SELECT doc_id, count(*) FILTER (gone) AS n_removed, count(*) FILTER (opens) AS n_spans, coalesce(string_agg(x, '' ORDER BY i) FILTER (NOT gone), '') AS kept FROM runs GROUP BY doc_id)
SELECT d.doc_id, CAST(len(x) AS BIGINT) AS n_bytes, coalesce(n_removed, 0) AS n_removed, coalesce(n_spans, 0) AS n_spans, sha256(unhex(coalesce(kept, ''))) AS kept_sha256
FROM d LEFT JOIN summed USING (doc_id)"""

SQL: dict[str, str] = {
    "op2_pii": _pii(),
    "op4_warc": _WARC,
    "op5_suffix_dedup": _REPEATS,
    "op7_minhash": near_duplicates(3, 85),
    "op9_spaced_seeds": passages(),
}
