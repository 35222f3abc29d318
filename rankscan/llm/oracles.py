"""DuckDB SQL for the queries that SQL can express."""

_LOW = "translate({x}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _words(text: str, pattern: str) -> str:
    return f"regexp_extract_all({_LOW.format(x=f"coalesce({text}, '')")}, '{pattern}')"


DECONTAMINATION = rf"""
WITH d AS (SELECT doc_id, {_words("text", r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")} AS w FROM documents),
i AS (SELECT coalesce(item_id::varchar, 'null') AS item, {_words("text", r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")} AS w FROM benchmark),
win AS (SELECT DISTINCT item, least(len(w), 13) AS n, array_to_string(w[s : s + least(len(w), 13) - 1], ' ') AS x
        FROM (SELECT item, w, unnest(range(1, greatest(len(w) - 12, 1) + 1)) AS s FROM i WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM win),
place AS (SELECT doc_id, n, s, array_to_string(w[s : s + n - 1], ' ') AS x
          FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS s FROM d, sizes WHERE len(w) >= n)),
hit AS (SELECT DISTINCT doc_id, place.n, s, item FROM place JOIN win ON place.x = win.x AND place.n = win.n),
covered AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS p FROM hit) GROUP BY doc_id),
named AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, item FROM hit) GROUP BY doc_id)
SELECT d.doc_id, len(w)::bigint AS n_words, coalesce(n_hit, 0)::bigint AS n_hit, coalesce(n_items, 0)::bigint AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN covered USING (doc_id) LEFT JOIN named USING (doc_id)
"""

NGRAM_JOIN = rf"""
WITH RECURSIVE d AS (SELECT doc_id, {_words("text", r"[^\x20\x09-\x0D]+")} AS w FROM documents),
sh AS (SELECT DISTINCT doc_id, array_to_string(w[s : s + 2], ' ') AS x FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 2, 1) + 1)) AS s FROM d WHERE len(w) > 0)),
sz AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
links AS (SELECT a.doc_id AS a, b.doc_id AS b FROM sh a JOIN sh b ON a.x = b.x AND a.doc_id <> b.doc_id JOIN sz p ON p.doc_id = a.doc_id JOIN sz q ON q.doc_id = b.doc_id
          WHERE 10 * least(p.n, q.n) >= 9 * greatest(p.n, q.n) GROUP BY a.doc_id, b.doc_id, p.n, q.n HAVING 100 * count(*) >= 90 * (p.n + q.n - count(*))),
reach AS (SELECT doc_id AS v, doc_id AS r FROM documents UNION SELECT reach.v, links.b FROM reach JOIN links ON links.a = reach.r),
comp AS (SELECT v, min(r) AS component_id FROM reach GROUP BY v)
SELECT d.doc_id, coalesce(sz.n, 0)::bigint AS n_shingles, component_id, (SELECT count(*) FROM links WHERE links.a = d.doc_id)::bigint AS n_links
FROM d JOIN comp ON comp.v = d.doc_id LEFT JOIN sz ON sz.doc_id = d.doc_id
"""

SQL = {"op1_decontamination": DECONTAMINATION, "op4_ngram_jaccard_join": NGRAM_JOIN}

TOP_K = """
WITH v AS (SELECT vec_id, [floor(256 * x::double)::bigint FOR x IN embedding] AS q FROM embeddings),
s AS (SELECT a.vec_id AS query_id, b.vec_id, list_sum([x[1] * x[2] FOR x IN list_zip(a.q, b.q)])::bigint AS score FROM v a JOIN v b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id)
SELECT query_id, rank::integer AS rank, vec_id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 5
"""

URL_RULES = f"""
WITH r(verdict, host, path) AS (VALUES ('allow', 'org', '/'), ('block', 'example.org', '/es/'), ('block', 'example.org', '/en/1'), ('allow', 'com', '/fr/'), ('block', 'com', '/de/')),
p AS (SELECT page_id, coalesce({_LOW.format(x="regexp_extract(url, '^(?s:.*?)://([^/?#]*)', 1)")}, '') AS host, coalesce(regexp_extract(url, '^(?s:.*?)://[^/?#]*([^?#]*)', 1), '') AS path FROM pages),
fit AS (SELECT page_id, r.host || r.path AS rule, verdict, row_number() OVER (PARTITION BY page_id ORDER BY length(r.host || r.path) DESC, length(r.host) DESC) AS k
        FROM p JOIN r ON (p.host = r.host OR ends_with(p.host, '.' || r.host)) AND starts_with(p.path, r.path))
SELECT p.page_id, p.host, p.path, rule, coalesce(verdict, 'allow') AS verdict FROM p LEFT JOIN fit ON fit.page_id = p.page_id AND k = 1
"""

WARC_FIXITY = """
WITH t AS (SELECT page_id, 'WARC/1.0\r\nWARC-Type: resource\r\nWARC-Target-URI: ' || coalesce(url, '') || '\r\nContent-Type: text/html\r\nContent-Length: ' || strlen(coalesce(html, ''))::varchar || '\r\n\r\n' || coalesce(html, '') || '\r\n\r\n' AS x, coalesce(html, '') AS html FROM pages),
e AS (SELECT page_id, sha256(x) AS digest, strlen(x)::bigint AS length, count(*) AS copies, max(html) AS html FROM t GROUP BY 1, 2, 3),
f AS (SELECT *, floor(page_id / 256)::bigint AS file FROM e)
SELECT page_id, file, row_number() OVER w - 1 AS pos, coalesce(sum(length) OVER (PARTITION BY file ORDER BY page_id, digest ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::bigint AS "offset", length, digest, copies,
       page_id IN (SELECT page_id FROM marked) AND length(html) > 0 AS corrupt
FROM f WINDOW w AS (PARTITION BY file ORDER BY page_id, digest)
"""


def _mixture() -> str:
    words = _words("text", r"[^\x20\x09-\x0D]+")
    worst = "(SELECT max(pow(s, a - 1)) / sum(pow(s, a)) FROM sh)"
    entropy = "(SELECT ln(sum(pow(s, a))) - a * sum(pow(s, a) * ln(s)) / sum(pow(s, a)) FROM sh)"
    return f"""
WITH RECURSIVE d AS (SELECT doc_id, coalesce(source, '') AS source, len({words})::bigint AS n_tokens FROM documents),
t AS (SELECT source, sum(n_tokens)::bigint AS tokens FROM d GROUP BY source HAVING sum(n_tokens) > 0),
total AS (SELECT sum(tokens)::bigint AS total, count(*) AS n FROM t),
sh AS (SELECT source, tokens, tokens / total AS s FROM t, total),
grid(step, lo, hi, lo2, hi2) AS (
  SELECT 0, 0, 1048577, -1, 1048577
  UNION ALL
  SELECT step + 1, CASE WHEN e THEN (lo + hi) // 2 ELSE lo END, CASE WHEN e THEN hi ELSE (lo + hi) // 2 END, CASE WHEN w THEN (lo2 + hi2) // 2 ELSE lo2 END, CASE WHEN w THEN hi2 ELSE (lo2 + hi2) // 2 END
  FROM (SELECT *, (SELECT {entropy.replace("a *", "(((lo + hi) // 2) / 1048576.0) *").replace("s, a", "s, ((lo + hi) // 2) / 1048576.0")} >= 0.9 * ln(n) - 1e-12 FROM total) AS e,
               {worst.replace("s, a", "s, ((lo2 + hi2) // 2) / 1048576.0")} > 4.0 AS w FROM grid WHERE step < 22)),
alpha AS (SELECT greatest(lo, least(lo2 + 1, 1048576)) / 1048576.0 AS a FROM grid WHERE step = 22),
raised AS (SELECT source, tokens, pow(s, a) AS r FROM sh, alpha),
wt AS (SELECT source, tokens, round(r / (SELECT sum(r) FROM raised), 12) AS weight FROM raised),
q AS (SELECT source, tokens, weight, floor(weight * total)::bigint AS quota FROM wt, total),
p AS (SELECT *, quota // tokens AS passes, quota % tokens AS rest FROM q),
c AS (SELECT doc_id, p.*, n_tokens, epoch, md5('42|' || epoch::varchar || '|' || coalesce(doc_id::varchar, 'null')) AS k FROM (SELECT *, unnest(range(0, passes + 1)) AS epoch FROM p) p JOIN d USING (source)),
o AS (SELECT *, sum(n_tokens) OVER (PARTITION BY source, epoch ORDER BY k, doc_id ROWS UNBOUNDED PRECEDING) AS e FROM c)
SELECT doc_id, source, epoch::integer AS epoch, floor((epoch * tokens + e - n_tokens) / (weight * 1048576))::bigint AS block, n_tokens FROM o WHERE epoch < passes OR e <= rest
"""


def _crc_marked(every: int, sql: str) -> str:
    """DuckDB has no crc32, so the ids are marked by a table-driven fold over the id's digits."""
    return "WITH RECURSIVE " + f"""bits(b, k, v) AS (SELECT b::ubigint, 0, b::ubigint FROM range(256) r(b) UNION ALL SELECT b, k + 1, CASE WHEN v & 1 = 1 THEN xor(v >> 1, 3988292384::ubigint) ELSE v >> 1 END FROM bits WHERE k < 8),
tab AS (SELECT b, v FROM bits WHERE k = 8),
fold(page_id, i, c) AS (SELECT DISTINCT page_id, 0, 4294967295::ubigint FROM pages WHERE page_id IS NOT NULL UNION ALL
  SELECT page_id, i + 1, xor(c >> 8, tab.v) FROM fold JOIN tab ON tab.b = xor(c, ascii(substr(page_id::varchar, i + 1, 1))::ubigint) & 255 WHERE i < length(page_id::varchar)),
marked AS (SELECT page_id FROM fold WHERE i = length(page_id::varchar) AND xor(c, 4294967295::ubigint) % {every} = 0),
""" + sql.strip().removeprefix("WITH ")


SQL |= {"op3_bit_sliced_top_k": TOP_K, "op7_url_rules": URL_RULES, "op2_source_mixture": _mixture(), "op9_warc_fixity": _crc_marked(97, WARC_FIXITY)}
