"""The operators' results as DuckDB SQL, where SQL can express them."""

from __future__ import annotations

from .licences import COPYRIGHT_LINE, KNOWN, SPELLINGS, with_headings
from .urls import LISTED, RULES

_ASSIGN = r"""([pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)"""
_KINDS = [("assign", _ASSIGN, 2, 6), ("access", "AKIA[A-Z0-9]+", 0, 20), ("hex", "[0-9a-f]+", 0, 24), ("live", "[A-Za-z0-9+/_-]{32,}", 0, 32)]
_PLACE = r"(?i)example|changeme|placeholder|your|dummy|xxxx|sample|\*\*|0000000|1234567"


def _secrets() -> str:
    parts = []
    for k, (_, pattern, group, _least) in enumerate(_KINDS):
        value = f"regexp_extract_all(t, '{pattern}', {group})"
        parts.append(f"SELECT r, doc_id, source, {k} AS kind, string_split_regex(t, '{pattern}') AS ps, regexp_extract_all(t, '{pattern}', 0) AS ms, {value} AS vs FROM d")
    least = " ".join(f"WHEN {k} THEN {n}" for k, (*_, n) in enumerate(_KINDS))
    names = " ".join(f"WHEN {k} THEN '{name}'" for k, (name, *_) in enumerate(_KINDS))
    listed = lambda where: f"coalesce(string_agg(name || ':' || s || ':' || e, ',' ORDER BY s, kind) FILTER (WHERE {where}), '')"
    return f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, source, coalesce(text, '') AS t FROM documents),
m AS MATERIALIZED (SELECT r, doc_id, source, kind, ps, ms, vs, unnest(range(1, len(ms) + 1)) AS i FROM ({' UNION ALL '.join(parts)})),
x AS (SELECT r, doc_id, source, kind, vs[i] AS v,
        CAST(list_sum(list_transform(ps[1:i], lambda p: length(p))) + coalesce(list_sum(list_transform(ms[1:i-1], lambda p: length(p))), 0) AS BIGINT) AS s, length(ms[i]) AS n FROM m),
y AS (SELECT *, s + n AS e, CASE kind {names} END AS name,
        length(v) >= 16 AND len(list_distinct(string_split(v, ''))) >= 10 AND NOT regexp_matches(v, '{_PLACE}') AS looks
      FROM x WHERE length(v) >= CASE kind {least} END),
z AS MATERIALIZED (SELECT * FROM y WHERE kind < 3 OR looks),
o AS (SELECT v, count(DISTINCT coalesce(source, chr(1))) AS owners FROM z GROUP BY v),
j AS (SELECT z.*, owners, looks AND owners <= 2 AS live FROM z JOIN o USING (v)),
k AS (SELECT j.*, kind < 3 OR (live AND NOT EXISTS (SELECT 1 FROM j b WHERE b.r = j.r AND b.kind < 3 AND b.s < j.e AND j.s < b.e)) AS kept FROM j),
g AS (SELECT r, count(*) FILTER (WHERE kind = 0) AS n_assign, count(*) FILTER (WHERE kind = 1) AS n_access, count(*) FILTER (WHERE kind = 2) AS n_hex,
        {listed('kind < 3')} AS base, {listed('kept')} AS spans, count(*) FILTER (WHERE kept AND live) AS n_live, count(*) FILTER (WHERE kept AND owners > 2) AS n_example
      FROM k GROUP BY r)
SELECT d.doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex,
  sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans, coalesce(n_live, 0) AS n_live, coalesce(n_example, 0) AS n_example
FROM d LEFT JOIN g USING (r)"""


def _licences() -> str:
    def norm(t: str) -> str:
        t = rf"regexp_replace(lower({t}), '{COPYRIGHT_LINE}', ' ', 'g')"
        t = rf"regexp_replace({t}, '[\x20\x09-\x0D]+', ' ', 'g')"
        for a, b in SPELLINGS:
            t = f"replace({t}, '{a}', '{b}')"
        t = rf"regexp_replace({t}, '[!-/:-@\[-`{{-~“”‘’–—«»©]', ' ', 'g')"
        return rf"trim(regexp_replace({t}, '[\x20\x09-\x0D]+', ' ', 'g'))"

    quoted = [(k, v.replace("'", "''")) for k, v in with_headings(KNOWN)]
    known = " UNION ALL ".join(f"SELECT '{k}' AS license_id, '{v}' AS text" for k, v in quoted)
    return f"""
WITH k AS (SELECT sha256({norm('text')}) AS digest, min(license_id) AS license_id FROM ({known}) GROUP BY 1),
d AS (SELECT doc_id, sha256({norm('text')}) AS digest FROM documents)
SELECT doc_id, digest, license_id FROM d LEFT JOIN k USING (digest)"""


def _urls() -> str:
    host = "coalesce(translate(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '')"
    path = "coalesce(regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1), '')"
    rules = ", ".join(f"('{r}', '{r.split('/')[0]}', '/{r.split('/', 1)[1]}', '{v}')" for r, v in RULES)
    listed = ", ".join(f"('{x}')" for x in LISTED)
    return f"""
WITH p AS (SELECT row_number() OVER () AS n, page_id, {host} AS host, {path} AS path FROM pages),
r(rule, own, start, verdict) AS (VALUES {rules}),
f AS (SELECT n, max_by(rule, length(rule)) AS rule, max_by(verdict, length(rule)) AS verdict
      FROM p JOIN r ON (host = own OR ends_with(host, '.' || own)) AND starts_with(path, start) GROUP BY n),
u AS (SELECT p.n, host, list_filter(string_split(string_split(rtrim(host, '.'), ':')[1], '.'), lambda x: x <> '') AS hs, list_filter(string_split(path, '/'), lambda x: x <> '') AS ps
      FROM p LEFT JOIN f USING (n) WHERE f.n IS NULL),
h AS (SELECT n, ps, array_to_string(hs[k:], '.') AS own FROM (SELECT n, ps, hs, unnest(range(1, greatest(len(hs), 2))) AS k FROM u WHERE len(hs) > 0)),
q AS (SELECT n, own || '/' || array_to_string(ps[:k], '/') AS key FROM (SELECT n, own, ps, unnest(range(0, len(ps) + 1)) AS k FROM h)),
l(key) AS (VALUES {listed}),
m AS (SELECT n, max_by(key, (length(key), key)) AS listed_key FROM q JOIN l USING (key) GROUP BY n)
SELECT page_id, host, path, rule, coalesce(verdict, CASE WHEN listed_key IS NULL THEN 'allow' ELSE 'block' END) AS verdict, listed_key
FROM p LEFT JOIN f USING (n) LEFT JOIN m USING (n)"""


SQL: dict[str, str] = {"op2_secret_ownership": _secrets(), "op6_licence_digests": _licences(), "op10_url_filter": _urls()}
