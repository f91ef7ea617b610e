"""DuckDB twins of the native operators."""

from __future__ import annotations

from momenttree.llm import licences, secrets, urls


def _quoted(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"


def url_rules() -> str:
    rules = ", ".join(f"({_quoted(h)}, {_quoted(p)}, {_quoted(v)})" for h, p, v in urls.RULES)
    form = lambda h, p: f"CASE WHEN regexp_replace({h}, '^(www|m)\\.', '') <> '' THEN regexp_replace({h}, '^(www|m)\\.', '') || regexp_replace({p}, '(/|\\.html)$', '') END"
    rest = lambda u: f"CASE WHEN strpos(coalesce({u}, ''), '://') > 0 THEN substr({u}, strpos({u}, '://') + 3) ELSE '' END"
    host = lambda r: f"translate(regexp_extract({r}, '^[^/?#]*', 0), '{urls.UPPER}', '{urls.LOWER}')"
    path = lambda r: f"regexp_extract({r}, '^[^/?#]*([^?#]*)', 1)"
    return rf"""WITH RECURSIVE rules(rh, rp, rv) AS (VALUES {rules}),
u AS (SELECT row_number() OVER () AS rid, page_id, html, {rest('url')} AS rest FROM pages),
p AS (SELECT rid, page_id, html, {host('rest')} AS host, {path('rest')} AS path FROM u),
f AS (SELECT *, {form('host', 'path')} AS form FROM p),
fit AS (SELECT rid, arg_max(rh || rp, (length(rh || rp), rv = 'allow')) AS rule, arg_max(rv, (length(rh || rp), rv = 'allow')) AS rv FROM f JOIN rules ON (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp) GROUP BY rid),
ruled AS (SELECT f.*, rule, rv FROM f LEFT JOIN fit USING (rid)),
t0 AS (SELECT form AS a, host AS bh, path AS bp, unnest(list_concat(list_transform(regexp_extract_all(html, '(?i)<link\b[^>]*\brel=["'']?canonical["'']?[^>]*>'), lambda x: regexp_extract(x, '(?i)\bhref=["'']?([^"''\s>]+)', 1)), list_transform(regexp_extract_all(html, '(?i)<meta\b[^>]*\bhttp-equiv=["'']?refresh["'']?[^>]*>'), lambda x: regexp_extract(x, '(?i)\burl=["'']?([^"''\s>]+)', 1)))) AS t FROM f WHERE regexp_matches(html, '(?i)canonical|http-equiv')),
ts AS (SELECT *, regexp_extract(t, '^[^?#]*', 0) AS plain FROM t0),
tw AS (SELECT *, CASE WHEN plain = '' THEN bp WHEN starts_with(plain, '/') THEN plain ELSE '/' || regexp_extract(bp, '^/(.*/)?[^/]*$', 1) || plain END AS whole FROM ts),
tl AS (SELECT *, list_reduce(list_transform(string_split(whole, '/'), lambda x: [x]), lambda kept, x: CASE WHEN x[1] = '..' THEN kept[1:greatest(len(kept) - 1, 1)] WHEN x[1] = '.' THEN kept ELSE kept || x END) AS steps FROM tw),
tr AS (SELECT a, CASE WHEN regexp_matches(t, '^[A-Za-z][A-Za-z0-9+.-]*://') THEN t WHEN starts_with(t, '//') THEN 'x:' || t WHEN t <> '' AND NOT regexp_matches(t, '^[A-Za-z][A-Za-z0-9+.-]*:') THEN 'x://' || bh || array_to_string(steps, '/') END AS target FROM tl),
t1 AS (SELECT a, {rest('target')} AS rest FROM tr), t2 AS (SELECT a, {form(host('rest'), path('rest'))} AS b FROM t1),
e AS (SELECT a, b FROM t2 WHERE a <> b UNION SELECT b, a FROM t2 WHERE a <> b),
reach(a, b) AS (SELECT a, a FROM e UNION SELECT r.a, e.b FROM reach r JOIN e ON e.a = r.b),
own AS (SELECT form, bool_or(rv = 'allow') AS allowed FROM ruled WHERE form IS NOT NULL AND rv IS NOT NULL GROUP BY form),
dec AS (SELECT form, bool_or(allowed) AS allowed FROM (SELECT form, allowed FROM own UNION ALL SELECT r.a, o.allowed FROM reach r JOIN own o ON o.form = r.b) GROUP BY form)
SELECT page_id, host, path, rule, coalesce(rv, CASE WHEN allowed THEN 'allow' WHEN NOT allowed THEN 'block' END, 'allow') AS verdict, CASE WHEN rv IS NOT NULL THEN 'rule' WHEN allowed IS NOT NULL THEN 'alias' ELSE 'default' END AS decided_by FROM ruled LEFT JOIN dec USING (form)"""


def secret_scan() -> str:
    parts = []
    kinds = [*secrets.KINDS, secrets.OPAQUE]
    for rank, (kind, pattern, group, least) in enumerate(kinds):
        secret = "hit" if group == 0 else f"regexp_extract(hit, {_quoted(pattern)}, {group})"
        more = " AND regexp_matches(hit, '[0-9]') AND regexp_matches(hit, '[A-Za-z]')" if kind == "opaque" else ""
        parts.append(f"""SELECT rid, owner, repo, s, {rank} AS rank, s + length(hit) AS e, '{kind}' AS kind, {secret} AS secret FROM (
SELECT rid, owner, repo, hits[i] AS hit, CAST(list_sum(list_transform(pieces[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(hits[1:i - 1], lambda x: length(x))), 0) AS BIGINT) AS s FROM (
SELECT *, unnest(range(1, len(hits) + 1)) AS i FROM (SELECT rid, owner, repo, regexp_split_to_array(text, {_quoted(pattern)}) AS pieces, regexp_extract_all(text, {_quoted(pattern)}) AS hits FROM docs)))
WHERE length({secret}) >= {least}{more}""")
    count = lambda k: f"count(*) FILTER (kind = '{k}')"
    joined = lambda where: f"coalesce(string_agg(kind || ':' || s || ':' || e, ',' ORDER BY s, rank) FILTER ({where}), '')"
    return f"""WITH docs AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS text, coalesce(source, '') AS owner, concat_ws('/', coalesce(source, ''), coalesce(lang, '')) AS repo FROM documents),
spans AS ({' UNION ALL '.join(parts)}),
seen AS (SELECT secret, count(DISTINCT owner) >= {secrets.COPIED_OWNERS} OR (count(DISTINCT owner) = 2 AND count(DISTINCT repo) >= {secrets.COPIED_REPOSITORIES}) AS copied FROM spans GROUP BY secret),
judged AS (SELECT s.*, NOT copied AS live, kind <> 'opaque' AS is_base FROM spans s JOIN seen USING (secret)),
kept AS (SELECT * FROM judged j WHERE is_base OR (live AND NOT EXISTS (SELECT 1 FROM judged b WHERE b.rid = j.rid AND b.is_base AND b.s < j.e AND j.s < b.e)))
SELECT doc_id, {count('assign')} AS n_assign, {count('access')} AS n_access, {count('hex')} AS n_hex, sha256({joined('is_base')}) AS base_sha256, {joined('kind IS NOT NULL')} AS spans, count(*) FILTER (kind IS NOT NULL AND NOT is_base) AS n_added, count(*) FILTER (live) AS n_live FROM docs LEFT JOIN kept USING (rid) GROUP BY rid, doc_id"""


def licence_scan() -> str:
    templates = ", ".join(f"({k}, {_quoted(n)}, {_quoted(f)}, {licences.LEAST_SHORT.get(f, licences.LEAST)}, {_quoted(t)})" for k, (n, f, t) in enumerate(licences.TEMPLATES))
    words = lambda t: f"regexp_extract_all(lower({t}), {_quoted(licences.WORD)})"
    mention, name = _quoted(licences.MENTION), f"coalesce(regexp_matches(path, {_quoted(licences.FILE_NAME)}), false)"
    return rf"""WITH tpl(template, license, form, least, text) AS (VALUES {templates}),
d0 AS (SELECT row_number() OVER () AS rid, doc_id, regexp_replace(coalesce(text, ''), '^\s+', '') AS text, concat_ws('/', coalesce(source, ''), coalesce(lang, ''), coalesce(CAST(CAST(floor(doc_id / 100.0) AS BIGINT) AS VARCHAR), ''), coalesce(CAST(doc_id AS VARCHAR), '')) AS path FROM documents),
h AS (SELECT *, len({words('text')}) AS n_words, list_filter(regexp_split_to_array(text, {_quoted(licences.BLANK)}), lambda x: regexp_matches(x, {mention})) AS blocks FROM d0 WHERE regexp_matches(text, {mention})),
ln AS (SELECT rid, 'line' AS level, i = 1 AS first, parts[i] AS text FROM (SELECT rid, parts, unnest(range(1, len(parts) + 1)) AS i FROM (SELECT rid, regexp_split_to_array(text, '[\r\n]+') AS parts FROM h)) WHERE regexp_matches(parts[i], {mention})),
each AS (SELECT * FROM (SELECT * FROM ln UNION ALL SELECT rid, 'block', starts_with(text, b), b FROM (SELECT rid, text, unnest(blocks) AS b FROM h) WHERE contains(b, chr(10)) UNION ALL SELECT rid, 'text', false, text FROM h WHERE {name} OR coalesce(list_sum(list_transform(blocks, lambda x: len({words('x')}))), 0) >= {licences.CANDIDATE_SHARE} * n_words) WHERE 2 * len(list_intersect(list_distinct({words('text')}), [{", ".join(map(_quoted, licences.VOCABULARY))}])) >= len(list_distinct({words('text')}))),
part AS (SELECT DISTINCT text FROM each), n AS (SELECT count(*) + {len(licences.TEMPLATES)} + 1.0 AS n FROM part),
terms AS (SELECT text, term, count(*) AS tf FROM (SELECT text, unnest({words('text')}) AS term FROM part) GROUP BY ALL),
mterms AS (SELECT template, term, count(*) AS tf FROM (SELECT template, unnest({words('text')}) AS term FROM tpl) GROUP BY ALL),
idf AS (SELECT term, ln(n / (count(*) + 1)) + 1 AS idf FROM (SELECT term FROM terms UNION ALL SELECT term FROM mterms) CROSS JOIN n GROUP BY term, n),
w AS (SELECT text, term, tf * idf AS w FROM terms JOIN idf USING (term)),
norm AS (SELECT text, sqrt(sum(w * w)) AS norm FROM w GROUP BY text),
unit AS (SELECT template, term, tf * idf / sqrt(sum(tf * idf * tf * idf) OVER (PARTITION BY template)) AS unit FROM mterms JOIN idf USING (term)),
sc AS (SELECT w.text, u.template, round(sum(w * unit) / any_value(norm), 9) AS cosine FROM w JOIN unit u USING (term) JOIN norm ON norm.text = w.text GROUP BY w.text, u.template),
best AS (SELECT sc.text, arg_min(license, (-cosine, license, form)) AS license, arg_min(form, (-cosine, license, form)) AS form, max(cosine) AS cosine FROM sc JOIN tpl t USING (template) WHERE cosine >= least GROUP BY sc.text),
own AS (SELECT rid, arg_min(license, (-cosine, license)) AS license, max(cosine) AS cosine, greatest(sum(CASE WHEN level = 'line' THEN s ELSE 0 END), sum(CASE WHEN level = 'block' THEN s ELSE 0 END), sum(CASE WHEN level = 'text' THEN s ELSE 0 END)) AS head, bool_or(first AND form = 'title') AS titled FROM (SELECT each.*, len({words('each.text')}) AS s FROM each) e JOIN best b ON b.text = e.text GROUP BY rid),
lic AS (SELECT rid, doc_id, path, license, cosine, head * 1.0 / n_words AS share, titled OR head * 1.0 / n_words >= {licences.FILE_SHARE} OR {name} AS is_file FROM own JOIN h USING (rid)),
files AS (SELECT regexp_extract(path, '^(.*)/[^/]*$', 1) AS folder, arg_min(license, (-share, doc_id, license)) AS given FROM lic WHERE is_file GROUP BY 1),
oth AS (SELECT rid, doc_id, path, string_split(path, '/') AS parts FROM d0 WHERE rid NOT IN (SELECT rid FROM lic)),
anc AS (SELECT rid, k, array_to_string(parts[1:k], '/') AS folder FROM (SELECT rid, parts, unnest(range(0, len(parts))) AS k FROM oth)),
near AS (SELECT rid, arg_max(given, (k, given)) AS given, arg_max(folder, (k, given)) AS folder FROM anc JOIN files USING (folder) GROUP BY rid)
SELECT doc_id, path, license, cosine, CASE WHEN is_file THEN 'file' ELSE 'header' END AS found, NULL AS inherited_from FROM lic UNION ALL SELECT doc_id, path, given, NULL, CASE WHEN given IS NULL THEN 'none' ELSE 'inherited' END, folder FROM oth LEFT JOIN near USING (rid)"""
