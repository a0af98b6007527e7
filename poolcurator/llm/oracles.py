"""DuckDB SQL for the queries that SQL can express."""

from poolcurator.llm import licenses, url_filter

OP2 = r"""
WITH d AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS body FROM documents)
SELECT doc_id, min(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       doc_id = min(doc_id) OVER w AS kept, sha256(body) AS text_sha256
FROM d WINDOW w AS (PARTITION BY body)
"""

OP10 = r"""
WITH dw AS (SELECT doc_id, regexp_extract_all(lower(text), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
bw AS (SELECT item_id, regexp_extract_all(lower(text), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
ds AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 4], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM dw)),
bs AS (SELECT DISTINCT item_id, array_to_string(w[i:i + 4], ' ') AS s FROM (SELECT item_id, w, unnest(range(1, len(w) - 3)) AS i FROM bw)),
n AS (SELECT item_id, count(*) AS item_shingles FROM bs GROUP BY item_id)
SELECT doc_id, item_id, item_shingles, count(*) AS shared, count(*) / item_shingles AS containment
FROM ds JOIN bs USING (s) JOIN n USING (item_id)
GROUP BY doc_id, item_id, item_shingles HAVING count(*) >= 0.8 * item_shingles
"""


WORDS = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"


def op3() -> str:
    """Votes by diagonal over all word pairs, merged within three diagonals; the templates are the operator's own list."""
    listed = licenses.templates()
    places = ", ".join(f"('{a}', '{b}', {t}, {j})" for a, b, t, j in licenses.template_pairs(listed))
    facts = ", ".join(f"({t.number}, '{t.label}', {t.base}, {t.whole}, {len(t.words) - 1})" for t in listed)
    return f"""
WITH d AS (SELECT doc_id, row_number() OVER () AS key, {WORDS} AS w FROM documents),
p(a, b, template, place) AS (VALUES {places}),
f(template, label, base, whole, n_pairs) AS (VALUES {facts}),
pairs AS (SELECT key, i, w[i] AS a, w[i + 1] AS b FROM (SELECT key, w, unnest(range(1, len(w))) AS i FROM d)),
hits AS (SELECT DISTINCT key, template, place, i - 1 - place AS diagonal FROM pairs JOIN p USING (a, b)),
votes AS (SELECT key, template, diagonal, count(*) AS n, min(place) AS least FROM hits GROUP BY ALL),
weak AS (SELECT v.*, label, base, n_pairs FROM votes v JOIN f USING (template) WHERE NOT whole AND n * 10 >= n_pairs),
runs AS (SELECT *, sum(fresh) OVER (PARTITION BY key, template ORDER BY diagonal) AS run
  FROM (SELECT *, CASE WHEN diagonal - lag(diagonal) OVER (PARTITION BY key, template ORDER BY diagonal) <= 3 THEN 0 ELSE 1 END AS fresh FROM weak)),
merged AS (SELECT r.key, label, base, min(r.diagonal + CASE WHEN fresh = 1 THEN r.least ELSE 1000000000 END) AS start, count(DISTINCT h.place) / any_value(n_pairs) AS cover
  FROM runs r JOIN hits h ON h.key = r.key AND h.template = r.template AND h.diagonal = r.diagonal GROUP BY r.key, r.template, label, base, run),
spans AS (SELECT key, label, base, diagonal AS start, 1.0::double AS cover FROM votes JOIN f USING (template) WHERE whole AND n = n_pairs
  UNION ALL SELECT key, label, base, start, cover FROM merged WHERE cover >= 0.6)
SELECT doc_id, len(any_value(w))::bigint AS n_words, count(*) FILTER (WHERE base) AS n_base,
  min(start) FILTER (WHERE base) AS first_word, max(start) FILTER (WHERE base) AS last_word,
  coalesce(string_agg(DISTINCT label, ',' ORDER BY label) FILTER (WHERE base), '') AS base_labels,
  coalesce(string_agg(DISTINCT label, ',' ORDER BY label), '') AS labels, coalesce(max(cover), 0.0)::double AS score
FROM d LEFT JOIN spans USING (key) GROUP BY key, doc_id
"""


def op6() -> str:
    """Rules, labels and posteriors level by level; rules, words and suffixes are the operator's own lists."""
    order = sorted(url_filter.RULES, key=lambda r: (len(r[0]) + len(r[1]), r), reverse=True)
    fits = [(f"(host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}')", h + p, v) for h, p, v in order]
    case = lambda n: "CASE " + " ".join(f"WHEN {f[0]} THEN '{f[n]}'" for f in fits) + " END"
    lower = f"translate({{}}, '{url_filter.UPPER}', '{url_filter.LOWER}')"
    words = "|".join(url_filter.BAD_WORDS)
    long = "array_to_string(l[-2:], '.') IN (" + ", ".join(f"'{x}'" for x in url_filter.LONG_SUFFIXES) + ")"

    def strength(table: str, n: str, bad: str, m: str) -> str:
        v, b = f"sum({n} * ({bad} / {n} - {m}) * ({bad} / {n} - {m}))", f"sum({n} * {m} * (1 - {m}))"
        return f"(SELECT CASE WHEN coalesce({v}, 0) = 0 THEN {url_filter.STRONGEST} ELSE greatest({url_filter.WEAKEST}, least({url_filter.STRONGEST}, {b} / {v} - 1)) END AS s FROM {table} WHERE {n} > 0)"

    return f"""
WITH a AS (SELECT page_id, coalesce(url, '') AS u, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
b AS (SELECT *, regexp_extract(rest, '^[^/?#]*') AS h FROM a),
c AS (SELECT page_id, u, {lower.format("h")} AS host, CASE WHEN substr(rest, length(h) + 1, 1) = '/' THEN regexp_extract(substr(rest, length(h) + 1), '^[^?#]*') ELSE '' END AS path FROM b),
r AS (SELECT *, {case(1)} AS rule, {case(2)} AS ruled, regexp_matches({lower.format("u")}, '(?:^|[^a-z0-9])(?:{words})(?:[^a-z0-9]|$)') AS named FROM c),
o AS (SELECT host, string_split(host, '.') AS l, count(*) AS n, count(*) FILTER (named OR coalesce(ruled = 'block', false)) AS bad FROM r GROUP BY host),
hs AS (SELECT host, n, bad, array_to_string(CASE WHEN {long} THEN l[-3:] ELSE l[-2:] END, '.') AS domain, array_to_string(CASE WHEN {long} THEN l[-2:] ELSE l[-1:] END, '.') AS suffix FROM o),
ds AS (SELECT suffix, domain, sum(n) AS n, sum(bad) AS bad FROM hs GROUP BY ALL),
ss AS (SELECT suffix, sum(n) AS n, sum(bad) AS bad, (SELECT sum(bad) / sum(n) FROM ds) AS m FROM ds GROUP BY suffix),
sp AS (SELECT suffix, (bad + s * m) / (n + s) AS m FROM ss, {strength("ss", "n", "bad", "m")}),
dm AS (SELECT ds.*, m FROM ds JOIN sp USING (suffix)),
dp AS (SELECT suffix, domain, (bad + s * m) / (n + s) AS m FROM dm, {strength("dm", "n", "bad", "m")}),
hm AS (SELECT hs.*, m FROM hs JOIN dp USING (suffix, domain)),
hp AS (SELECT host, (bad + s * m) / (n + s) AS p, n + s + 1 AS w FROM hm, {strength("hm", "n", "bad", "m")}),
q AS (SELECT host, p, greatest(0.0, p - {url_filter.Z} * sqrt(p * (1 - p) / w)) AS bound FROM hp)
SELECT page_id, host, path, rule, coalesce(ruled, CASE WHEN bound > {url_filter.BLOCK_ABOVE} THEN 'block' ELSE 'allow' END) AS verdict, round(p, 6) AS reputation, round(bound, 6) AS lower_bound
FROM r JOIN q USING (host)
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_exact_dedup": OP2, "op3_licenses": op3(), "op6_url_filter": op6(), "op10_decontamination": OP10}
