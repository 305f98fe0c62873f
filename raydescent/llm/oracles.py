"""DuckDB SQL for the queries of this subpackage that SQL can express; the others are tested against brute force."""

from __future__ import annotations

from raydescent.llm.common import LOWER, UPPER
from raydescent.llm.license_votes import BASE_PHRASES, TEMPLATES, K
from raydescent.llm.url_reputation import PRODUCTION_RULES, TWO_LABEL_SUFFIXES


def host_reputation() -> str:
    """Counts by host, then three levels of shrinkage, each strength from the spread around the level above."""
    rules = sorted(PRODUCTION_RULES, key=lambda r: -len(r.text))
    fits = [f"(host = '{r.host}' OR ends_with(host, '.{r.host}')) AND starts_with(path, '{r.path}')" for r in rules]
    rule = "CASE " + " ".join(f"WHEN {f} THEN '{r.text}'" for f, r in zip(fits, rules)) + " END"
    verdict = "CASE " + " ".join(f"WHEN {f} THEN '{'allow' if r.allow else 'block'}'" for f, r in zip(fits, rules)) + " END"
    wide = ", ".join(f"'{s}'" for s in TWO_LABEL_SUFFIXES)

    def last(n: int) -> str:
        return f"array_to_string(list_slice(string_split(name, '.'), greatest(1, len(string_split(name, '.')) - {n - 1}), len(string_split(name, '.'))), '.')"

    bare, address = "regexp_replace(host, '^.*@', '')", r"regexp_matches(bare, '^\[|^[0-9.]+(:[0-9]*)?$')"
    name = r"CASE WHEN starts_with(bare, '[') THEN regexp_extract(bare, '^(\[[^\]]*\]?)', 1) ELSE regexp_replace(bare, '\.?(:[0-9]*)?$', '') END"

    def strength(table: str, mean: str) -> str:
        return f"""(SELECT CASE WHEN coalesce(r, 0) = 0 THEN 10000.0 ELSE 1 / least(greatest(o / r, 1 / 10001.0), 0.5) - 1 END FROM (
 SELECT sum((k - n * {mean}) * (k - n * {mean}) - n * {mean} * (1 - {mean})) AS o, sum(n * (n - 1) * {mean} * (1 - {mean})) AS r FROM {table} WHERE n > 1))"""

    return f"""
WITH p AS (SELECT page_id, coalesce(translate(regexp_extract(url, '://([^/?#]*)', 1), '{UPPER}', '{LOWER}'), '') AS host, coalesce(regexp_extract(url, '://[^/?#]*([^?#]*)', 1), '') AS path FROM pages),
l AS (SELECT doc_id AS page_id, max((quality = 1 AND toxic = 0)::INT) AS good FROM labels GROUP BY 1),
h00 AS (SELECT host, count(good)::DOUBLE AS n, coalesce(sum(good), 0)::DOUBLE AS k FROM p LEFT JOIN l USING (page_id) GROUP BY host),
h0 AS (SELECT *, {name} AS name FROM (SELECT *, {bare} AS bare FROM h00)),
h AS (SELECT *, CASE WHEN {address} THEN name WHEN {last(2)} IN ({wide}) THEN {last(3)} ELSE {last(2)} END AS domain,
 CASE WHEN {address} THEN '' WHEN {last(2)} IN ({wide}) THEN {last(2)} ELSE {last(1)} END AS suffix FROM h0),
d0 AS (SELECT domain, suffix, sum(n) AS n, sum(k) AS k FROM h GROUP BY ALL),
s0 AS (SELECT suffix, sum(n) AS n, sum(k) AS k, (SELECT (sum(k) + 1) / (sum(n) + 2) FROM h) AS m FROM d0 GROUP BY suffix),
s AS (SELECT suffix, (k + q * m) / (n + q) AS sm FROM s0, (SELECT {strength('s0', 'm')} AS q)),
d1 AS (SELECT d0.*, sm FROM d0 JOIN s USING (suffix)),
d AS (SELECT domain, (k + q * sm) / (n + q) AS dm FROM d1, (SELECT {strength('d1', 'sm')} AS q)),
h1 AS (SELECT h.*, dm FROM h JOIN d USING (domain)),
r AS (SELECT host, n, n + q AS weight, (k + q * dm) / (n + q) AS g FROM h1, (SELECT {strength('h1', 'dm')} AS q)),
f AS (SELECT p.*, n::BIGINT AS n_labelled, least(1.0::DOUBLE, g + 1.64 * sqrt(g * (1 - g) / (weight + 1))) AS up FROM p JOIN r USING (host))
SELECT page_id, host, path, {rule} AS rule, coalesce({verdict}, CASE WHEN up < 0.5 THEN 'block' ELSE 'allow' END) AS verdict, n_labelled, round(up, 6) AS good_upper FROM f"""


def vector_components() -> str:
    """All pairs of vectors, and the smallest number reached by following links."""
    return """
WITH RECURSIVE v AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings
 WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
link AS MATERIALIZED (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.vec_id <> b.vec_id AND len(a.e) = len(b.e) WHERE list_cosine_similarity(a.e, b.e) >= 0.9),
reach(a, b) AS (SELECT a, b FROM link UNION SELECT reach.a, link.b FROM reach JOIN link ON reach.b = link.a),
low AS (SELECT a, min(b) AS b FROM reach GROUP BY a), many AS (SELECT a, count(*) AS n FROM link GROUP BY a)
SELECT vec_id, coalesce(n, 0)::BIGINT AS n_links, least(vec_id, coalesce(low.b, vec_id)) AS component_id, vec_id <= coalesce(low.b, vec_id) AS kept
FROM embeddings LEFT JOIN low ON low.a = vec_id LEFT JOIN many ON many.a = vec_id"""


def license_votes() -> str:
    """Votes of equal word k-grams by diagonal, merged where neighbouring, verified by cover and span."""
    rows = []
    for number, (label, phrase) in enumerate([*BASE_PHRASES, *TEMPLATES], 1):
        words = phrase.split()
        rows += [f"({number}, '{label}', {number <= len(BASE_PHRASES)}, {len(words)}, {i}, '{' '.join(words[i : i + K])}')" for i in range(len(words) - K + 1)]
    return f"""
WITH w AS MATERIALIZED (SELECT row_number() OVER () AS rid, doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS words FROM documents),
g AS (SELECT rid, i - 1 AS spot, array_to_string(list_slice(words, i, i + {K - 1}), ' ') AS gram FROM (SELECT rid, words, unnest(range(1, len(words) - {K - 2})) AS i FROM w)),
t(template, label, base, length, place, gram) AS (VALUES {', '.join(rows)}),
v AS (SELECT rid, template, label, base, length, spot - place AS diagonal, count(*) AS votes, min(place) AS low, max(place) AS high FROM g JOIN t USING (gram) GROUP BY ALL),
c AS (SELECT *, sum(fresh) OVER (PARTITION BY rid ORDER BY template, diagonal ROWS UNBOUNDED PRECEDING) AS part FROM (
 SELECT *, (base OR coalesce(lag(template) OVER o <> template OR diagonal - lag(diagonal) OVER o > 3, true))::INT AS fresh FROM v WINDOW o AS (PARTITION BY rid ORDER BY template, diagonal))),
s AS (SELECT rid, template, label, base, length, min(diagonal + low) AS first_word, max(diagonal + high + {K}) AS end_word, least(1.0::DOUBLE, sum(votes) / (length - {K - 1})::DOUBLE) AS coverage FROM c GROUP BY rid, template, label, base, length, part),
k AS (SELECT * FROM s WHERE (base AND coverage = 1) OR (NOT base AND coverage >= 0.6 AND end_word - first_word <= length + 6))
SELECT doc_id, len(any_value(words))::BIGINT AS n_words, count(*) FILTER (base)::BIGINT AS n_base, min(first_word) FILTER (base)::BIGINT AS first_word, max(first_word) FILTER (base)::BIGINT AS last_word,
 coalesce(array_to_string(list_sort(list(DISTINCT label) FILTER (base)), ','), '') AS base_labels, coalesce(array_to_string(list_sort(list(DISTINCT label) FILTER (label IS NOT NULL)), ','), '') AS labels, round(coalesce(max(coverage), 0.0), 6) AS score
FROM w LEFT JOIN k USING (rid) GROUP BY rid, doc_id"""


EXACT_DEDUP = r"""
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(norm) AS text_sha256
FROM (SELECT doc_id, norm, min(doc_id) OVER (PARTITION BY norm) AS keep_id, count(*) OVER (PARTITION BY norm) AS group_size
      FROM (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS norm FROM documents))
"""

ORACLES = {"op1_host_reputation": host_reputation(), "op2_nn_descent": vector_components(), "op5_exact_dedup": EXACT_DEDUP, "op6_license_votes": license_votes()}
