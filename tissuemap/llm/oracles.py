"""DuckDB SQL for the corpus operators that SQL can express on whole tables."""

from __future__ import annotations

from .quality_rules import STOP_WORDS

_BLANK = r"[\x20\x09-\x0D]"
_WORDS = rf"list_filter(regexp_split_to_array(coalesce(text, ''), '{_BLANK}+'), lambda x: x <> '')"

ORACLES: dict[str, str] = {}

ORACLES["op3_pareto_mixing"] = rf"""
WITH d AS (SELECT doc_id, source, len({_WORDS})::BIGINT AS size FROM documents),
per AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
w AS (SELECT *, CASE (row_number() OVER (ORDER BY encode(source) NULLS LAST) - 1) % 3 WHEN 0 THEN 3.0 WHEN 1 THEN 1.0 ELSE 2.0 END::DOUBLE AS weight,
             source_size * 2.0::DOUBLE AS cap FROM per),
o AS (SELECT *, sum(source_size) OVER ()::DOUBLE * 1.5 AS budget,
             coalesce(sum(cap) OVER (ORDER BY cap / weight, encode(source) NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS full_before,
             sum(weight) OVER (ORDER BY cap / weight, encode(source) NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS open_weight FROM w),
l AS (SELECT *, (budget - full_before) / open_weight AS level FROM o),
f AS (SELECT *, level * weight >= cap AS is_full FROM l),
t AS (SELECT *, CASE WHEN is_full THEN cap ELSE least(cap, weight * (SELECT arg_min(level, cap / weight) FROM f WHERE NOT is_full)) END::DOUBLE AS target FROM f),
s AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size + 1e-9) ELSE 0 END AS whole FROM t),
r AS (SELECT *, greatest(target - whole * source_size, 0) AS rest FROM s),
z AS (SELECT source, size, count(*) AS n FROM d WHERE size > 0 GROUP BY source, size),
y AS (SELECT z.source, z.size, (r.rest - coalesce(sum(z.n * z.size) OVER (PARTITION BY z.source ORDER BY z.size DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
             / (sum(z.n::HUGEINT * z.size * z.size) OVER (PARTITION BY z.source ORDER BY z.size DESC ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))::DOUBLE AS slope
      FROM z JOIN r ON z.source IS NOT DISTINCT FROM r.source),
k AS (SELECT source, arg_max(slope, size) AS slope FROM y WHERE slope * size <= 1 GROUP BY source),
u AS (SELECT d.*, r.source_size, r.target, r.whole, r.rest, k.slope * d.size AS p,
             (('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null')), 1, 13))::BIGINT + 0.5::DOUBLE) / 4503599627370496.0 AS u
      FROM d JOIN r ON d.source IS NOT DISTINCT FROM r.source LEFT JOIN k ON d.source IS NOT DISTINCT FROM k.source),
v AS (SELECT *, CASE WHEN size > 0 AND rest > 0 THEN CASE WHEN p >= 1 THEN -1000 ELSE ln(u / (1 - u)) - ln(p / (1 - p)) END END AS v FROM u),
c AS (SELECT *, sum(size) OVER (PARTITION BY source ORDER BY v NULLS LAST RANGE UNBOUNDED PRECEDING) AS upto FROM v),
g AS (SELECT *, upto - size AS before FROM c)
SELECT doc_id, size, source_size, target, source,
       (size * (CASE WHEN size > 0 THEN whole ELSE 0 END + CASE WHEN v IS NOT NULL AND (upto <= rest OR (before <= rest AND upto - rest < rest - before)) THEN 1 ELSE 0 END))::BIGINT AS taken
FROM g
"""

ORACLES["op5_substring_dedup"] = rf"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
p AS (SELECT doc_id, w, unnest(generate_series(1, len(w) - 19)) AS i FROM d WHERE len(w) >= 20),
g AS (SELECT doc_id, i, array_to_string(w[i:i + 19], ' ') AS t FROM p),
f AS (SELECT t, min((doc_id, i)) AS first FROM g GROUP BY t HAVING count(*) > 1),
x AS (SELECT g.doc_id, g.i FROM g JOIN f USING (t) WHERE (g.doc_id, g.i) <> f.first),
gone AS (SELECT DISTINCT doc_id, unnest(generate_series(i, i + 19)) AS i FROM x),
e AS (SELECT doc_id, unnest(w) AS word, unnest(generate_series(1, len(w))) AS i FROM d),
k AS (SELECT e.doc_id, count(*) AS kept, string_agg(e.word, ' ' ORDER BY e.i) AS t FROM e ANTI JOIN gone ON e.doc_id = gone.doc_id AND e.i = gone.i GROUP BY e.doc_id)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, (len(d.w) - coalesce(k.kept, 0))::BIGINT AS n_removed, sha256(coalesce(k.t, '')) AS kept_sha256
FROM d LEFT JOIN k USING (doc_id)
"""

ORACLES["op6_url_filters"] = r"""
WITH r(rhost, rpath, verdict) AS (VALUES ('org', '/', 'allow'), ('example.org', '/es/', 'block'), ('example.org', '/en/1', 'block'), ('com', '/fr/', 'allow'), ('com', '/de/', 'block')),
p AS (SELECT page_id, CASE WHEN position('://' IN coalesce(url, '')) > 0 THEN substr(url, position('://' IN url) + 3) ELSE '' END AS tail FROM pages),
h AS (SELECT page_id, translate(regexp_extract(tail, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
             regexp_extract(regexp_replace(tail, '^[^/?#]*', ''), '^[^?#]*') AS path FROM p),
m AS (SELECT h.page_id, arg_max(struct_pack(rule := rhost || rpath, verdict := verdict), length(rhost || rpath)) AS best
      FROM h JOIN r ON (h.host = rhost OR suffix(h.host, '.' || rhost)) AND starts_with(h.path, rpath) GROUP BY h.page_id)
SELECT h.page_id, h.host, h.path, m.best.rule AS rule, coalesce(m.best.verdict, 'allow') AS verdict FROM h LEFT JOIN m USING (page_id)
"""

_STOPS = ", ".join(f"'{w}'" for w in dict.fromkeys(STOP_WORDS))
ORACLES["op9_quality_rules"] = rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, {_WORDS} AS w FROM documents),
n AS (SELECT doc_id, text, w, len(w)::BIGINT AS n_words, length(regexp_replace(text, '{_BLANK}', '', 'g'))::BIGINT AS word_chars,
             length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
             list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines FROM d),
p AS (SELECT doc_id, w, unnest(generate_series(1, len(w) - 2)) AS i FROM n WHERE n_words >= 3),
g AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, w[i], w[i + 1], w[i + 2]) AS c FROM p),
z AS (SELECT DISTINCT doc_id, unnest([i, i + 1, i + 2]) AS i FROM g WHERE c > 1),
y AS (SELECT doc_id, count(*) AS n FROM z GROUP BY doc_id),
b AS (SELECT n.*, (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines, coalesce(y.n, 0)::BIGINT AS n_repeat_words,
             length(text) - length(replace(text, '!', '')) AS shouts, length(regexp_replace(text, '[^A-Z]', '', 'g')) AS capitals FROM n LEFT JOIN y USING (doc_id)),
c AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM b)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND NOT (n_symbols / n_words::DOUBLE > 0.3 OR shouts / n_words::DOUBLE > 0.3 OR capitals / length(text)::DOUBLE > 0.5
         OR word_chars / n_words::DOUBLE < 2 OR word_chars / n_words::DOUBLE > 20 OR NOT list_has_any(w, [{_STOPS}]) OR n_dup_lines / len(lines)::DOUBLE > 0.6) AS kept
FROM c
"""

ORACLES["op10_exact_topk"] = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_inner_product(q.v, c.v)::BIGINT AS score FROM v q JOIN v c ON q.vec_id % 100 = 0 AND q.vec_id <> c.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM r WHERE rank <= 10
"""
