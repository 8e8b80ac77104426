"""Queries of the training-data operators, and their SQL where SQL can express them."""

from __future__ import annotations

from . import lattice, media, minhash, mixing, packing, phrases, suffixes, surrogates, toxicity, urls
from .common import table


def op1_surrogates(spark, sf_dir):
    return surrogates.replace_entities(table(spark, sf_dir, "documents"), surrogates.session_key(spark)).select("doc_id", "text", "n_entities")


def op2_lattice_hashing(spark, sf_dir):
    return lattice.near_vectors(table(spark, sf_dir, "embeddings"))


def op3_matroska(spark, sf_dir):
    return media.text_media_digest(table(spark, sf_dir, "documents"))


def op4_minimum_bin_slack(spark, sf_dir):
    return packing.pack_documents(table(spark, sf_dir, "documents"))


def op5_flow_mixing(spark, sf_dir):
    return mixing.mix_sources(table(spark, sf_dir, "documents"))


def op6_hashed_suffix_sort(spark, sf_dir):
    return suffixes.repeated_bytes(table(spark, sf_dir, "documents"))


def op7_url_automaton(spark, sf_dir):
    return urls.filter_urls(table(spark, sf_dir, "pages"), urls.PAGE_RULES)


def op8_nnpu_toxicity(spark, sf_dir):
    return toxicity.toxic_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op10_lsh_forest(spark, sf_dir):
    return minhash.near_duplicates(table(spark, sf_dir, "documents"), minhash.QUERY)


def op9_phrase_automata(spark, sf_dir):
    return phrases.repeated_words(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_surrogates, op2_lattice_hashing, op3_matroska, op4_minimum_bin_slack, op5_flow_mixing, op6_hashed_suffix_sort, op7_url_automaton, op8_nnpu_toxicity, op9_phrase_automata, op10_lsh_forest)}

ORACLES: dict[str, str] = {}

ORACLES["op7_url_automaton"] = r"""
WITH cut AS (
  SELECT page_id, CASE WHEN url IS NOT NULL AND strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages
), parts AS (
  SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM cut
), rules(verdict, h, p) AS (
  VALUES ('allow', 'org', '/'), ('block', 'example.org', '/es/'), ('block', 'example.org', '/en/1'), ('allow', 'com', '/fr/'), ('block', 'com', '/de/')
), fits AS (
  SELECT page_id, r.h || r.p AS rule, r.verdict, row_number() OVER (PARTITION BY page_id, host, path ORDER BY length(r.h || r.p) DESC) AS n
  FROM (SELECT DISTINCT page_id, host, path FROM parts) x JOIN rules r ON (host = r.h OR suffix(host, '.' || r.h)) AND starts_with(path, r.p)
)
SELECT a.page_id, a.host, a.path, f.rule, coalesce(f.verdict, 'allow') AS verdict
FROM parts a LEFT JOIN fits f ON a.page_id = f.page_id AND f.n = 1
"""

# the stops at twice a source's size are reached in at most as many rounds as there are sources: taken in order of
# size over weight, the k tightest sources are stopped for the first k at which all others fit
ORACLES["op5_flow_mixing"] = r"""
WITH base AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size FROM documents
), by_source AS (
  SELECT source, sum(size)::BIGINT AS n FROM base GROUP BY source
), weighed AS (
  SELECT source, n, CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS w FROM by_source
), ranked AS (
  SELECT *, row_number() OVER (ORDER BY 2.0 * n / w, source NULLS LAST) AS k, 1.5 * sum(n) OVER () AS total FROM weighed
), stops AS (
  SELECT a.k, a.total - coalesce((SELECT sum(2.0 * b.n) FROM ranked b WHERE b.k < a.k), 0) AS left_over,
    (SELECT sum(b.w) FROM ranked b WHERE b.k >= a.k) AS w_left, 2.0 * a.n / a.w AS ratio FROM ranked a
), cut AS (
  SELECT min(k) AS k FROM stops WHERE left_over / w_left <= ratio
), level AS (
  SELECT s.k, s.left_over / s.w_left AS unit FROM stops s JOIN cut ON s.k = cut.k
), targets AS (
  SELECT r.source, r.n, CASE WHEN l.k IS NULL OR r.k < l.k THEN 2.0 * r.n ELSE r.w * l.unit END AS target FROM ranked r LEFT JOIN level l ON true
), given AS (
  SELECT source, n, target, floor(target + 1e-9)::BIGINT AS give FROM targets
), running AS (
  SELECT b.doc_id, b.size, g.n, g.target, g.give,
    sum(b.size) OVER (PARTITION BY b.source ORDER BY md5('7:' || b.doc_id), b.doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) - b.size AS before
  FROM base b JOIN given g ON b.source IS NOT DISTINCT FROM g.source
)
SELECT doc_id, size, n AS source_size, target,
  (CASE WHEN n > 0 THEN (give // n) * size + greatest(0, least(size, give - (give // n) * n - before)) ELSE 0 END)::BIGINT AS taken
FROM running
"""

ORACLES["op10_lsh_forest"] = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), sets AS (
  SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN []::VARCHAR[] WHEN len(w) = 1 THEN [w[1]] ELSE list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]) END) AS s FROM words
), flat AS (
  SELECT doc_id, len(s) AS n, unnest(s) AS x FROM sets
), common AS (
  SELECT a.doc_id AS a, b.doc_id AS b, any_value(a.n) AS na, any_value(b.n) AS nb, count(*) AS n_common
  FROM flat a JOIN flat b ON a.x = b.x AND a.doc_id < b.doc_id AND 100 * b.n >= 80 * a.n AND 100 * a.n >= 80 * b.n GROUP BY ALL
), links AS (
  SELECT a, b FROM common WHERE 100 * n_common >= 80 * (na + nb - n_common)
), arcs AS (
  SELECT a, b FROM links UNION ALL SELECT b, a FROM links
), reach(node, r) AS (
  SELECT DISTINCT a, a FROM arcs UNION SELECT arcs.b, reach.r FROM reach JOIN arcs ON arcs.a = reach.node
), comp AS (
  SELECT node, min(r) AS c FROM reach GROUP BY node
)
SELECT s.doc_id, len(s.s)::BIGINT AS n_shingles, coalesce(c.c, s.doc_id) AS component_id, s.doc_id = coalesce(c.c, s.doc_id) AS kept
FROM sets s LEFT JOIN comp c ON s.doc_id = c.node
"""

ORACLES["op2_lattice_hashing"] = r"""
WITH RECURSIVE cast_ AS (
  SELECT vec_id, label, embedding::DOUBLE[] AS v FROM embeddings
), usable AS (
  SELECT vec_id, label, v, sqrt(list_sum(list_transform(v, lambda x: x * x))) AS norm FROM cast_
  WHERE label IS NOT NULL AND v IS NOT NULL AND len(list_filter(v, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND list_sum(list_transform(v, lambda x: x * x)) > 0
), links AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM usable a JOIN usable b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.v) = len(b.v)
  WHERE list_inner_product(a.v, b.v) / (a.norm * b.norm) >= 0.93
), reach(node, r) AS (
  SELECT DISTINCT a, a FROM links UNION SELECT links.b, reach.r FROM reach JOIN links ON links.a = reach.node
), comp AS (
  SELECT node, min(r) AS c FROM reach GROUP BY node
), counts AS (
  SELECT a, count(*)::BIGINT AS n FROM links GROUP BY a
)
SELECT e.vec_id, coalesce(n.n, 0)::BIGINT AS n_links, coalesce(c.c, e.vec_id) AS component_id, coalesce(c.c, e.vec_id) = e.vec_id AS kept
FROM embeddings e LEFT JOIN counts n ON e.vec_id = n.a LEFT JOIN comp c ON e.vec_id = c.node
"""
