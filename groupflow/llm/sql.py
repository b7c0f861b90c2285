"""DuckDB SQL with the results of the operators that SQL can express."""

from __future__ import annotations

from groupflow.llm.url_filter import UrlParams

_LOWER = "translate({0}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

_REACH = """
reach(a, b) AS (
  SELECT a, b FROM links
  UNION
  SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a
)"""


def op2_sql(threshold: float = 0.95) -> str:
    return f"""
WITH RECURSIVE vectors AS (
  SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings
), valid AS (
  SELECT vec_id, v, sqrt(list_dot_product(v, v)) AS norm FROM vectors
  WHERE v IS NOT NULL AND len(v) > 0 AND len(list_filter(v, lambda x: x IS NULL OR NOT isfinite(x))) = 0
    AND list_dot_product(v, v) > 0
), links(a, b) AS (
  SELECT x.vec_id, y.vec_id FROM valid x JOIN valid y ON x.vec_id <> y.vec_id AND len(x.v) = len(y.v)
  WHERE list_dot_product(x.v, y.v) / (x.norm * y.norm) >= {threshold}
), {_REACH}
SELECT e.vec_id, (SELECT count(*) FROM links l WHERE l.a = e.vec_id) AS n_links,
  least(e.vec_id, (SELECT min(b) FROM reach r WHERE r.a = e.vec_id)) AS component_id,
  e.vec_id = least(e.vec_id, (SELECT min(b) FROM reach r WHERE r.a = e.vec_id)) AS kept
FROM embeddings e"""


def op4_sql(threshold: int = 85, width: int = 5) -> str:
    return f"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all({_LOWER.format("coalesce(text, '')")}, '[^\\x20\\x09-\\x0D]+') AS w FROM documents
), sets AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN []
    WHEN len(w) < {width} THEN [array_to_string(w, ' ')]
    ELSE list_distinct(list_transform(range(1, len(w) - {width} + 2), lambda i: array_to_string(w[i:i + {width - 1}], ' '))) END AS s
  FROM words
), flat AS (
  SELECT doc_id, len(s) AS n, unnest(s) AS shingle FROM sets
), links(a, b) AS (
  SELECT x.doc_id, y.doc_id FROM flat x JOIN flat y ON x.shingle = y.shingle AND x.doc_id <> y.doc_id
  GROUP BY x.doc_id, y.doc_id, x.n, y.n
  HAVING 100 * count(*) >= {threshold} * (x.n + y.n - count(*))
), {_REACH}, lowest AS (
  SELECT a, min(b) AS b FROM reach GROUP BY a
)
SELECT s.doc_id, len(s.s) AS n_shingles, least(s.doc_id, l.b) AS component_id, s.doc_id = least(s.doc_id, l.b) AS kept
FROM sets s LEFT JOIN lowest l ON l.a = s.doc_id"""


def op7_sql(p: UrlParams = UrlParams()) -> str:
    fits = "((host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{q}'))"
    rules = sorted(p.rules, key=lambda r: (len(r[0] + r[1]), r), reverse=True)
    cases = [(fits.format(h=h, q=q), h + q, v) for h, q, v in rules]
    rule = "CASE " + " ".join(f"WHEN {c} THEN '{name}'" for c, name, _ in cases) + " END"
    given = "CASE " + " ".join(f"WHEN {c} THEN '{v}'" for c, _, v in cases) + " END"
    levels = []
    for k in range(p.depth + 1):
        levels.append(f"""
step{k} AS (SELECT *, shape[{k + 1}] AS segment FROM level{k}),
child{k} AS (
  SELECT host, template, segment, sum(n_block)::BIGINT AS b, sum(n_labelled)::BIGINT AS n
  FROM step{k} WHERE segment IS NOT NULL GROUP BY ALL
), parent{k} AS (
  SELECT host, template, sum(b)::BIGINT AS pb, sum(n)::BIGINT AS pn, count(*) AS siblings FROM child{k} GROUP BY ALL
), branch{k} AS (
  SELECT c.host, c.template, c.segment, CASE WHEN
    CASE WHEN siblings = 1 THEN true
      WHEN n = 0 OR pn = n THEN siblings <= {p.fanout}
      ELSE (b * (pn - n) - (pb - b) * n)::DOUBLE * (b * (pn - n) - (pb - b) * n)::DOUBLE * pn
        > {p.z * p.z}::DOUBLE * (pb::DOUBLE * (pb_rest)::DOUBLE * n * (pn - n)) END
    THEN c.segment ELSE '*' END AS kept
  FROM child{k} c JOIN (SELECT *, pn - pb AS pb_rest FROM parent{k}) USING (host, template)
), level{k + 1} AS (
  SELECT s.host, s.shape, s.n_block, s.n_labelled, s.template || coalesce('/' || kept, '') AS template
  FROM step{k} s LEFT JOIN branch{k} b ON s.host = b.host AND s.template = b.template AND s.segment = b.segment
)""")
    last = p.depth + 1
    return f"""
WITH cut AS (
  SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages
), split AS (
  SELECT page_id, {_LOWER.format("coalesce(regexp_extract(rest, '^[^/?#]*'), '')")} AS host,
    coalesce(regexp_extract(rest, '^[^/?#]*([^?#]*)', 1), '') AS path FROM cut
), judged AS (
  SELECT *, {rule} AS rule, {given} AS given,
    list_transform(list_transform(string_split_regex(regexp_replace(path, '^/+|/+$', '', 'g'), '/+'),
      lambda s: regexp_replace(s, '[.][A-Za-z0-9]{{1,5}}$', '')),
      lambda s: CASE WHEN regexp_full_match(s, '[0-9]+|[0-9a-f-]{{16,}}') THEN '{{}}' ELSE s END) AS whole
  FROM split
), pageset AS (
  SELECT *, CASE WHEN len(whole) > {p.depth} THEN list_append(whole[1:{p.depth}], '**') ELSE whole END AS shape FROM judged
), level0 AS (
  SELECT host, shape, count(*) FILTER (WHERE given = 'block') AS n_block, count(given) AS n_labelled, '' AS template
  FROM pageset GROUP BY host, shape
), {",".join(levels)}, total AS (
  SELECT host, template, (sum(n_block)::DOUBLE + {p.strength * p.prior}::DOUBLE) / (sum(n_labelled)::DOUBLE + {p.strength}::DOUBLE) AS purity
  FROM level{last} GROUP BY ALL
)
SELECT page_id, s.host, path, rule,
  coalesce(given, CASE WHEN purity > {p.reject} THEN 'block' ELSE 'allow' END) AS verdict, l.template, purity
FROM pageset s JOIN level{last} l ON s.host = l.host AND s.shape = l.shape
JOIN total t ON t.host = l.host AND t.template = l.template"""
