"""DuckDB SQL that tells the results of operators from their definitions, by plain means and without their methods."""

from __future__ import annotations

from dagquotient.llm import spotsigs
from dagquotient.llm.urls import Rule

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_LOWERED = f"translate(coalesce(text, ''), '{UPPER}', '{LOWER}')"


def repeats(length: int = 200) -> str:
    """Every byte of every window that starts elsewhere too, over bytes; what is left goes by hexadecimal digits."""
    return f"""
WITH d AS (SELECT doc_id, encode(coalesce(text, '')) AS raw, hex(encode(coalesce(text, ''))) AS h, strlen(coalesce(text, ''))::BIGINT AS n FROM documents),
w AS (SELECT doc_id, p, md5(raw[p + 1 : p + {length}]) AS k FROM (SELECT doc_id, raw, unnest(range(0, n - {length - 1})) AS p FROM d WHERE n >= {length})),
c AS (SELECT doc_id, p FROM w JOIN (SELECT k FROM w GROUP BY k HAVING count(*) > 1) USING (k)),
f AS (SELECT doc_id, p, coalesce(p > lag(p) OVER o + {length}, true) AS fresh FROM c WINDOW o AS (PARTITION BY doc_id ORDER BY p)),
r AS (SELECT doc_id, min(p) AS s, max(p) + {length} AS e FROM (SELECT doc_id, p, sum(fresh::INT) OVER (PARTITION BY doc_id ORDER BY p) AS g FROM f) GROUP BY doc_id, g),
t AS (SELECT doc_id, s, e, coalesce(lag(e) OVER (PARTITION BY doc_id ORDER BY s), 0) AS b FROM r),
k AS (SELECT doc_id, sum(e - s)::BIGINT AS gone, count(*) AS spans, max(e) AS last, string_agg(substr(h, 2 * b + 1, 2 * (s - b)), '' ORDER BY s) AS front FROM t JOIN d USING (doc_id) GROUP BY doc_id)
SELECT doc_id, n AS n_bytes, coalesce(gone, 0) AS n_removed, coalesce(spans, 0) AS n_spans,
       sha256(unhex(coalesce(front, '') || substr(h, 2 * coalesce(last, 0) + 1))) AS kept_sha256
FROM d LEFT JOIN k USING (doc_id)"""


def jaccard(n: int, percent: int, documents: str = "documents") -> str:
    """All pairs of documents by the n-grams that they share, and what their links reach."""
    gram = " || ' ' || ".join(f"w[i + {k}]" for k in range(n))
    return f"""
WITH RECURSIVE w AS (SELECT doc_id, list_filter(string_split_regex({_LOWERED}, '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS w FROM {documents}),
s AS (SELECT doc_id, CASE WHEN len(w) >= {n} THEN list_distinct(list_transform(range(1, len(w) - {n - 2}), lambda i: {gram})) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END AS g FROM w),
e AS (SELECT doc_id, len(g) AS n, md5_number_lower(unnest(g)) AS x FROM s),
l AS (SELECT a.doc_id AS a, b.doc_id AS b FROM e a JOIN e b ON a.x = b.x AND a.doc_id <> b.doc_id AND 100 * least(a.n, b.n) >= {percent} * greatest(a.n, b.n)
      GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= {percent} * (a.n + b.n - count(*))),
r(id, reach) AS (SELECT a, b FROM l UNION SELECT r.id, l.b FROM r JOIN l ON l.a = r.reach),
m AS (SELECT id, min(reach) AS least FROM r GROUP BY id)
SELECT doc_id, len(g)::BIGINT AS n_shingles, least(doc_id, coalesce(least, doc_id)) AS component_id FROM s LEFT JOIN m ON m.id = s.doc_id"""


def url_verdicts(rules: list[Rule], least_share: float = 0.02, z: float = 2.0, prior: float = 4.0, bound: float = 0.6) -> str:
    """The template tree, a level in each step of the recursion."""
    order = sorted(rules, key=lambda r: (-len(r.name), r.name))

    def case(what: str) -> str:
        return "CASE " + " ".join(f"WHEN (host = '{r.host}' OR ends_with(host, '.{r.host}')) AND starts_with(path, '{r.path}') THEN '{getattr(r, what)}'" for r in order) + " END"

    return f"""
WITH RECURSIVE u AS (
  SELECT page_id, translate(regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)', 1), '{UPPER}', '{LOWER}') AS host,
         regexp_extract(coalesce(url, ''), '(?s)^.*?://[^/?#]*([^?#]*)', 1) AS path FROM pages),
j AS (SELECT page_id, host, path, {case("name")} AS rule, {case("verdict")} AS ruled,
        list_transform(list_filter(string_split(path, '/'), lambda x: x <> ''), lambda x: CASE WHEN regexp_matches(x, '[0-9]') THEN regexp_replace(x, '^[^.]*', '*') ELSE x END) AS shape FROM u),
b AS (SELECT host, shape, count(*) AS seen, count(*) FILTER (WHERE ruled = 'block') AS bad, count(*) FILTER (WHERE ruled = 'allow') AS good FROM j GROUP BY host, shape),
t(depth, host, shape, template, handed, seen, bad, good) AS (
  SELECT 0, host, shape, []::VARCHAR[], (SELECT sum(bad) / sum(seen) FROM b), seen, bad, good FROM b
  UNION ALL
  SELECT depth + 1, host, shape,
         list_concat(template, CASE WHEN NOT keep THEN ['*'] WHEN all_shapes = 1 THEN shape[depth + 1 :] ELSE [segment] END),
         (all_bad + {prior} * handed) / (all_seen + {prior}), seen, bad, good
  FROM (
    SELECT y.* REPLACE (own_seen AS seen, own_bad AS bad, own_good AS good),
           y.seen >= {least_share} * all_seen AND NOT CASE WHEN y.bad + y.good >= 5 AND all_bad + all_good - y.bad - y.good >= 5 THEN
             CASE WHEN all_bad = 0 OR all_good = 0 THEN true
                  ELSE abs(y.bad / (y.bad + y.good) - (all_bad - y.bad) / (all_bad + all_good - y.bad - y.good))
                       < {z} * sqrt(all_bad / (all_bad + all_good) * (1 - all_bad / (all_bad + all_good)) * (1 / (y.bad + y.good) + 1 / (all_bad + all_good - y.bad - y.good))) END ELSE false END AS keep
    FROM (
      SELECT depth, host, shape, template, handed, segment, seen AS own_seen, bad AS own_bad, good AS own_good,
             sum(seen) OVER s AS seen, sum(bad) OVER s AS bad, sum(good) OVER s AS good,
             sum(seen) OVER p AS all_seen, sum(bad) OVER p AS all_bad, sum(good) OVER p AS all_good, count(*) OVER p AS all_shapes
      FROM (SELECT *, shape[depth + 1] AS segment FROM t WHERE len(template) < len(shape))
      WINDOW s AS (PARTITION BY host, template, segment), p AS (PARTITION BY host, template)) y)),
e AS (SELECT * FROM t WHERE len(template) = len(shape)),
v AS (SELECT host, template, (sum(bad) + {prior} * sum(seen * handed) / sum(seen)) / (sum(bad) + sum(good) + {prior}) AS purity FROM e GROUP BY host, template)
SELECT page_id, host, path, rule, coalesce(ruled, CASE WHEN round(purity, 9) > {bound} THEN 'block' ELSE 'allow' END) AS verdict,
       '/' || array_to_string(template, '/') AS template, round(purity, 9) AS purity
FROM j JOIN e USING (host, shape) JOIN v USING (host, template)"""


def fingerprints() -> str:
    """Spot signatures of texts and edited texts by list functions."""
    anchors = "[" + ", ".join(f"'{x}'" for x in sorted(set(spotsigs.ANCHORS))) + "]"

    def sigs(text: str, out: str, source: str) -> str:
        words = f"list_filter(string_split_regex(lower({text}), '[^\\p{{L}}\\p{{N}}]+'), lambda x: x <> '')"
        return f"""
{out}_w AS (SELECT doc_id, {text} AS text, {words} AS w FROM {source}),
{out}_k AS (SELECT doc_id, text, w, list_filter(list_transform(range(1, len(w) + 1), lambda i: CASE WHEN list_contains({anchors}, w[i]) THEN list_prepend(w[i], list_filter(w[i + 1 : i + {spotsigs.REACH}], lambda y: NOT list_contains({anchors}, y))[1 : {spotsigs.CHAIN}]) ELSE [] END), lambda c: len(c) = {spotsigs.CHAIN + 1}) AS c FROM {out}_w),
{out} AS (SELECT doc_id, list_sort(list_distinct(list_transform(
  CASE WHEN len(c) > 0 THEN list_transform(c, lambda x: '3 ' || array_to_string(x, ' ')) WHEN len(w) > 1 THEN list_transform(range(1, len(w)), lambda i: '2 ' || w[i] || ' ' || w[i + 1]) ELSE ['1 ' || text] END,
  lambda x: substr(md5(x), 1, 8)))) AS g FROM {out}_k)"""

    like = "CASE WHEN len({0}) + len({1}) > 0 THEN len(list_intersect({0}, {1})) / (len({0}) + len({1}) - len(list_intersect({0}, {1}))) ELSE 1 END"
    return f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
n AS (SELECT doc_id, text, coalesce(lead(doc_id) OVER o, max(doc_id) OVER ()) AS next_id, coalesce(lead(text) OVER o, first_value(text) OVER o) AS next_text FROM d WINDOW o AS (ORDER BY doc_id DESC)),
x AS (SELECT doc_id, next_id, length(text) AS n_chars, left(text, length(text) - length(text) // 2) || left(next_text, length(text) // 2) AS new FROM n),
{sigs("text", "a", "d")},
{sigs("new", "b", "x")}
SELECT x.doc_id, n_chars::BIGINT AS n_chars, sha256(new) AS edited_sha256, array_to_string(a.g, ',') AS fingerprint, array_to_string(b.g, ',') AS edited_fingerprint,
       {like.format("a.g", "b.g")}::DOUBLE AS near_edited, {like.format("a.g", "c.g")}::DOUBLE AS near_next
FROM x JOIN a ON a.doc_id = x.doc_id JOIN b ON b.doc_id = x.doc_id JOIN a c ON c.doc_id = x.next_id"""
