"""DuckDB SQL of the corpus queries that SQL can express."""

from __future__ import annotations

from gradsift.llm.urlvocab import RULES, SOFT, SOFT_LIMIT, STRICT

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
BLANK_WORD = r"[^\x20\x09-\x0D]+"
ALNUM_WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def lower(text: str) -> str:
    return f"translate({text}, '{UPPER}', '{LOWER}')"


def words(text: str, pattern: str) -> str:
    return f"regexp_extract_all(coalesce({text}, ''), '{pattern}')"


def runs(size: int) -> str:
    """Windows of `size` words of the list w, as strings, or all words of a
    shorter list as one."""
    return f"CASE WHEN len(w) = 0 THEN [] ELSE list_transform(range(greatest(len(w) - {size} + 1, 1)), lambda i: list_aggregate(w[i + 1 : i + {size}], 'string_agg', ' ')) END"


WU_MANBER = f"""
WITH d AS (SELECT doc_id, {words(lower("text"), ALNUM_WORD)} AS w FROM documents),
b AS (SELECT CAST(item_id AS VARCHAR) AS item, {words(lower("text"), ALNUM_WORD)} AS w FROM benchmark),
bw AS (SELECT DISTINCT item, least(len(w), 10) AS n, unnest({runs(10)}) AS p FROM b WHERE len(w) > 0),
sz AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT doc_id, n, i, list_aggregate(w[i : i + n - 1], 'string_agg', ' ') AS p FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, sz WHERE len(w) >= n)),
hit AS (SELECT doc_id, dw.n, i, item FROM dw JOIN bw ON dw.p = bw.p AND dw.n = bw.n),
pos AS (SELECT doc_id, count(DISTINCT x) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS x FROM (SELECT DISTINCT doc_id, n, i FROM hit)) GROUP BY doc_id),
its AS (SELECT doc_id, count(DISTINCT item) AS n_items, string_agg(DISTINCT item, ',' ORDER BY item) AS s FROM hit GROUP BY doc_id)
SELECT doc_id, len(w) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(s, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN pos USING (doc_id) LEFT JOIN its USING (doc_id)"""

SUPERMINHASH = f"""
WITH RECURSIVE d AS (SELECT doc_id, {words(lower("text"), BLANK_WORD)} AS w FROM documents),
s AS MATERIALIZED (SELECT DISTINCT doc_id, unnest({runs(5)}) AS g FROM d),
n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
e AS MATERIALIZED (SELECT a, b FROM (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM s x JOIN s y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY ALL)
  JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * c >= 85 * (na.n + nb.n - c)),
r AS (SELECT doc_id AS v, doc_id AS root FROM d UNION SELECT e.b, r.root FROM r JOIN e ON e.a = r.v),
m AS (SELECT v, min(root) AS root FROM r GROUP BY v)
SELECT d.doc_id, coalesce(n, 0) AS n_shingles, root AS component_id, d.doc_id = root AS kept FROM d JOIN m ON m.v = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id"""

PHRASES = f"""
WITH d AS (SELECT doc_id, {words("text", BLANK_WORD)} AS w FROM documents),
p AS (SELECT doc_id, i, md5(list_aggregate(w[i : i + 34], 'string_agg', ' ')) AS h FROM (SELECT doc_id, w, unnest(range(1, len(w) - 33)) AS i FROM d WHERE len(w) >= 35)),
t AS (SELECT doc_id, i FROM p JOIN (SELECT h FROM p GROUP BY h HAVING count(*) > 1) USING (h)),
c AS (SELECT doc_id, list(DISTINCT x) AS gone FROM (SELECT doc_id, unnest(range(i, i + 35)) AS x FROM t) GROUP BY doc_id),
k AS (SELECT doc_id, string_agg(x, ' ' ORDER BY i) AS kept FROM (SELECT d.doc_id, gone, unnest(w) AS x, unnest(range(1, len(w) + 1)) AS i FROM d LEFT JOIN c USING (doc_id)) WHERE gone IS NULL OR NOT list_contains(gone, i) GROUP BY doc_id)
SELECT doc_id, len(w) AS n_words, coalesce(len(gone), 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN c USING (doc_id) LEFT JOIN k USING (doc_id)"""


def _list(terms: tuple[str, ...]) -> str:
    return "[" + ", ".join(f"'{t}'" for t in terms) + "]"


def url_vocabulary() -> str:
    fits = "\n  UNION ALL ".join(
        f"SELECT page_id, '{h + p}' AS rule, '{verdict}' AS rv FROM u WHERE (host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}')" for verdict, h, p in RULES
    )
    return f"""
WITH v AS (SELECT page_id, strpos(coalesce(url, ''), '://') AS m, url FROM pages),
t AS (SELECT page_id, CASE WHEN m > 0 THEN substr(url, m + 3) ELSE '' END AS rest FROM v),
u AS (SELECT page_id, {lower("regexp_extract(rest, '^[^/?#]*')")} AS host, CASE WHEN regexp_matches(rest, '^[^/?#]*/') THEN regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) ELSE '' END AS path FROM t),
f AS ({fits}),
b AS (SELECT page_id, arg_max(rule, length(rule)) AS rule, arg_max(rv, length(rule)) AS rv FROM f GROUP BY page_id),
x AS (SELECT page_id, regexp_extract_all({lower("host || path")}, '[a-z0-9\\x{{80}}-\\x{{10FFFF}}]+') AS w FROM u),
h AS (SELECT page_id, len(list_filter(w, lambda y: list_contains({_list(STRICT)}, y))) AS strict_hits, list_filter(w, lambda y: list_contains({_list(SOFT)}, y)) AS soft FROM x)
SELECT u.page_id, host, path, rule, coalesce(rv, CASE WHEN strict_hits > 0 OR len(list_distinct(soft)) >= {SOFT_LIMIT} THEN 'block' ELSE 'allow' END) AS verdict,
  strict_hits, len(soft) AS soft_hits, len(list_distinct(soft)) AS soft_distinct FROM u JOIN h USING (page_id) LEFT JOIN b USING (page_id)"""


ORACLE: dict[str, str] = {
    "op2_wu_manber": WU_MANBER,
    "op8_superminhash": SUPERMINHASH,
    "op9_repeated_phrases": PHRASES,
    "op10_url_vocabulary": url_vocabulary(),
}
