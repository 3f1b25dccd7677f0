"""Pieces of DuckDB SQL from which the oracles are put together.

They follow the definitions, not the Spark plans: self-joins instead of lists, a product instead of a
sum of logarithms, reachability instead of rounds.
"""

from __future__ import annotations


def words(text: str) -> str:
    return (f"list_filter(string_split(trim(regexp_replace(lower(coalesce({text}, '')), '[^0-9a-zà-öø-ÿß]+', ' ', 'g')), ' '), "
            "lambda x: x <> '')")


def runs(w: str, n: int) -> str:
    return f"list_transform(generate_series(1, len({w}) - {n - 1}), lambda i: array_to_string({w}[i:i + {n - 1}], ' '))"


def word_pairs(w: str) -> str:
    return (f"flatten(list_transform(generate_series(1, len({w}) - 1), lambda i: list_transform(generate_series(i + 1, len({w})), "
            f"lambda j: least({w}[i], {w}[j]) || ' ' || greatest({w}[i], {w}[j]))))")


def beside(x: str, y: str) -> str:
    return f"flatten(list_transform({x}, lambda p: list_transform({y}, lambda q: p || ' | ' || q)))"


def whole(w: str) -> str:
    return f"CASE WHEN len({w}) > 0 THEN [array_to_string({w}, ' ')] ELSE [] END"


def tail(w: str, n: int = 6) -> str:
    d = f"regexp_replace(array_to_string({w}, ''), '[^0-9]', '', 'g')"
    return f"CASE WHEN length({d}) >= {n} THEN [right({d}, {n})] ELSE [] END"


def cents(x: str) -> str:
    return f"CAST(CAST(round({x} * 100) AS BIGINT) AS VARCHAR)"


DOCS = f"rec AS (SELECT min(doc_id) AS rid, 0 AS source, {words('text')} AS words FROM documents GROUP BY text)"


def postings(*families: str) -> str:
    """From ``rec`` (rid, source, attributes)."""
    each = " || ".join(f"({f})" for f in families)
    return f"post AS (SELECT DISTINCT rid, source, unnest({each}) AS sig FROM rec)"


def links(a: float, b: float, rho: float, tau: float, cross: bool = False) -> str:
    """From ``post``: ``kk``, ``pr`` (lo, hi, sig, k, p) and ``links`` (lo, hi, n_sig, prob)."""
    return shared(a, b, rho, cross) + f""",
links AS (SELECT lo, hi, count(*) AS n_sig, 1 - product(1 - p) AS prob FROM pr GROUP BY lo, hi HAVING 1 - product(1 - p) > {tau})"""


def shared(a: float, b: float, rho: float, cross: bool = False) -> str:
    where = " AND x.source <> y.source" if cross else ""
    return f"""kk AS (SELECT sig, count(*) AS k, 1 / (1 + pow({a}::DOUBLE, count(*)) * {b}) AS p FROM post GROUP BY sig
  HAVING count(*) >= 2 AND 1 / (1 + pow({a}::DOUBLE, count(*)) * {b}) > {rho}),
good AS (SELECT post.*, kk.k, kk.p FROM post JOIN kk USING (sig)),
pr AS (SELECT x.rid AS lo, y.rid AS hi, x.sig, x.k, x.p FROM good x JOIN good y ON x.sig = y.sig AND x.rid < y.rid{where})"""


def eliminated(contiguous: bool) -> str:
    """``pr`` without candidates that another shared one of the pair contains, as ``pe``."""
    if contiguous:
        test = "contains(' ' || l.sig || ' ', ' ' || s.sig || ' ')"
    else:  # words of the shorter one in order, with words between them
        test = "regexp_matches(' ' || l.sig || ' ', ' ' || replace(s.sig, ' ', ' (?:.* )?') || ' ')"
    return f"""pe AS (SELECT * FROM pr s WHERE NOT EXISTS (SELECT 1 FROM pr l WHERE l.lo = s.lo AND l.hi = s.hi
  AND len(string_split(l.sig, ' ')) > len(string_split(s.sig, ' ')) AND {test}))"""


def components(nodes: str | None, edges: str) -> str:
    """Least label over reachability; for sparse graphs."""
    start = f"SELECT rid, rid AS m FROM {nodes}" if nodes else "SELECT a AS rid, a AS m FROM both_ways"
    return f"""both_ways AS (SELECT a, b FROM ({edges}) UNION SELECT b, a FROM ({edges})),
reach AS ({start} UNION SELECT e.b, r.m FROM reach r JOIN both_ways e ON e.a = r.rid WHERE r.m < e.b),
cc AS (SELECT rid, min(m) AS entity_id FROM reach GROUP BY rid)"""


def dense_components(edges: str) -> str:
    """Least label of a node's neighbours, round by round until nothing falls; for graphs of any density."""
    return f"""both_ways AS MATERIALIZED (SELECT a, b FROM ({edges}) UNION SELECT b, a FROM ({edges})),
cc(rid, entity_id) USING KEY (rid) AS (SELECT DISTINCT a, a FROM both_ways
  UNION (SELECT e.b, min(n.entity_id) FROM cc n JOIN both_ways e ON e.a = n.rid JOIN recurring.cc o ON o.rid = e.b
    WHERE n.entity_id < o.entity_id GROUP BY e.b))"""


def quality(links: str, truth: str) -> str:
    """tp, fp, fn and rates of two pair sets (lo, hi)."""
    return f"""SELECT tp, fp, fn, round(CASE WHEN tp + fp = 0 THEN 0.0 ELSE tp / (tp + fp) END, 6) AS "precision",
  round(CASE WHEN tp + fn = 0 THEN 0.0 ELSE tp / (tp + fn) END, 6) AS recall,
  round(CASE WHEN 2 * tp + fp + fn = 0 THEN 0.0 ELSE 2 * tp / (2 * tp + fp + fn) END, 6) AS f
FROM (SELECT (SELECT count(*) FROM (SELECT lo, hi FROM {links} INTERSECT SELECT lo, hi FROM {truth})) AS tp,
  (SELECT count(*) FROM (SELECT lo, hi FROM {links} EXCEPT SELECT lo, hi FROM {truth})) AS fp,
  (SELECT count(*) FROM (SELECT lo, hi FROM {truth} EXCEPT SELECT lo, hi FROM {links})) AS fn)"""


# ---- fixtures ----

_NAME = (f"{words('p_name')} || [regexp_replace(lower(p_brand), '[^0-9a-z]+', '', 'g')] || {words('p_type')} || "
         f"['size' || p_size, 'p' || {cents('p_retailprice')}]")
PRODUCTS = f"""pw AS (SELECT p_partkey AS key, {_NAME} AS n FROM part),
p1 AS (SELECT key, CASE WHEN key % 4 = 1 THEN n[1:2] || n[4:] ELSE n END AS n FROM pw),
p2 AS (SELECT key, CASE WHEN key % 5 = 2 THEN n[2:2] || n[1:1] || n[3:] ELSE n END AS n FROM p1),
p3 AS (SELECT key, CASE WHEN key % 6 = 3 THEN n[1:len(n) - 1] ELSE n END AS n FROM p2),
rec AS (SELECT key * 2 AS rid, 0 AS source, n AS name FROM pw UNION ALL SELECT key * 2 + 1, 1, n FROM p3),
truth AS (SELECT key * 2 AS lo, key * 2 + 1 AS hi FROM pw)"""

OFFERS = PRODUCTS.replace("rec AS (", "base AS (", 1) + f""",
last AS (SELECT * FROM lineitem QUALIFY row_number() OVER (PARTITION BY l_partkey ORDER BY l_orderkey DESC, l_linenumber DESC) = 1),
rec AS (SELECT rid, source, name FROM base UNION ALL
  SELECT l_partkey * 2 + 1 + 20000000000, 1, list_transform(p3.n, lambda w: CASE WHEN w = 'p' || {cents('p_retailprice')}
    THEN 'p' || {cents('l_extendedprice / l_quantity')} ELSE w END)
  FROM last JOIN p3 ON l_partkey = p3.key JOIN part ON p_partkey = p3.key)"""


def _person(late: bool) -> str:
    pick = lambda on, new, old: f"(CASE WHEN {on} THEN {new} ELSE {old} END)" if late else f"({old})"
    d3, m3 = "k % 3 = 1", "k // 3 % 3 = 1"
    res = (f"[CAST(1 + (k * 17 + {pick(d3, 400, 0)}) % 997 AS VARCHAR), 'st' || (k // 3 + {pick(d3, 13, 0)}) % 41, 'street', "
           f"'city' || (k + {pick(d3, 7, 0)}) % 25, lpad(CAST(10000 + (k * 37 + {pick(d3, 1000, 0)}) % 4999 AS VARCHAR), 5, '0')]")
    mail = (f"[CAST(1 + (k * 19 + {pick(m3, 300, 0)}) % 991 AS VARCHAR), 'st' || (k // 5 + {pick(m3, 17, 0)}) % 41, 'road', "
            f"'city' || (k + {pick(m3, 9, 0)}) % 25, CAST(20000 + (k * 41 + {pick(m3, 900, 0)}) % 4993 AS VARCHAR)]")
    phone = pick("(k * 7 + k // 100) % 25 < 12", "(k * 7919 + 555555) % 1000000", "(k * 7919) % 1000000")
    state = pick("k % 100 IN (7, 31, 77)", "(k * 3 + 1) % 25", "(k * 3) % 25")
    age = f"18 + (k * 13) % 60 + {pick('k % 50 IN (3, 17, 41)', 7, 3) if late else 0}"
    family = pick("k % 20 = 0", "(k % 37 + 11) % 37", "k % 37")
    return (f"SELECT k * 2 + {int(late)} AS rid, {int(late)} AS source, k AS key, ['g' || k % 31, 'm' || k // 31 % 29, 'f' || {family}] AS name, "
            f"{res} AS res, {mail} AS mail, [lpad(CAST({phone} AS VARCHAR), 6, '0')] AS phone, ['s' || {state}] AS birth_state, "
            f"[CAST({age} AS VARCHAR)] AS age FROM (SELECT c_custkey AS k FROM customer) WHERE "
            + ("(k % 100 < 59 OR k % 100 >= 66)" if late else "k % 100 < 66"))


PEOPLE = f"""pa AS ({_person(False)}), pb AS ({_person(True)}), rec AS (SELECT * FROM pa UNION ALL SELECT * FROM pb),
truth AS (SELECT pa.rid AS lo, pb.rid AS hi FROM pa JOIN pb USING (key))"""

_PAGE = "regexp_extract(html, '(?s)<article>(.*?)</article>', 1)"
for _p in ("(?s)<(script|style)[^>]*>.*?</(script|style)>", "(?s)<h1>.*?</h1>", "(?s)<[^>]+>", "&[a-z0-9#]+;"):
    _PAGE = f"regexp_replace({_PAGE}, '{_p}', ' ', 'g')"
_BIB = "SELECT rid, source, body[1:12] AS title, list_sort(list_distinct(body[greatest(len(body) - 5, 1):])) AS authors, body FROM"
BIB = f"""rec AS ({_BIB} (SELECT min(doc_id) * 2 AS rid, 0 AS source, {words('text')} AS body FROM documents GROUP BY text)
  UNION ALL {_BIB} (SELECT page_id * 2 + 1 AS rid, 1 AS source, {words(_PAGE)} AS body FROM pages)),
truth AS (SELECT DISTINCT least(lo, hi) AS lo, greatest(lo, hi) AS hi FROM (SELECT 2 * g.rep AS lo, page_id * 2 + 1 AS hi
  FROM pages JOIN documents d ON regexp_extract(url, '^https?://[^/]+/[a-z]+/([0-9]+)', 1) = CAST(d.doc_id AS VARCHAR)
  JOIN (SELECT text, min(doc_id) AS rep FROM documents GROUP BY text) g ON g.text = d.text))"""
BIB_LIGHT = f"""src AS ({_BIB} (SELECT min(doc_id) * 2 AS rid, 0 AS source, {words('text')} AS body FROM documents GROUP BY text)),
cut AS (SELECT rid + 1 AS rid, 1 AS source, CASE WHEN rid // 2 % 4 = 1 THEN title[1:2] || title[4:] ELSE title END AS title, authors, body FROM src),
rec AS (SELECT * FROM src UNION ALL SELECT rid, source, CASE WHEN rid // 2 % 6 = 3 AND len(title) > 0 THEN title[1:greatest(len(title) - 1, 1)] ELSE title END, authors, body FROM cut),
truth AS (SELECT rid AS lo, rid + 1 AS hi FROM src)"""

MENTIONS = """ord AS (SELECT o_orderkey AS ok, o_custkey AS k, o_orderkey % 4 AS v FROM orders),
raw AS (SELECT ok, k AS key,
  CASE v WHEN 0 THEN ['g' || k % 31, 'm' || k // 31 % 29, 'f' || k % 37] WHEN 1 THEN ['f' || k % 37, 'g' || k % 31] ELSE ['g' || k % 31, 'f' || k % 37] END AS name,
  CASE WHEN v IN (0, 3) THEN [CASE WHEN v = 3 THEN '9' ELSE '' END || (1 + (k * 17) % 997), 'st' || k // 3 % 41, 'street', 'city' || k % 25,
    lpad(CAST(10000 + (k * 37) % 4999 AS VARCHAR), 5, '0')] ELSE [] END AS address,
  CASE WHEN v IN (0, 1) THEN [(1940 + (k * 13) % 60) || '-' || (1 + k % 12) || '-' || (1 + (k * 7) % 28)] ELSE [] END AS dob,
  CASE WHEN v = 0 THEN [lpad(CAST((k * 7919) % 1000000 AS VARCHAR), 6, '0')] ELSE [] END AS phone,
  CASE WHEN v = 1 THEN ['u' || k || '@h' || k % 7 || '.example'] ELSE [] END AS email,
  CASE WHEN v = 2 THEN [lpad(CAST((k * 4093 + 17) % 1000000 AS VARCHAR), 6, '0')] ELSE [] END AS id,
  CASE WHEN v IN (2, 3) THEN [lpad(CAST((k * 6151) % 1000000 AS VARCHAR), 6, '0')] ELSE [] END AS account,
  CASE WHEN v = 3 THEN [lpad(CAST((k * 2741 + 5) % 1000000 AS VARCHAR), 6, '0')] ELSE [] END AS company FROM ord),
rec AS (SELECT min(ok) AS rid, 0 AS source, key, name, address, dob, phone, email, id, account, company FROM raw
  GROUP BY key, name, address, dob, phone, email, id, account, company)"""
