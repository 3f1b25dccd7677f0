"""Queries of the methods, their variants and candidate families, with oracles."""

from __future__ import annotations

from pyspark.sql import functions as F

from sigres.functions import posterior as law
from sigres.functions.text import is_subrecord, words
from sigres.operators import candidates as fam
from sigres.operators import index, metrics, pairs, resolve, verify, world
from sigres.operators.components import Trace, connected_components, flatten, normalise, to_forest
from sigres.operators.records import dedupe_exact, members
from sigres.operators.resolve import Config
from sigres.plans import duck
from sigres.plans.scratch import Scratch
from sigres.sources import fixtures as fx
from sigres.sources.tables import load_table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f
    return add


def long(name: str):
    return F.col(name).cast("long").alias(name)


# ---- records and tokens ----

@query("m01_exact_dedup", "SELECT min(doc_id) AS rid, count(*) AS members FROM documents GROUP BY text")
def _(s, d):
    return dedupe_exact(load_table(s, d, "documents"), ["text"], "doc_id")


@query("m01_members", "SELECT min(doc_id) OVER (PARTITION BY text) AS rid, doc_id FROM documents")
def _(s, d):
    return members(load_table(s, d, "documents"), ["text"], "doc_id")


@query("m02_words", f"SELECT doc_id, len(w) AS n, array_to_string(w[1:20], ' ') AS head FROM (SELECT doc_id, {duck.words('text')} AS w FROM documents)")
def _(s, d):
    return load_table(s, d, "documents").select("doc_id", words(F.col("text")).alias("w")).select(
        "doc_id", F.size("w").cast("long").alias("n"), F.array_join(F.slice("w", 1, 20), " ").alias("head"))


_PLAIN = "array_to_string(" + duck.words("p_name") + ", ' ')"


@query("m02_qgrams", f"""SELECT g, count(*) AS n FROM (SELECT unnest(list_transform(generate_series(1, length(t) - 2), lambda i: substr(t, i, 3))) AS g
FROM (SELECT {_PLAIN} AS t FROM part)) GROUP BY g""")
def _(s, d):
    return load_table(s, d, "part").select(F.explode(words(F.col("p_name"), "qgram")).alias("g")).groupBy("g").agg(F.count("*").alias("n"))


@query("m02_chars", f"SELECT g, count(*) AS n FROM (SELECT unnest(list_transform(generate_series(1, length(t)), lambda i: substr(t, i, 1))) AS g FROM (SELECT {_PLAIN} AS t FROM part)) GROUP BY g")
def _(s, d):
    return load_table(s, d, "part").select(F.explode(words(F.col("p_name"), "char")).alias("g")).groupBy("g").agg(F.count("*").alias("n"))


_TYPE = duck.words("p_name || ' ' || p_brand || ' ' || p_type || ' ' || p_size")


@query("m03_subrecord_gap", f"""WITH r AS (SELECT p_partkey, array_to_string({_TYPE}, ' ') AS t FROM part),
q AS (SELECT DISTINCT w[1] AS a, w[len(w)] AS z FROM (SELECT {duck.words("p_name || ' ' || p_type")} AS w FROM part))
SELECT a || ' ' || z AS short, count(*) AS n FROM r JOIN q ON regexp_matches(' ' || t || ' ', ' ' || a || ' (?:.* )?' || z || ' ') GROUP BY 1""")
def _(s, d):
    part = load_table(s, d, "part")
    text = F.concat_ws(" ", "p_name", "p_brand", "p_type", F.col("p_size").cast("string"))
    ends = words(F.concat_ws(" ", "p_name", "p_type"))
    short = part.select(F.array(F.element_at(ends, 1), F.element_at(ends, -1)).alias("q")).distinct()
    # a few hundred short records against every part: a stated query set, in one pass
    hits = part.select(words(text).alias("w")).join(F.broadcast(short), is_subrecord(F.col("q"), F.col("w")))
    return hits.groupBy(F.array_join("q", " ").alias("short")).agg(F.count("*").alias("n"))


_SMALL = duck.words("p_name || ' ' || p_brand || ' ' || p_type")
_SUBSETS = f"""pw AS (SELECT p_partkey, p_name, {_SMALL} AS w FROM part),
subs AS (SELECT DISTINCT p_partkey, p_name, array_to_string(list_filter(list_transform(generate_series(1, len(w)),
  lambda i: CASE WHEN (m >> (i - 1)) & 1 = 1 THEN w[i] END), lambda x: x IS NOT NULL), ' ') AS sig
  FROM (SELECT *, unnest(generate_series(1, (1::BIGINT << len(w)) - 1)) AS m FROM pw))"""


def _small_parts(s, d):
    return load_table(s, d, "part").select("p_partkey", "p_name", words(F.concat_ws(" ", "p_name", "p_brand", "p_type")).alias("words"))


@query("m04_all_subrecords", f"WITH {_SUBSETS} SELECT sig, count(*) AS n FROM subs GROUP BY sig")
def _(s, d):
    return _small_parts(s, d).select(F.explode(world.all_subrecords(F.col("words"))).alias("sig")).groupBy("sig").agg(F.count("*").alias("n"))


# an entity is a customer, its records the residences of both snapshots
@query("m04_street_world", f"WITH {duck.PEOPLE}" + """, o AS (SELECT DISTINCT key AS entity, array_to_string(list_filter(list_transform(generate_series(1, len(w)), lambda i: CASE WHEN (m >> (i - 1)) & 1 = 1 THEN w[i] END), lambda x: x IS NOT NULL), ' ') AS sig
  FROM (SELECT key, res AS w, unnest(generate_series(1, (1::BIGINT << len(res)) - 1)) AS m FROM rec))
SELECT sig, count(*) AS owners, CASE WHEN count(*) = 1 THEN min(entity) END AS entity FROM o GROUP BY sig""")
def _(s, d):
    streets = fx.people(s, d).select(F.col("key").alias("entity"), F.col("res").alias("words"))
    n = world.enumerate_world(streets).groupBy("sig").agg(F.count("*").alias("owners"), F.min("entity").alias("entity"))
    return n.select("sig", "owners", F.when(F.col("owners") == 1, F.col("entity")).alias("entity"))


# ---- relations ----

@query("m05_rel_equality", "SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS class_id, count(*) OVER (PARTITION BY text) - 1 AS links FROM documents")
def _(s, d):
    """Equal texts as classes: each document's class and how many others it equals; pairs are never expanded."""
    return world.equality_classes(load_table(s, d, "documents"), ["text"], "doc_id").select("doc_id", "class_id", "links")


_NUMBER = "^https?://[^/]+/[a-z]+/([0-9]+)"


@query("m05_rel_regex", f"""SELECT a.page_id AS lid, b.page_id AS rid FROM pages a JOIN pages b
ON regexp_extract(a.url, '{_NUMBER}', 1) = regexp_extract(b.url, '{_NUMBER}', 1) AND a.page_id < b.page_id WHERE regexp_extract(a.url, '{_NUMBER}', 1) <> ''""")
def _(s, d):
    p = load_table(s, d, "pages")
    return world.relation_regex(p.select(F.col("page_id").alias("lid"), F.col("url").alias("lv")),
                                p.select(F.col("page_id").alias("rid"), F.col("url").alias("rv")), _NUMBER).where("lid < rid")


@query("m05_rel_distance", """WITH n AS (SELECT DISTINCT p_name AS v FROM part) SELECT a.v AS lid, b.v AS rid FROM n a JOIN n b ON a.v < b.v AND levenshtein(a.v, b.v) <= 2""")
def _(s, d):
    n = load_table(s, d, "part").select("p_name").distinct()
    return world.relation_distance(n.select(F.col("p_name").alias("lid"), F.col("p_name").alias("lv")),
                                   n.select(F.col("p_name").alias("rid"), F.col("p_name").alias("rv")), 2).where("lid < rid")


_W12 = f"""SELECT b.item_id AS lid, d.rid FROM (SELECT item_id, array_to_string({duck.words('text')}, ' ') AS t FROM benchmark) b
JOIN (SELECT min(doc_id) AS rid, array_to_string({duck.words('text')}, ' ') AS t FROM documents GROUP BY text) d ON contains(' ' || d.t || ' ', ' ' || b.t || ' ')"""


@query("m05_rel_subrecord", _W12)
def _(s, d):
    short = load_table(s, d, "benchmark").select(F.col("item_id").alias("lid"), words(F.col("text")).alias("lv"))
    long_ = fx.doc_dedup(s, d).select("rid", F.col("words").alias("rv"))
    return world.relation_subrecord(short, long_, anchor=8)


# ---- signatures in a labelled world ----

_OWNED = f"{_SUBSETS}, tru AS (SELECT sig, min(p_name) AS entity FROM subs GROUP BY sig HAVING count(DISTINCT p_name) = 1)"


def _owned(s, d):
    rows = _small_parts(s, d).select(F.col("p_name").alias("entity"), F.explode(world.all_subrecords(F.col("words"))).alias("sig")).distinct()
    return Scratch(s, "world").save(rows, "owned")


@query("m06_true_signatures", f"WITH {_OWNED} SELECT sig, entity FROM tru")
def _(s, d):
    return world.true_signatures(_owned(s, d))


@query("m07_closure", f"""WITH {_OWNED} SELECT (SELECT count(*) FROM tru) AS signatures,
(SELECT count(*) FROM tru JOIN (SELECT DISTINCT sig, p_name FROM subs) o USING (sig) WHERE o.p_name <> entity) AS violations""")
def _(s, d):
    owned = _owned(s, d)
    mine = world.true_signatures(owned)
    # every longer subrecord of the same entity must be a signature as well
    bad = world.upward_violations(owned, mine).agg(F.count("*").alias("violations"))
    return mine.agg(F.count("*").alias("signatures")).crossJoin(bad)


@query("m08_common", f"WITH {_OWNED} SELECT (SELECT count(*) FROM tru) AS signatures, 0::BIGINT AS violations")
def _(s, d):
    owned = _owned(s, d)
    mine = world.true_signatures(owned)
    return mine.agg(F.count("*").alias("signatures")).crossJoin(world.common_violations(owned, mine).agg(F.count("*").alias("violations")))


# ---- recurrence and posterior ----

_DOC3 = f"{duck.DOCS}, {duck.postings(duck.runs('words', 3))}"
_PROD3 = f"{duck.PRODUCTS}, {duck.postings(*[duck.runs('name', n) for n in (1, 2, 3)])}"
PROD_FAMILIES = [fam.consecutive("name", n) for n in (1, 2, 3)]


def doc_postings(s, d, n=3):
    return fam.emit(fx.doc_dedup(s, d), [fam.consecutive("words", n)])


@query("m09_histogram", f"WITH {_DOC3} SELECT k, count(*) AS signatures FROM (SELECT sig, count(*) AS k FROM post GROUP BY sig) GROUP BY k")
def _(s, d):
    return index.recurrence_histogram(doc_postings(s, d))


@query("m09_histogram_part", f"WITH {_PROD3} SELECT k, count(*) AS signatures FROM (SELECT sig, count(*) AS k FROM post GROUP BY sig) GROUP BY k")
def _(s, d):
    return index.recurrence_histogram(fam.emit(fx.prod_pair(s, d), PROD_FAMILIES))


@query("m10_mixture_vs_poisson", f"""WITH w AS (SELECT DISTINCT p_partkey, unnest({_SMALL}) AS t FROM part), n AS (SELECT count(*)::DOUBLE AS n FROM part),
r AS (SELECT t, count(*) / (SELECT n FROM n) AS p FROM w GROUP BY t), g AS (SELECT r.p, k, (SELECT n FROM n) AS n FROM r, generate_series(1, 9) t(k) WHERE p < 1)
SELECT k::INTEGER AS k, round(avg(exp(lgamma(n + 1) - lgamma(k + 1) - lgamma(n - k + 1) + k * ln(p) + (n - k) * ln(1 - p))), 6) AS mixture,
round(avg(exp(k * ln(n * p) - n * p - lgamma(k + 1))), 6) AS poisson FROM g GROUP BY k""")
def _(s, d):
    part = _small_parts(s, d)
    n = part.count()
    rates = part.select("p_partkey", F.explode(F.array_distinct("words")).alias("t")).groupBy("t").agg((F.count("*") / n).alias("p"), F.lit(1.0).alias("weight"))
    out = metrics.binomial_mixture_pmf(rates.where("p < 1"), n, list(range(1, 10)))
    return out.select("k", F.round("mixture", 6).alias("mixture"), F.round("poisson", 6).alias("poisson"))


_WORD_K = f"wk AS (SELECT t, count(*) AS k FROM (SELECT DISTINCT p_partkey, unnest({_TYPE}) AS t FROM part) GROUP BY t)"


def _word_k(s, d):
    text = F.concat_ws(" ", "p_name", "p_brand", "p_type", F.col("p_size").cast("string"))
    rows = load_table(s, d, "part").select(F.explode(F.array_distinct(words(text))).alias("t"))
    return rows.groupBy("t").agg(F.count("*").alias("k"))


@query("m11_posterior_rates", f"WITH {_WORD_K} SELECT t, k, round(1 / (1 + exp(least(700.0, k * ln(3.0 / 0.5) + ln(0.1 / 0.9) + 0.5 - 3.0))), 6) AS p FROM wk")
def _(s, d):
    return _word_k(s, d).select("t", "k", F.round(law.posterior_poisson(F.col("k"), 0.5, 3.0, 0.9), 6).alias("p"))


@query("m12_posterior_ab", f"WITH {_WORD_K} SELECT t, k, round(1 / (1 + pow(2.0, least(k, 1000)) * 0.1), 6) AS p FROM wk")
def _(s, d):
    return _word_k(s, d).select("t", "k", F.round(law.posterior(F.col("k"), 2.0, 0.1), 6).alias("p"))


@query("m13_power", f"WITH {_WORD_K} SELECT t, k, round(least(1.0, 0.95 * pow(k, -1.5)), 6) AS p FROM wk")
def _(s, d):
    return _word_k(s, d).select("t", "k", F.round(law.posterior_power(F.col("k"), 1.5, 0.95), 6).alias("p"))


@query("m13_low_mean", f"WITH {_WORD_K} SELECT t, k, round(exp((k - 1) * ln(0.5) - lgamma(k + 1)), 6) AS p FROM wk")
def _(s, d):
    return _word_k(s, d).select("t", "k", F.round(law.posterior_low_mean(F.col("k"), 0.5), 6).alias("p"))


#: The curve over fixed recurrences.
CURVE = """SELECT k::INTEGER AS k, a::DOUBLE AS a, b::DOUBLE AS b, round(1 / (1 + pow(a::DOUBLE, k) * b::DOUBLE), 6) AS p
FROM generate_series(0, 20) t(k), (VALUES (1.1), (1.3), (2.0), (3.0)) x(a), (VALUES (0.05), (0.1), (0.5), (1.0)) y(b)"""
_CUSTOMER_K = "h AS (SELECT k, count(*) AS signatures FROM (SELECT count(*) AS k FROM orders GROUP BY o_custkey) GROUP BY k)"


def _customer_k(s, d):
    """In how many orders a customer's key recurs: (k, signatures)."""
    return index.recurrence_histogram(load_table(s, d, "orders").select(F.col("o_custkey").alias("sig")))


@query("m14_curves", f"""WITH {_CUSTOMER_K} SELECT k, signatures, a::DOUBLE AS a, b::DOUBLE AS b, round(1 / (1 + pow(a::DOUBLE, k) * b::DOUBLE), 6) AS p
FROM h, (VALUES (1.1), (1.3), (2.0), (3.0)) x(a), (VALUES (0.05), (0.1), (0.5), (1.0)) y(b)""")
def _(s, d):
    return metrics.posterior_curves_of(_customer_k(s, d), [1.1, 1.3, 2.0, 3.0], [0.05, 0.1, 0.5, 1.0])


@query("m15_em_fit")
def _(s, d):
    h = {r.k: r.signatures for r in index.recurrence_histogram(doc_postings(s, d)).collect()}
    lam, mu, c = law.fit_em(h)
    a, b = law.two_parameters(lam, mu, c)
    return s.createDataFrame([(lam, mu, c, a, b)], "lam double, mu double, c double, a double, b double")


@query("m17_kmax", f"""WITH {_CUSTOMER_K}, g AS (SELECT a::DOUBLE AS a, b::DOUBLE AS b, rho::DOUBLE AS rho,
  coalesce((SELECT max(k) FROM generate_series(1, 2000) t(k) WHERE 1 / (1 + pow(a::DOUBLE, k) * b::DOUBLE) > rho::DOUBLE), 0) AS k_max
  FROM (VALUES (1.1), (1.3), (2.0), (3.0)) x(a), (VALUES (0.05), (0.1), (0.5)) y(b), (VALUES (0.1), (0.3), (0.5), (0.9)) z(rho))
SELECT a, b, rho, k_max, CAST(sum(CASE WHEN 1 / (1 + pow(a, k) * b) > rho THEN signatures ELSE 0 END) AS BIGINT) AS kept FROM g, h GROUP BY a, b, rho, k_max""")
def _(s, d):
    """The bound on k of each point of a grid, and how many customers' keys recur in few enough orders for it."""
    points = [(a, b, r, law.k_max(r, a, b)) for a in (1.1, 1.3, 2.0, 3.0) for b in (0.05, 0.1, 0.5) for r in (0.1, 0.3, 0.5, 0.9)]
    cells = F.explode(F.array(*[F.struct(*[F.lit(x).alias(n) for n, x in zip(("a", "b", "rho"), p)], F.lit(p[3]).cast("long").alias("k_max")) for p in points])).alias("g")
    rows = _customer_k(s, d).select("k", "signatures", cells)
    return rows.groupBy("g.a", "g.b", "g.rho", "g.k_max").agg(F.sum(F.when(F.col("k") <= F.col("g.k_max"), F.col("signatures")).otherwise(0)).alias("kept"))


# ---- index, pairs, product ----

@query("m18_index", f"WITH {_PROD3}, {duck.shared(2.0, 0.1, 0.3)} SELECT sig, rid, k FROM good")
def _(s, d):
    return index.build_index(fam.emit(fx.prod_pair(s, d), PROD_FAMILIES), 2.0, 0.1, 0.3).select("sig", "rid", "k")


@query("m18_index_dictionary", f"WITH {_DOC3}, {duck.shared(2.0, 0.1, 0.5)} SELECT sig, k, round(p, 6) AS p FROM kk")
def _(s, d):
    found = index.dictionary(doc_postings(s, d), law.k_max(0.5, 2.0, 0.1))
    return index.with_posterior(found, 2.0, 0.1).select("sig", "k", F.round("p", 6).alias("p"))


@query("m18_hashed", f"WITH {_DOC3}, {duck.shared(2.0, 0.1, 0.5)} SELECT rid, count(*) AS n, CAST(sum(k) AS BIGINT) AS k FROM good GROUP BY rid")
def _(s, d):
    return index.build_index(fam.hashed(doc_postings(s, d)), 2.0, 0.1, 0.5).groupBy("rid").agg(F.count("*").alias("n"), F.sum("k").alias("k"))


@query("m19_pairs_dedupe", f"WITH {_DOC3}, {duck.shared(2.0, 0.1, 0.5)} SELECT lo, hi, sig, k FROM pr")
def _(s, d):
    return pairs.generate(index.build_index(doc_postings(s, d), 2.0, 0.1, 0.5)).select("lo", "hi", "sig", "k")


def prod_pairs(s, d, scope="cross", rho=0.3):
    return pairs.generate(index.build_index(fam.emit(fx.prod_pair(s, d), PROD_FAMILIES), 2.0, 0.1, rho), scope)


@query("m19_pairs_cross", f"WITH {_PROD3}, {duck.shared(2.0, 0.1, 0.3, True)} SELECT lo, hi, sig, k FROM pr")
@query("m31_scope_cross", f"WITH {_PROD3}, {duck.shared(2.0, 0.1, 0.3, True)} SELECT lo, hi, sig, k FROM pr")
def _(s, d):
    return prod_pairs(s, d)


@query("m31_scope_both", f"WITH {_PROD3}, {duck.shared(2.0, 0.1, 0.3)} SELECT lo, hi, sig, k FROM pr")
def _(s, d):
    return prod_pairs(s, d, "both")


@query("m20_eliminate_gapped", f"WITH {_PROD3}, {duck.shared(2.0, 0.1, 0.3, True)}, {duck.eliminated(False)} SELECT lo, hi, sig, k FROM pe")
def _(s, d):
    return pairs.eliminate(prod_pairs(s, d), "gapped")


@query("m20_eliminate_contiguous", f"WITH {_PROD3}, {duck.shared(2.0, 0.1, 0.3, True)}, {duck.eliminated(True)} SELECT lo, hi, sig, k FROM pe")
def _(s, d):
    return pairs.eliminate(prod_pairs(s, d), "contiguous")


_SKIP = f"{duck.PRODUCTS}, {duck.postings(duck.runs('name', 3))}, {duck.shared(2.0, 0.1, 0.3, True)}"


@query("m21_skip", f"WITH {_SKIP}, {duck.eliminated(True)} SELECT lo, hi, sig, k FROM pe")
def _(s, d):
    cfg = Config([fam.consecutive("name", 3)], rho=0.3, scope="cross", hashed=False)
    assert not fam.nested(cfg.families)
    return resolve.potential_links(fx.prod_pair(s, d), cfg)


@query("m22_product", f"WITH {_DOC3}, {duck.links(2.0, 0.1, 0.5, 0.0)} SELECT lo, hi, n_sig, round(prob, 6) AS prob FROM links")
def _(s, d):
    found = pairs.combine(pairs.generate(index.build_index(doc_postings(s, d), 2.0, 0.1, 0.5)), 2.0, 0.1)
    return found.select("lo", "hi", "n_sig", F.round("prob", 6).alias("prob"))


W11 = dict(a=2.0, b=0.1, rho=0.5, tau=0.9)


def doc_config(**more) -> Config:
    return Config([fam.consecutive("words", 3)], **(W11 | more))


@query("m23_links", f"WITH {_DOC3}, {duck.links(**W11)} SELECT lo, hi, n_sig FROM links")
def _(s, d):
    return resolve.links(fx.doc_dedup(s, d), doc_config()).select("lo", "hi", "n_sig")


def _verified(test: str) -> str:
    return f"WITH {_DOC3}, {duck.links(**W11)} SELECT lo, hi FROM links JOIN rec x ON x.rid = lo JOIN rec y ON y.rid = hi WHERE {test}"


_JAC = "len(list_intersect(list_distinct(x.words), list_distinct(y.words))) / len(list_distinct(x.words || y.words)) >= 0.5"


@query("m24_verified_jaccard", _verified(_JAC))
def _(s, d):
    return resolve.links(fx.doc_dedup(s, d), doc_config(rule=_word_jaccard(0.5), rule_cols=("words",))).select("lo", "hi")


def _word_jaccard(least):
    # the bound by sizes holds for sets, so sets are compared
    def rule(x, y):
        a, b = F.array_distinct(f"{x}_words"), F.array_distinct(f"{y}_words")
        return F.size(F.array_intersect(a, b)) >= least * F.size(F.array_union(a, b))
    return rule


_PROD_LINKS = f"{duck.PRODUCTS}, {duck.postings(duck.runs('name', 2))}, {duck.links(2.0, 0.1, 0.3, 0.5, True)}"


def _prod_verified(test: str) -> str:
    return f"""WITH {_PROD_LINKS} SELECT lo, hi FROM links JOIN rec x ON x.rid = lo JOIN rec y ON y.rid = hi
WHERE {test.format(x="array_to_string(x.name, ' ')", y="array_to_string(y.name, ' ')")}"""


def _prod_config(rule):
    return Config([fam.consecutive("name", 2)], rho=0.3, tau=0.5, scope="cross", rule=rule, rule_cols=("name",))


@query("m24_verified_levenshtein", _prod_verified("levenshtein({x}, {y}) <= 8"))
def _(s, d):
    return resolve.links(fx.prod_pair(s, d), _prod_config(verify.by_levenshtein("name", 8))).select("lo", "hi")


@query("m24_verified_jaro", _prod_verified("jaro_similarity({x}, {y}) >= 0.85"))
def _(s, d):
    return resolve.links(fx.prod_pair(s, d), _prod_config(verify.by_jaro("name", 0.85))).select("lo", "hi")


@query("m24_verified_jaro_winkler", _prod_verified("jaro_winkler_similarity({x}, {y}) >= 0.9"))
def _(s, d):
    return resolve.links(fx.prod_pair(s, d), _prod_config(verify.by_jaro("name", 0.9, winkler=True))).select("lo", "hi")


PERSON_FAMILIES = [
    fam.compose(fam.word_pairs("name"), fam.consecutive("res", 2)),
    fam.compose(fam.word_pairs("name"), fam.consecutive("mail", 2)),
    fam.compose(fam.word_pairs("name"), fam.last_digits("phone")),
    fam.compose(fam.whole("name"), fam.whole("birth_state"), fam.shifted("age", {0: 3})),
]
_N2, _N3 = duck.word_pairs("name"), duck.whole("name")
_AGE = "CASE WHEN len(age) > 0 THEN [CAST(CAST(age[1] AS BIGINT) + CASE WHEN source = 0 THEN 3 ELSE 0 END AS VARCHAR)] ELSE [] END"
_PERSON = [duck.beside(_N2, duck.runs("res", 2)), duck.beside(_N2, duck.runs("mail", 2)), duck.beside(_N2, duck.tail("phone")),
           duck.beside(duck.beside(_N3, duck.whole("birth_state")), _AGE)]
PEOPLE_POST = f"{duck.PEOPLE}, {duck.postings(*_PERSON)}"
W5 = dict(a=1.3, b=0.5, rho=0.3, tau=0.9)


@query("m24_verified_rules", f"""WITH {PEOPLE_POST}, {duck.links(**W5, cross=True)} SELECT lo, hi FROM links JOIN rec x ON x.rid = lo JOIN rec y ON y.rid = hi
WHERE NOT (x.res = y.res AND x.name[1] <> y.name[1])""")
def _(s, d):
    cfg = Config(PERSON_FAMILIES, **W5, scope="cross", rule=verify.by_rules([verify.not_co_residents()]), rule_cols=("res", "name"))
    return resolve.links(fx.people(s, d), cfg).select("lo", "hi")


@query("m26_rules_mentions", f"""WITH {duck.MENTIONS}, {duck.postings(duck.runs('name', 2), _N3, duck.whole('account'))}, {duck.links(1.3, 0.5, 0.1, 0.3)}
SELECT lo, hi FROM links JOIN rec x ON x.rid = lo JOIN rec y ON y.rid = hi WHERE ((len(x.company) > 0) = (len(y.company) > 0))
AND NOT (len(x.account) > 0 AND len(y.account) > 0 AND x.account = y.account AND len(list_intersect(x.name, y.name)) = 0)""")
def _(s, d):
    rules = verify.by_rules([verify.not_person_and_company(), verify.not_account_only()])
    cfg = Config([fam.consecutive("name", 2), fam.whole("name"), fam.whole("account")], a=1.3, b=0.5, rho=0.1, tau=0.3, eliminate="never",
                 rule=rules, rule_cols=("company", "account", "name"))
    return resolve.links(fx.mentions(s, d), cfg).select("lo", "hi")


# ---- components ----

def _cc(edges: str) -> str:
    return f"WITH RECURSIVE {duck.dense_components(edges)} SELECT rid, entity_id FROM cc"


_BIP = "SELECT DISTINCT l_orderkey * 2 AS a, l_partkey * 2 + 1 AS b FROM lineitem"
_PER_CUSTOMER = "SELECT o_orderkey AS rid, min(o_orderkey) OVER (PARTITION BY o_custkey) AS entity_id FROM orders QUALIFY count(*) OVER (PARTITION BY o_custkey) > 1"


@query("m27_forest", """SELECT CAST(0 AS BIGINT) AS multi_parent, (SELECT count(*) FROM (SELECT DISTINCT a FROM ({e}) UNION SELECT DISTINCT b FROM ({e}))) AS nodes,
true AS ordered""".format(e=_BIP))
def _(s, d):
    forest = to_forest(normalise(fx.bipartite_edges(s, d)), Scratch(s, "forest"), Trace())
    per = forest.groupBy("child").agg(F.count("*").alias("n"))
    nodes = forest.select("parent").union(forest.select("child")).distinct().agg(F.count("*").alias("nodes"))
    one = forest.agg(F.coalesce(F.bool_and(F.expr("parent < child")), F.lit(True)).alias("ordered"))
    return per.agg(F.count_if(F.expr("n > 1")).alias("multi_parent")).crossJoin(nodes).crossJoin(one)


@query("m28_flatten", f"SELECT rid AS child, entity_id AS parent FROM ({_PER_CUSTOMER}) WHERE rid <> entity_id")
def _(s, d):
    scratch, trace = Scratch(s, "flat"), Trace()
    return flatten(to_forest(normalise(fx.chain_edges(s, d)), scratch, trace), scratch, trace).select("child", "parent")


for _name, _edges, _sql in (
        ("chain", lambda s, d: fx.chain_edges(s, d), _PER_CUSTOMER), ("star", lambda s, d: fx.star_edges(s, d), _PER_CUSTOMER),
        ("hublast", lambda s, d: fx.star_edges(s, d, last=True), _PER_CUSTOMER), ("shuffled", lambda s, d: fx.chain_edges(s, d, shuffled=True), _PER_CUSTOMER),
        ("clique", lambda s, d: fx.clique_edges(s, d), _PER_CUSTOMER), ("bip", lambda s, d: fx.bipartite_edges(s, d), _cc(_BIP))):
    query(f"m29_components_{_name}", _sql)(lambda s, d, e=_edges: connected_components(e(s, d)))


@query("m29_toy_components", "SELECT event_id AS rid, min(event_id) OVER (PARTITION BY user_id) AS entity_id FROM events QUALIFY count(*) OVER (PARTITION BY user_id) > 1")
def _(s, d):
    return connected_components(fx.event_edges(s, d))


# ---- end to end ----

def _resolved(ctes: str) -> str:
    return f"WITH RECURSIVE {ctes}, {duck.components('rec', 'SELECT lo AS a, hi AS b FROM links')} SELECT rid, entity_id FROM cc"


_VLINKS = duck.links(**W11) + f""",
checked AS (SELECT lo, hi FROM links JOIN rec x ON x.rid = lo JOIN rec y ON y.rid = hi WHERE {_JAC})"""
W11_ORACLE = f"WITH RECURSIVE {_DOC3}, {_VLINKS}, {duck.components('rec', 'SELECT lo AS a, hi AS b FROM checked')} SELECT rid, entity_id FROM cc"


@query("m30_resolve_documents", W11_ORACLE)
@query("w11_near_copies", W11_ORACLE)
def resolve_documents(s, d):
    return resolve.resolve(fx.doc_dedup(s, d), doc_config(rule=_word_jaccard(0.5), rule_cols=("words",)))


@query("m30_resolve_part", _resolved(_PROD_LINKS))
def _(s, d):
    return resolve.resolve(fx.prod_pair(s, d), _prod_config(None))


_STRICT = dict(a=2.0, b=0.5, rho=0.3, tau=0.999)


@query("m32_star_links", _resolved(f"{_DOC3}, {duck.links(**_STRICT)}"))
def _(s, d):
    return resolve.star_resolve(fx.doc_dedup(s, d), doc_config(**_STRICT))


@query("m33_block_only", f"WITH {_PROD_LINKS} SELECT lo, hi FROM links")
def _(s, d):
    return resolve.blocks(fx.prod_pair(s, d), _prod_config(None))


@query("m33_direct", f"WITH {_PROD_LINKS} SELECT lo, hi, n_sig FROM links")
def _(s, d):
    return resolve.links(fx.prod_pair(s, d), _prod_config(None)).select("lo", "hi", "n_sig")


@query("m30_trace")
def _(s, d):
    """Rounds, edges and sum of ids of both component phases on shuffled chains."""
    t = Trace()
    connected_components(fx.chain_edges(s, d, shuffled=True), trace=t, measure=True).count()
    return s.createDataFrame([(i, p, n, x) for i, (p, n, x) in enumerate(t.sizes)], "round int, phase string, edges long, id_sum long")


# ---- families ----

def _family(name, families, ctes, fixture, sqls):
    query(name, f"WITH {ctes}, {duck.postings(*sqls)} SELECT sig, count(*) AS k FROM post GROUP BY sig")(
        lambda s, d: fam.emit(fixture(s, d), families).groupBy("sig").agg(F.count("*").alias("k")))


for _n in (1, 2, 3):
    _family(f"f01_consecutive{_n}", [fam.consecutive("name", _n)], duck.PRODUCTS, fx.prod_pair, [duck.runs("name", _n)])
_family("f02_word_pairs", [fam.word_pairs("mail")], duck.PEOPLE, fx.people, [duck.word_pairs("mail")])
_family("f03_last_digits", [fam.last_digits("phone")], duck.PEOPLE, fx.people, [duck.tail("phone")])
_family("f04_whole", [fam.whole("name")], duck.PEOPLE, fx.people, [_N3])
_family("f05_compose", [fam.compose(fam.consecutive("title", 2), fam.word_pairs("authors"))], duck.BIB_LIGHT, fx.bib_light,
        [duck.beside(duck.runs("title", 2), duck.word_pairs("authors"))])
_family("f06_shifted", [fam.compose(fam.whole("name"), fam.shifted("age", {0: 3}))], duck.PEOPLE, fx.people, [duck.beside(_N3, _AGE)])
_RANDOM = ("CASE WHEN len(name) > 0 THEN list_transform(generate_series(1, 5), lambda i: array_to_string(list_transform(list_sort(list_distinct("
           "list_transform(generate_series(1, 3), lambda j: (rid * 7919 + i * 104729 + j * 1299709 + 7) % len(name) + 1))), lambda p: name[p]), ' ')) ELSE [] END")
_family("f07_random", [fam.random_subrecords("name", 3, 5, 7)], duck.PRODUCTS, fx.prod_pair, [_RANDOM])
_GRAMMAR = [duck.runs(a, n) for a in ("name", "phone") for n in (1, 2, 3)] + [duck.word_pairs("name"), duck.word_pairs("phone"),
                                                                              duck.beside(duck.runs("name", 1), duck.whole("phone"))]
_family("f08_grammar", fam.grammar(["name", "phone"]), duck.PEOPLE, fx.people, _GRAMMAR)


@query("f09_fallback", f"""WITH {duck.PRODUCTS}, post1 AS (SELECT DISTINCT rid, source, unnest({duck.runs('name', 2)}) AS sig FROM rec),
k1 AS (SELECT sig FROM post1 GROUP BY sig HAVING count(*) <= 3), good1 AS (SELECT post1.* FROM post1 JOIN k1 USING (sig)),
post2 AS (SELECT DISTINCT rid, source, unnest({duck.runs('name', 4)}) AS sig FROM rec WHERE rid NOT IN (SELECT rid FROM good1))
SELECT rid, sig FROM good1 UNION ALL SELECT rid, sig FROM post2""")
def _(s, d):
    cfg = Config([fam.consecutive("name", 2)], a=2.0, b=0.1, rho=0.5)
    return resolve.with_fallback(fx.prod_pair(s, d), cfg, [fam.consecutive("name", 4)]).select("rid", "sig")


@query("f10_qgram_family", f"""WITH rec AS (SELECT p_partkey AS rid, 0 AS source, list_transform(generate_series(1, length(t) - 2), lambda i: substr(t, i, 3)) AS g FROM (SELECT p_partkey, {_PLAIN} AS t FROM part)),
{duck.postings(duck.runs('g', 2))} SELECT sig, count(*) AS k FROM post GROUP BY sig""")
def _(s, d):
    rec = load_table(s, d, "part").select(F.col("p_partkey").alias("rid"), F.lit(0).alias("source"), words(F.col("p_name"), "qgram").alias("g"))
    return fam.emit(rec, [fam.consecutive("g", 2)]).groupBy("sig").agg(F.count("*").alias("k"))


@query("f11_namespace", f"WITH {duck.PEOPLE}, x AS (SELECT DISTINCT rid, unnest(list_transform({duck.tail('phone')}, lambda v: '0: ' || v) || list_transform({duck.whole('age')}, lambda v: '1: ' || v)) AS sig FROM rec) SELECT sig, count(*) AS k FROM x GROUP BY sig")
def _(s, d):
    return fam.emit(fx.people(s, d), [fam.last_digits("phone"), fam.whole("age")], namespace=True).groupBy("sig").agg(F.count("*").alias("k"))
