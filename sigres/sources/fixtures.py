"""Stand-ins for the experiments' data: views over the given tables by integer arithmetic and regular
expressions, so that any engine makes the same rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sigres.functions.text import cents, words
from sigres.operators.records import distinct_records
from sigres.sources.tables import load_table


def _tag(letter: str, value: Column) -> Column:
    return F.concat(F.lit(letter), value.cast("string"))


def street_world(spark: SparkSession) -> DataFrame:
    """The worked example of three people in six street records."""
    rows = [(1, "Victoria Street"), (1, "Victoria St"), (2, "George Street"), (2, "George St"), (3, "St George Street"), (3, "St George St")]
    return spark.createDataFrame(rows, "entity long, text string").select("entity", F.split("text", " ").alias("words"))


def toy_edges(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(1, 2), (1, 4), (2, 3), (2, 4), (2, 5), (3, 5)], "a long, b long")


def distinct_documents(spark: SparkSession, d: str) -> DataFrame:
    docs = load_table(spark, d, "documents").select("doc_id", "text")
    return distinct_records(docs, ["text"], "doc_id")


def doc_dedup(spark: SparkSession, d: str) -> DataFrame:
    """rid, source, words of the distinct documents."""
    return distinct_documents(spark, d).select(F.col("doc_id").alias("rid"), F.lit(0).alias("source"), words(F.col("text")).alias("words"))


def _bib(df: DataFrame, rid: Column, source: int, body: Column) -> DataFrame:
    return df.select(rid.alias("rid"), F.lit(source).alias("source"), body.alias("body")).select(
        "rid", "source", F.slice("body", 1, 12).alias("title"),
        F.array_sort(F.array_distinct(F.slice("body", F.greatest(F.size("body") - 5, F.lit(1)), 6))).alias("authors"), "body")


def page_text(html: Column) -> Column:
    """Text of the article: scripts, styles, the heading, tags and entities go, in this order."""
    inner = F.regexp_extract(html, "(?s)<article>(.*?)</article>", 1)
    for pattern in ("(?s)<(script|style)[^>]*>.*?</(script|style)>", "(?s)<h1>.*?</h1>", "(?s)<[^>]+>", "&[a-z0-9#]+;"):
        inner = F.regexp_replace(inner, pattern, " ")
    return inner


def bib_pair(spark: SparkSession, d: str) -> DataFrame:
    """Documents (even rid) and pages (odd rid) as two bibliographic sources."""
    docs = _bib(distinct_documents(spark, d), F.col("doc_id") * 2, 0, words(F.col("text")))
    pages = _bib(load_table(spark, d, "pages"), F.col("page_id") * 2 + 1, 1, words(page_text(F.col("html"))))
    return docs.unionByName(pages)


def bib_truth(spark: SparkSession, d: str) -> DataFrame:
    """(lo, hi): document and page, by the number in the page's address, through exact copies."""
    docs = load_table(spark, d, "documents").select("doc_id", F.xxhash64("text").alias("h1"), F.xxhash64(F.lit(1), "text").alias("h2"))
    first = docs.groupBy("h1", "h2").agg(F.min("doc_id").alias("rep"))
    number = F.regexp_extract("url", "^https?://[^/]+/[a-z]+/([0-9]+)", 1)
    pages = load_table(spark, d, "pages").select("page_id", number.alias("n")).where("n <> ''").select("page_id", F.col("n").cast("long").alias("doc_id"))
    pairs = pages.join(docs, "doc_id").join(first, ["h1", "h2"]).select((F.col("rep") * 2).alias("x"), (F.col("page_id") * 2 + 1).alias("y"))
    return pairs.select(F.least("x", "y").alias("lo"), F.greatest("x", "y").alias("hi")).distinct()


def bib_light(spark: SparkSession, d: str) -> DataFrame:
    """Documents against a lightly edited copy: word 3 of the title dropped, or its last word."""
    own = distinct_documents(spark, d)
    a = _bib(own, F.col("doc_id") * 2, 0, words(F.col("text")))
    b = _bib(own, F.col("doc_id") * 2 + 1, 1, words(F.col("text")))
    key = F.floor(F.col("rid") / 2)
    t = F.col("title")
    t = F.when(key % 4 == 1, F.concat(F.slice(t, 1, 2), F.slice(t, 4, 12))).otherwise(t)
    t = F.when((key % 6 == 3) & (F.size(t) > 0), F.slice(t, 1, F.greatest(F.size(t) - 1, F.lit(1)))).otherwise(t)
    return a.unionByName(b.withColumn("title", t))


def own_truth(records: DataFrame) -> DataFrame:
    """rid = 2 key + source: the two records of each key that is in both sources."""
    keys = records.groupBy(F.floor(F.col("rid") / 2).alias("key")).agg(F.count_distinct("source").alias("n")).where("n = 2")
    return keys.select((F.col("key") * 2).alias("lo"), (F.col("key") * 2 + 1).alias("hi"))


def _product_words() -> Column:
    name = words(F.col("p_name"))
    brand = F.regexp_replace(F.lower("p_brand"), "[^0-9a-z]+", "")
    return F.concat(name, F.array(brand), words(F.col("p_type")), F.array(F.concat(F.lit("size"), F.col("p_size").cast("string")),
                                                                       F.concat(F.lit("p"), cents(F.col("p_retailprice")))))


def prod_a(spark: SparkSession, d: str) -> DataFrame:
    return load_table(spark, d, "part").select((F.col("p_partkey") * 2).alias("rid"), F.lit(0).alias("source"), _product_words().alias("name"))


def _edited(name: Column, key: Column) -> Column:
    n = F.when(key % 4 == 1, F.concat(F.slice(name, 1, 2), F.slice(name, 4, 100))).otherwise(name)
    n = F.when(key % 5 == 2, F.concat(F.slice(n, 2, 1), F.slice(n, 1, 1), F.slice(n, 3, 100))).otherwise(n)
    return F.when(key % 6 == 3, F.slice(n, 1, F.size(n) - 1)).otherwise(n)


def prod_b(spark: SparkSession, d: str) -> DataFrame:
    return load_table(spark, d, "part").select((F.col("p_partkey") * 2 + 1).alias("rid"), F.lit(1).alias("source"),
                                               _edited(_product_words(), F.col("p_partkey")).alias("name"))


def prod_pair(spark: SparkSession, d: str) -> DataFrame:
    return prod_a(spark, d).unionByName(prod_b(spark, d))


def prod_offers(spark: SparkSession, d: str) -> DataFrame:
    """The edited catalogue plus one offer per part that was ever sold, with the price of its last order line."""
    part = load_table(spark, d, "part")
    line = load_table(spark, d, "lineitem")
    paid = F.max_by(F.col("l_extendedprice") / F.col("l_quantity"), F.struct("l_orderkey", "l_linenumber"))
    sold = line.groupBy(F.col("l_partkey").alias("p_partkey")).agg(cents(paid).alias("paid"))
    offers = part.join(sold, "p_partkey").withColumn("_n", _edited(_product_words(), F.col("p_partkey")))
    price = F.concat(F.lit("p"), cents(F.col("p_retailprice")))
    offers = offers.select((F.col("p_partkey") * 2 + 1 + 20_000_000_000).alias("rid"), F.lit(1).alias("source"), "p_partkey",
                           F.transform("_n", lambda w: F.when(w == price, F.concat(F.lit("p"), F.col("paid"))).otherwise(w)).alias("name"))
    base = prod_b(spark, d).withColumn("p_partkey", F.floor(F.col("rid") / 2))
    return base.unionByName(offers)


def person(spark: SparkSession, d: str, snapshot: str) -> DataFrame:
    """One of two snapshots of people: name, residence, mail address, phone, birth state, age."""
    k = F.col("c_custkey")
    late = snapshot == "b"
    r = k % 100
    rows = load_table(spark, d, "customer").where((r < 59) | (r >= 66) if late else r < 66)
    pick = lambda changed, new, old: F.when(changed, new).otherwise(old) if late else old
    family = pick(k % 20 == 0, (k % 37 + 11) % 37, k % 37)
    d3, m3 = k % 3 == 1, F.floor(k / 3) % 3 == 1
    res = F.array((1 + (k * 17 + pick(d3, F.lit(400), F.lit(0))) % 997).cast("string"), _tag("st", (F.floor(k / 3) + pick(d3, F.lit(13), F.lit(0))) % 41),
                  F.lit("street"), _tag("city", (k + pick(d3, F.lit(7), F.lit(0))) % 25),
                  F.lpad((10000 + (k * 37 + pick(d3, F.lit(1000), F.lit(0))) % 4999).cast("string"), 5, "0"))
    mail = F.array((1 + (k * 19 + pick(m3, F.lit(300), F.lit(0))) % 991).cast("string"), _tag("st", (F.floor(k / 5) + pick(m3, F.lit(17), F.lit(0))) % 41),
                   F.lit("road"), _tag("city", (k + pick(m3, F.lit(9), F.lit(0))) % 25), (20000 + (k * 41 + pick(m3, F.lit(900), F.lit(0))) % 4993).cast("string"))
    phone = pick((k * 7 + F.floor(k / 100)) % 25 < 12, (k * 7919 + 555555) % 1000000, (k * 7919) % 1000000)
    state = pick((r == 7) | (r == 31) | (r == 77), (k * 3 + 1) % 25, (k * 3) % 25)
    off = k % 50
    age = 18 + (k * 13) % 60 + (pick((off == 3) | (off == 17) | (off == 41), F.lit(7), F.lit(3)) if late else F.lit(0))
    return rows.select((k * 2 + int(late)).alias("rid"), F.lit(int(late)).alias("source"), k.alias("key"),
                       F.array(_tag("g", k % 31), _tag("m", F.floor(k / 31) % 29), _tag("f", family)).alias("name"), res.alias("res"), mail.alias("mail"),
                       F.array(F.lpad(phone.cast("string"), 6, "0")).alias("phone"), F.array(_tag("s", state)).alias("birth_state"),
                       F.array(age.cast("string")).alias("age"))


def people(spark: SparkSession, d: str) -> DataFrame:
    return person(spark, d, "a").unionByName(person(spark, d, "b"))


def mentions(spark: SparkSession, d: str) -> DataFrame:
    """One mention of a party per order, with the attributes that its variant has; distinct mentions only."""
    k, v = F.col("o_custkey"), F.col("o_orderkey") % 4
    none = F.array().cast("array<string>")
    only = lambda on, value: F.when(on, value).otherwise(none)
    six = lambda x: F.array(F.lpad(x.cast("string"), 6, "0"))
    given, middle, family = _tag("g", k % 31), _tag("m", F.floor(k / 31) % 29), _tag("f", k % 37)
    name = F.when(v == 0, F.array(given, middle, family)).when(v == 1, F.array(family, given)).otherwise(F.array(given, family))
    number = (1 + (k * 17) % 997).cast("string")
    address = F.array(F.when(v == 3, F.concat(F.lit("9"), number)).otherwise(number), _tag("st", F.floor(k / 3) % 41), F.lit("street"),
                      _tag("city", k % 25), F.lpad((10000 + (k * 37) % 4999).cast("string"), 5, "0"))
    dob = F.array(F.concat_ws("-", (1940 + (k * 13) % 60).cast("string"), (1 + k % 12).cast("string"), (1 + (k * 7) % 28).cast("string")))
    rows = load_table(spark, d, "orders").select(
        "o_orderkey", k.alias("key"), name.alias("name"), only((v == 0) | (v == 3), address).alias("address"), only((v == 0) | (v == 1), dob).alias("dob"),
        only(v == 0, six((k * 7919) % 1000000)).alias("phone"), only(v == 1, F.array(F.concat(_tag("u", k), _tag("@h", k % 7), F.lit(".example")))).alias("email"),
        only(v == 2, six((k * 4093 + 17) % 1000000)).alias("id"), only((v == 2) | (v == 3), six((k * 6151) % 1000000)).alias("account"),
        only(v == 3, six((k * 2741 + 5) % 1000000)).alias("company"))
    attrs = [c for c in rows.columns if c != "o_orderkey"]
    return rows.groupBy(*attrs).agg(F.min("o_orderkey").alias("rid"), F.count("*").alias("members")).withColumn("source", F.lit(0))


def turns(spark: SparkSession, d: str) -> DataFrame:
    t = load_table(spark, d, "conversations")
    return t.select((F.col("conv_id") * 1000 + F.col("turn")).alias("rid"), F.lit(0).alias("source"), words(F.col("text")).alias("words"))


# ---- graphs ----

def chain_edges(spark: SparkSession, d: str, shuffled: bool = False) -> DataFrame:
    """Consecutive orders of each customer: one path per customer."""
    from pyspark.sql import Window

    o = load_table(spark, d, "orders").select("o_custkey", "o_orderkey")
    by = (F.col("o_orderkey") * 7919) % 1000003 if shuffled else F.col("o_orderkey")
    w = Window.partitionBy("o_custkey").orderBy(by, "o_orderkey")
    return o.select(F.lag("o_orderkey").over(w).alias("a"), F.col("o_orderkey").alias("b")).where("a is not null")


def event_edges(spark: SparkSession, d: str) -> DataFrame:
    """Each event of a user with the two before it: overlapping triangles per user, as in the worked example."""
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = load_table(spark, d, "events").select("event_id", F.array(F.lag("event_id").over(w), F.lag("event_id", 2).over(w)).alias("before"))
    return e.select(F.explode("before").alias("a"), F.col("event_id").alias("b")).where("a is not null")


def star_edges(spark: SparkSession, d: str, last: bool = False) -> DataFrame:
    """The least (or the greatest) order of each customer with each other one."""
    o = load_table(spark, d, "orders").select("o_custkey", "o_orderkey")
    hub = o.groupBy("o_custkey").agg((F.max if last else F.min)("o_orderkey").alias("a"))
    return o.join(hub, "o_custkey").where("a <> o_orderkey").select("a", F.col("o_orderkey").alias("b"))


def clique_edges(spark: SparkSession, d: str) -> DataFrame:
    """Every two orders of a customer."""
    o = load_table(spark, d, "orders").select("o_custkey", "o_orderkey")
    return o.select("o_custkey", F.col("o_orderkey").alias("a")).join(o.select("o_custkey", F.col("o_orderkey").alias("b")), "o_custkey").where("a < b").select("a", "b")


def bipartite_edges(spark: SparkSession, d: str) -> DataFrame:
    """Orders (even ids) and the parts (odd ids) in their lines."""
    return load_table(spark, d, "lineitem").select((F.col("l_orderkey") * 2).alias("a"), (F.col("l_partkey") * 2 + 1).alias("b")).distinct()
