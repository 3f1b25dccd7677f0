"""Queries of the relational operators, scalar functions, sources and sinks around the methods."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from sigres.plans.scratch import Scratch
from sigres.sources.tables import load, load_table, save

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f
    return add


def _t(name):
    return lambda s, d: load_table(s, d, name)


lineitem, orders, customer, part, events, nation, region, supplier = map(_t, "lineitem orders customer part events nation region supplier".split())


def sql(name: str, text: str, oracle: str | None = None):
    """A query given as Spark SQL over temporary views; the oracle is the same text unless given."""
    def run(s, d):
        import re
        for t in set(re.findall(r"\b(lineitem|orders|customer|part|events|nation|region|supplier|documents|labels)\b", text)):
            load_table(s, d, t).createOrReplaceTempView(t)
        return s.sql(text)
    query(name, oracle or text)(run)


# ---- projection, filters, joins ----

sql("rel_filter", "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_quantity BETWEEN 5 AND 7 AND l_returnflag IN ('A', 'R') AND l_shipdate >= TIMESTAMP '1996-01-01'")
sql("rel_like", "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%ring' AND p_brand <> 'Brand#2'")
sql("rel_null_safe", "SELECT count(*) AS n FROM labels a JOIN labels b ON a.doc_id = b.doc_id AND a.toxic IS NOT DISTINCT FROM b.toxic")


@query("rel_hash_join", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def _(s, d):
    return customer(s, d).hint("shuffle_hash").join(nation(s, d), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@query("rel_merge_join", "SELECT o_orderstatus, count(*) AS n, CAST(sum(l_linenumber) AS BIGINT) AS lines FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus")
def _(s, d):
    return lineitem(s, d).hint("merge").join(orders(s, d), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(
        F.count("*").alias("n"), F.sum("l_linenumber").alias("lines"))


@query("rel_broadcast_join", "SELECT r_name, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def _(s, d):
    # nation and region have 25 and 5 rows at every scale
    return supplier(s, d).join(F.broadcast(nation(s, d)), F.col("s_nationkey") == F.col("n_nationkey")).join(
        F.broadcast(region(s, d)), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n"))


@query("rel_theta_join", "SELECT a.n_nationkey AS x, b.n_nationkey AS y FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey AND a.n_name > b.n_name")
def _(s, d):
    a, b = nation(s, d).alias("a"), F.broadcast(nation(s, d)).alias("b")
    return a.join(b, (F.col("a.n_regionkey") < F.col("b.n_regionkey")) & (F.col("a.n_name") > F.col("b.n_name"))).select(
        F.col("a.n_nationkey").alias("x"), F.col("b.n_nationkey").alias("y"))


sql("rel_semi", "SELECT c_custkey FROM customer LEFT SEMI JOIN orders ON o_custkey = c_custkey AND o_orderstatus = 'P'",
    "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'P')")
sql("rel_anti", "SELECT c_custkey FROM customer LEFT ANTI JOIN orders ON o_custkey = c_custkey AND o_orderstatus = 'P'",
    "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'P')")
sql("rel_left_outer", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey AND o_totalprice > 300000 GROUP BY c_custkey")
sql("rel_full_outer", "SELECT coalesce(c_nationkey, s_nationkey) AS k, count(c_custkey) AS c, count(s_suppkey) AS n FROM (SELECT * FROM customer WHERE c_custkey % 7 = 0) x FULL OUTER JOIN (SELECT * FROM supplier WHERE s_suppkey % 3 = 0) y ON c_custkey = s_suppkey GROUP BY 1")
sql("rel_self_join", "SELECT a.p_partkey AS x, b.p_partkey AS y FROM part a JOIN part b ON a.p_name = b.p_name AND a.p_brand = b.p_brand AND a.p_type = b.p_type AND a.p_partkey < b.p_partkey")


@query("rel_range_join", "SELECT a.p_partkey AS x, b.p_partkey AS y FROM part a JOIN part b ON a.p_name = b.p_name AND a.p_partkey < b.p_partkey AND abs(a.p_size - b.p_size) <= 1 AND abs(a.p_retailprice - b.p_retailprice) <= 5")
def _(s, d):
    # prices within 5 of each other lie in the same bucket of 5 or in the next: an equi-join on buckets
    p = part(s, d).select("p_partkey", "p_name", "p_size", "p_retailprice", F.floor(F.col("p_retailprice") / 5).alias("g"))
    b = p.select(*[F.col(c).alias(f"b_{c}") for c in p.columns]).select("*", F.explode(F.array(F.col("b_g") - 1, F.col("b_g"), F.col("b_g") + 1)).alias("h"))
    return p.join(b, (F.col("g") == F.col("h")) & (F.col("p_name") == F.col("b_p_name"))).where(
        "p_partkey < b_p_partkey and abs(p_size - b_p_size) <= 1 and abs(p_retailprice - b_p_retailprice) <= 5").select(
        F.col("p_partkey").alias("x"), F.col("b_p_partkey").alias("y"))


@query("rel_asof_join", """SELECT p.event_id, max_by(c.event_id, (c.ts, c.event_id)) AS last_click FROM events p LEFT JOIN events c
ON c.user_id = p.user_id AND c.event_type = 'click' AND c.ts < p.ts WHERE p.event_type = 'purchase' GROUP BY p.event_id""")
def _(s, d):
    """The latest click of the user before each purchase: one window per user, no range join."""
    e = events(s, d).where(F.col("event_type").isin("purchase", "click"))
    w = Window.partitionBy("user_id").orderBy("ts", F.col("event_type").desc(), "event_id").rowsBetween(Window.unboundedPreceding, -1)
    click = F.when(F.col("event_type") == "click", F.col("event_id"))
    return e.withColumn("last_click", F.last(click, ignorenulls=True).over(w)).where("event_type = 'purchase'").select("event_id", "last_click")


# ---- aggregates ----

sql("rel_agg", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem GROUP BY l_returnflag, l_linestatus")
sql("rel_agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, count(*) AS n FROM events GROUP BY event_type")
sql("rel_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 15")
sql("rel_filter_agg", "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS f, count(*) AS n FROM orders GROUP BY o_orderpriority")
sql("rel_grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang, source), (lang), ())")
sql("rel_rollup", "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)")
sql("rel_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")


@query("rel_approx")
def _(s, d):
    """Sketches for planning: distinct counts, quantiles and heavy hitters, each in one pass."""
    return lineitem(s, d).agg(F.approx_count_distinct("l_orderkey", 0.02).alias("orders"), F.percentile_approx("l_quantity", 0.5, 1000).alias("median"),
                              F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("parts"))


@query("rel_percentile_bound", "SELECT true AS within")
def _(s, d):
    n = lineitem(s, d).agg(F.approx_count_distinct("l_orderkey", 0.02).alias("a"), F.count_distinct("l_orderkey").alias("b"))
    return n.select((F.abs(F.col("a") - F.col("b")) <= 0.1 * F.col("b")).alias("within"))


# ---- windows, order, sets ----

sql("rel_window_rank", "SELECT o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderstatus) AS k, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderstatus) AS dk FROM orders",
    "SELECT o_orderkey, CAST(row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS INTEGER) AS r, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY o_orderstatus) AS INTEGER) AS k, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderstatus) AS INTEGER) AS dk FROM orders")
sql("rel_window_shift", "SELECT o_orderkey, lag(o_orderkey) OVER w AS p, lead(o_orderkey) OVER w AS n, first_value(o_orderkey) OVER w AS f FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
sql("rel_window_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS c, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 4) AS s FROM events")
sql("rel_window_ntile", "SELECT c_custkey, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS q FROM customer",
    "SELECT c_custkey, CAST(ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS INTEGER) AS q FROM customer")
sql("rel_top_k", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
sql("rel_top_per_group", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) x WHERE r <= 2")
sql("rel_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
sql("rel_intersect_all", "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")
sql("rel_except_all", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
sql("rel_pivot", "SELECT * FROM (SELECT event_type, user_id % 5 AS g FROM events) PIVOT (count(*) FOR event_type IN ('click' AS click, 'error' AS error, 'purchase' AS purchase))",
    "SELECT user_id % 5 AS g, nullif(count(*) FILTER (event_type = 'click'), 0) AS click, nullif(count(*) FILTER (event_type = 'error'), 0) AS error, nullif(count(*) FILTER (event_type = 'purchase'), 0) AS purchase FROM events GROUP BY 1")


@query("rel_unpivot", "SELECT p_partkey, 'size' AS what, CAST(p_size AS BIGINT) AS v FROM part UNION ALL SELECT p_partkey, 'cents', CAST(round(p_retailprice * 100) AS BIGINT) FROM part")
def _(s, d):
    p = part(s, d).select("p_partkey", F.col("p_size").cast("long").alias("size"), F.round(F.col("p_retailprice") * 100).cast("long").alias("cents"))
    return p.unpivot("p_partkey", ["size", "cents"], "what", "v")


@query("rel_sample_by_key", "SELECT c_custkey FROM customer WHERE c_custkey % 10 < 3")
def _(s, d):
    return customer(s, d).where("c_custkey % 10 < 3").select("c_custkey")


sql("rel_recursive_cte", "WITH RECURSIVE c AS (SELECT CAST(year(o_orderdate) AS BIGINT) AS g, count(*) AS k FROM orders GROUP BY 1), t(g, n, x, k) AS (SELECT g, 1, CAST(1 AS BIGINT), k FROM c UNION ALL SELECT g, n + 1, x * 2, k FROM t WHERE x * 2 <= k) SELECT g, n, x FROM t")


@query("rel_sql_parameters", "SELECT count(*) AS n FROM orders WHERE o_totalprice > 250000 AND o_orderstatus = 'F'")
def _(s, d):
    return s.sql("SELECT count(*) AS n FROM {t} WHERE o_totalprice > :least AND o_orderstatus = :status", args={"least": 250000, "status": "F"}, t=orders(s, d))


@query("rel_sql_pipe", "SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_totalprice > 100000 GROUP BY o_orderstatus")
def _(s, d):
    orders(s, d).createOrReplaceTempView("orders")
    return s.sql("FROM orders |> WHERE o_totalprice > 100000 |> AGGREGATE count(*) AS n GROUP BY o_orderstatus")


# ---- sources and sinks ----

def _round_trip(fmt: str, schema: str, **options):
    def run(s, d):
        path = Scratch(s, f"io-{fmt}").base
        save(nation(s, d).select("n_nationkey", "n_name", "n_regionkey"), path, fmt, **options)
        return load(s, path, fmt, schema, **options)
    return run


for _fmt in ("csv", "json", "orc", "parquet"):
    query(f"io_{_fmt}", "SELECT n_nationkey, n_name, n_regionkey FROM nation")(_round_trip(_fmt, "n_nationkey int, n_name string, n_regionkey int"))


@query("io_text", "SELECT n_name AS value FROM nation")
def _(s, d):
    path = Scratch(s, "io-text").base
    save(nation(s, d).select("n_name"), path, "text")
    return load(s, path, "text", "value string")


@query("io_partitioned", "SELECT n_nationkey, n_regionkey FROM nation WHERE n_regionkey = 2")
def _(s, d):
    path = Scratch(s, "io-partitioned").base
    save(nation(s, d), path, partition_by=["n_regionkey"])
    return load(s, path, "parquet", "n_nationkey int, n_name string, n_regionkey int").where("n_regionkey = 2").select("n_nationkey", "n_regionkey")


# ---- functions ----

def fn(name: str, spark: str, duck: str | None = None, table: str = "part", key: str = "p_partkey"):
    """One scalar expression per row of a table."""
    query(f"fn_{name}", f"SELECT {key}, {duck or spark} AS v FROM {table}")(lambda s, d: load_table(s, d, table).selectExpr(key, f"{spark} AS v"))


fn("lower_upper", "concat(lower(p_brand), upper(p_name))")
fn("trim", "trim(concat('  ', p_name, ' '))")
fn("regexp_replace", "regexp_replace(p_name, '[aeiou]', '*')", "regexp_replace(p_name, '[aeiou]', '*', 'g')")
fn("regexp_extract", "regexp_extract(p_brand, '([0-9]+)', 1)")
fn("split", "split(p_name, ' ')[1]", "string_split(p_name, ' ')[2]")
fn("substring", "substring(p_name, 2, 4)")
fn("lpad", "lpad(cast(p_size as string), 5, '0')", "lpad(CAST(p_size AS VARCHAR), 5, '0')")
fn("concat_ws", "concat_ws('-', p_name, p_brand)")
fn("length", "cast(length(p_name) as bigint)")
fn("reverse", "reverse(p_name)")
fn("translate", "translate(p_name, 'abc', 'xyz')")
fn("levenshtein", "cast(levenshtein(p_name, p_type) as bigint)")
fn("sha2", "sha2(p_name, 256)", "sha256(p_name)")
fn("startswith", "startswith(p_name, 'red')", "starts_with(p_name, 'red')")
fn("contains", "contains(p_name, 'in')")
fn("repeat", "repeat(p_type, 2)")
fn("pmod", "pmod(p_partkey - 50, 7)", "((p_partkey - 50) % 7 + 7) % 7")
fn("math", "round(exp(-p_size / 10.0) + ln(p_size + 1) + log2(p_size + 1) + pow(p_size, 0.5), 6)")
fn("log1p", "round(log1p(p_size), 6)", "round(ln(1 + p_size), 6)")
fn("floor_ceil", "cast(floor(p_retailprice) + ceil(p_retailprice) as bigint)")
fn("least_greatest", "least(p_size, 10) + greatest(p_size, 20)")
fn("case", "case when p_size < 10 then 'small' when p_size < 30 then 'mid' else 'big' end")
fn("coalesce_nullif", "coalesce(nullif(p_type, 'ECONOMY'), 'none')")
fn("try_cast", "try_cast(substring(p_brand, 7, 2) as int)", "TRY_CAST(substring(p_brand, 7, 2) AS INTEGER)")
fn("sequence", "cast(size(sequence(1, p_size + 1)) as bigint)", "len(generate_series(1, p_size + 1))")
fn("transform", "array_join(transform(split(p_name, ' '), x -> upper(x)), ' ')", "array_to_string(list_transform(string_split(p_name, ' '), lambda x: upper(x)), ' ')")
fn("filter_exists", "exists(split(p_name, ' '), x -> x = 'red')", "list_contains(string_split(p_name, ' '), 'red')")
fn("aggregate", "aggregate(split(p_name, ' '), 0L, (a, x) -> a + length(x))", "list_sum(list_transform(string_split(p_name, ' '), lambda x: length(x)))::BIGINT")
fn("array_sort", "array_join(array_sort(split(p_name, ' ')), ' ')", "array_to_string(list_sort(string_split(p_name, ' ')), ' ')")
fn("array_sets", "cast(size(array_intersect(split(p_name, ' '), array('red', 'ring'))) as bigint)", "len(list_intersect(string_split(p_name, ' '), ['red', 'ring']))")
fn("array_position", "array_position(split(p_name, ' '), 'ring')", "coalesce(list_position(string_split(p_name, ' '), 'ring'), 0)::BIGINT")
fn("array_repeat", "array_join(array_repeat(p_type, 3), '/')", "array_to_string([p_type, p_type, p_type], '/')")
fn("map", "map_from_arrays(array('a', 'b'), array(p_size, p_size + 1))['b']", "p_size + 1")
fn("struct", "named_struct('a', p_size, 'b', p_name).b", "p_name")
fn("json", "cast(get_json_object(props, '$.k') as bigint)", "CAST(json_extract_string(props, '$.k') AS BIGINT)", "events", "event_id")
fn("from_json", "from_json(props, 'k bigint').k", "CAST(json_extract_string(props, '$.k') AS BIGINT)", "events", "event_id")
fn("date_trunc", "date_format(date_trunc('MONTH', ts), 'yyyy-MM-dd')", "strftime(date_trunc('month', ts), '%Y-%m-%d')", "events", "event_id")
fn("year_month", "year(ts) * 100 + month(ts)", "CAST(year(ts) * 100 + month(ts) AS INTEGER)", "events", "event_id")
fn("datediff", "cast(datediff(ts, date'2024-01-01') as bigint)", "date_diff('day', DATE '2024-01-01', CAST(ts AS DATE))", "events", "event_id")
fn("parse_url", "parse_url(url, 'HOST')", "regexp_extract(url, '^https?://([^/?#]+)', 1)", "pages", "page_id")


@query("fn_soundex")
def _(s, d):
    return customer(s, d).select("c_custkey", F.soundex("c_mktsegment").alias("v"), F.xxhash64("c_name").alias("h"))
