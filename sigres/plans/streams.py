"""Queries of the streaming surface and of registered functions; the oracles are their batch twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from sigres.functions.posterior import posterior
from sigres.functions.udtf import noisy_or, register
from sigres.operators import candidates as fam
from sigres.operators import resolve
from sigres.operators.resolve import Config
from sigres.plans import duck
from sigres.plans import methods as m
from sigres.plans.scratch import Scratch
from sigres.sources import fixtures as fx
from sigres.sources.tables import load_table
from sigres.streaming import jobs

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f
    return add


def _events(s, d, scratch, where="true"):
    e = load_table(s, d, "events").where(where).select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")
    return jobs.arrivals(s, e, scratch, f"events{abs(hash(where))}")


def _cfg():
    return m._prod_config(None)


@query("st_s01_daily_rerun", m.ORACLES["m30_resolve_part"])
def _(s, d):
    scratch = Scratch(s, "rerun")
    return jobs.daily_rerun(jobs.arrivals(s, fx.prod_pair(s, d), scratch, "records"), _cfg(), scratch)


@query("st_s02_incremental", m.ORACLES["m30_resolve_part"])
@query("m34_incremental", m.ORACLES["m30_resolve_part"])
def _(s, d):
    rec = fx.prod_pair(s, d)
    return jobs.resolve_incremental(rec.where("floor(rid / 2) % 4 <> 0"), rec.where("floor(rid / 2) % 4 = 0"), _cfg())


@query("st_s03_dedup", "SELECT count(*) AS n FROM (SELECT DISTINCT event_id FROM events)")
def _(s, d):
    scratch = Scratch(s, "dedup")
    e = load_table(s, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    twice = e.unionByName(e.where("event_id % 3 = 0"))
    return jobs.run_to_end(jobs.distinct_events(jobs.arrivals(s, twice, scratch, "twice"), "60 days"), scratch, "out").agg(F.count("*").alias("n"))



@query("st_s04_tumbling", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def _(s, d):
    scratch = Scratch(s, "tumbling")
    out = jobs.complete_to_end(jobs.tumbling(_events(s, d, scratch), "1 day", "40 days"), scratch, "out")
    last = out.agg(F.max("_batch")).first()[0]
    return out.where(F.col("_batch") == last).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n")


@query("st_s04_sliding", "SELECT strftime(h, '%Y-%m-%d %H') AS hour, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS h FROM events) GROUP BY 1")
def _(s, d):
    scratch = Scratch(s, "sliding")
    out = jobs.complete_to_end(jobs.sliding(_events(s, d, scratch), "2 hours", "1 hour", "40 days"), scratch, "out")
    last = out.agg(F.max("_batch")).first()[0]
    return out.where(F.col("_batch") == last).select(F.date_format("start", "yyyy-MM-dd HH").alias("hour"), "n")


@query("st_s04_session", """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events),
i AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS i FROM g) SELECT user_id, count(*) AS n FROM i GROUP BY user_id, i""")
def _(s, d):
    scratch = Scratch(s, "session")
    out = jobs.complete_to_end(jobs.sessions(_events(s, d, scratch), "6 hours", "40 days"), scratch, "out")
    last = out.agg(F.max("_batch")).first()[0]
    return out.where(F.col("_batch") == last).select("user_id", "n")


@query("st_s05_late_data")
def _(s, d):
    """Rows that come after the watermark has passed their window are dropped: rows in, and rows counted."""
    scratch = Scratch(s, "late")
    e = load_table(s, d, "events").select(F.when(F.col("event_id") % 50 == 0, F.col("event_id") + 10_000_000).otherwise(F.col("event_id")).alias("event_id"),
                                          F.col("ts").cast("timestamp").alias("ts"), "event_type")
    counted = jobs.run_to_end(jobs.tumbling(jobs.arrivals(s, e, scratch, "late"), "1 hour", "1 hour"), scratch, "out")
    return counted.agg(F.sum("n").alias("counted")).crossJoin(e.agg(F.count("*").alias("rows")))


@query("st_s06_stateful_counts", f"WITH {duck.PRODUCTS}, {duck.postings(duck.runs('name', 2))} SELECT sig, count(*) AS k FROM post GROUP BY sig")
def _(s, d):
    scratch = Scratch(s, "state")
    posts = fam.emit(fx.prod_pair(s, d), [fam.consecutive("name", 2)]).select("rid", "sig")
    out = jobs.complete_to_end(jobs.recurrence_state(jobs.arrivals(s, posts, scratch, "postings")), scratch, "out", "update")
    return out.groupBy("sig").agg(F.max("k").alias("k"))


_INDEX = f"{duck.PRODUCTS}, {duck.postings(duck.runs('name', 2))}, {duck.shared(2.0, 0.1, 0.3)}"


@query("st_s07_stream_static", f"WITH {_INDEX} SELECT p.rid, count(*) AS n FROM post p JOIN kk USING (sig) WHERE p.source = 1 GROUP BY p.rid")
def _(s, d):
    """Arriving records against the persisted dictionary of candidates."""
    from sigres.functions.posterior import k_max
    from sigres.operators import index
    scratch = Scratch(s, "static")
    posts = scratch.save(fam.emit(fx.prod_pair(s, d), [fam.consecutive("name", 2)]), "postings")
    known = scratch.save(index.dictionary(posts, k_max(0.3, 2.0, 0.1)), "dictionary")
    stream = jobs.arrivals(s, posts.where("source = 1").select("rid", "sig"), scratch, "new")
    return jobs.run_to_end(stream.join(known, "sig").select("rid", "sig"), scratch, "out").groupBy("rid").agg(F.count("*").alias("n"))


@query("st_s07_interval_join", "SELECT b.event_id AS buy, v.event_id AS click FROM events b JOIN events v ON b.user_id = v.user_id AND v.ts < b.ts AND v.ts >= b.ts - INTERVAL 6 HOUR WHERE b.event_type = 'purchase' AND v.event_type = 'click'")
def _(s, d):
    scratch = Scratch(s, "interval")
    one = lambda kind: load_table(s, d, "events").where(F.col("event_type") == kind).select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id")
    views, buys = jobs.arrivals(s, one("click"), scratch, "views", 1), jobs.arrivals(s, one("purchase"), scratch, "buys", 1)
    return jobs.run_to_end(jobs.interval_join(views, buys, "6 hours"), scratch, "out")


@query("st_s08_update_mode", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def _(s, d):
    scratch = Scratch(s, "update")
    out = jobs.complete_to_end(_events(s, d, scratch).groupBy("event_type").agg(F.count("*").alias("n")), scratch, "out", "update")
    return out.groupBy("event_type").agg(F.max("n").alias("n"))


@query("st_s08_append_mode", "SELECT event_id, user_id FROM events WHERE event_type = 'error'")
def _(s, d):
    scratch = Scratch(s, "append")
    return jobs.run_to_end(_events(s, d, scratch).where("event_type = 'error'").select("event_id", "user_id"), scratch, "out")


# ---- registered functions ----

@query("udtf_subrecords", f"WITH {m._SUBSETS} SELECT sig, count(*) AS n FROM subs WHERE len(string_split(sig, ' ')) <= 3 GROUP BY sig")
def _(s, d):
    register(s)
    m._small_parts(s, d).select("p_partkey", F.array_join("words", " ").alias("t")).createOrReplaceTempView("small_parts")
    return s.sql("SELECT sig, count(*) AS n FROM small_parts, LATERAL subrecords(t, 3) GROUP BY sig")


def joint(shared, a: float, b: float, scratch: Scratch):
    """(lo, hi, sig, k) -> (lo, hi, prob), with ``noisy_or`` called once for each list of recurrences, not for each pair.

    p depends on k only, so pairs whose candidates recur alike have one probability.  There are few such lists,
    however many pairs: k is at most k_max, and a pair shares at most as many candidates as a record has.
    """
    # neither table's size is known before it is made; both are written, so that a list of many pairs can be split
    found = scratch.save(shared.repartition("lo", "hi").groupBy("lo", "hi").agg(F.array_sort(F.collect_list("k")).alias("ks")), "pairs")
    p = found.select("ks").distinct().select("ks", F.explode("ks").alias("k")).select("ks", posterior(F.col("k"), a, b).alias("p"))
    probs = scratch.save(p.groupBy("ks").agg(noisy_or()("p").alias("prob")), "probabilities")
    return found.hint("merge").join(probs, "ks").select("lo", "hi", "prob")


@query("udaf_noisy_or", f"WITH {m._PROD_LINKS} SELECT lo, hi, round(prob, 6) AS prob FROM links")
def _(s, d):
    shared = resolve.potential_links(fx.prod_pair(s, d), Config([fam.consecutive("name", 2)], rho=0.3, scope="cross"))
    return joint(shared, 2.0, 0.1, Scratch(s, "noisy-or")).where("prob > 0.5").select("lo", "hi", F.round("prob", 6).alias("prob"))
