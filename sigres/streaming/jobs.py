"""Streaming: daily reruns, incremental resolution equal to a batch run, and stream operators."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sigres.functions.posterior import k_max
from sigres.operators import pairs, verify
from sigres.operators.resolve import Config, drops, partition, postings, resolve
from sigres.plans.scratch import Scratch, small_side

#: Touched candidates, records or pairs up to which their table is broadcast (about 30 bytes each).
TOUCHED = 300_000


def run_to_end(stream: DataFrame, scratch: Scratch, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there now into Parquet and return the result (append mode)."""
    path = f"{scratch.base}/{name}"
    q = (stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", f"{path}-state")
         .outputMode(mode).trigger(availableNow=True).start())
    q.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(path)


def complete_to_end(stream: DataFrame, scratch: Scratch, name: str, mode: str = "complete") -> DataFrame:
    """Run an aggregating stream to the end; each batch replaces (complete) or amends (update) the result."""
    path = f"{scratch.base}/{name}"

    def put(df: DataFrame, batch: int) -> None:
        df.withColumn("_batch", F.lit(batch)).write.mode("append").parquet(path)
    q = stream.writeStream.foreachBatch(put).option("checkpointLocation", f"{path}-state").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.read.parquet(path)


def arrivals(spark: SparkSession, df: DataFrame, scratch: Scratch, name: str, parts: int = 3) -> DataFrame:
    """A stream over ``df`` written as ``parts`` files, one file a batch, by the first column's order."""
    path = f"{scratch.base}/{name}"
    key = df.columns[0]
    df.repartitionByRange(parts, key).write.parquet(path)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def daily_rerun(stream: DataFrame, cfg: Config, scratch: Scratch) -> DataFrame:
    """Append each batch to the store and resolve all of it: equal to a batch run by construction."""
    store, out = f"{scratch.base}/store", f"{scratch.base}/resolved"

    def step(batch: DataFrame, n: int) -> None:
        batch.write.mode("append").parquet(store)
        everything = batch.sparkSession.read.schema(batch.schema).parquet(store)
        resolve(everything, cfg).write.mode("overwrite").parquet(out)
    q = stream.writeStream.foreachBatch(step).option("checkpointLocation", f"{scratch.base}/rerun").trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.read.parquet(out)


@dataclass
class Store:
    """A resolved set of records as written tables: records, postings, counts (sig, k) of all candidates,
    links (lo, hi) and labels (rid, entity_id)."""

    records: DataFrame
    postings: DataFrame
    counts: DataFrame
    links: DataFrame
    labels: DataFrame


def _links(entries: DataFrame, records: DataFrame, cfg: Config, only: DataFrame | None = None) -> DataFrame:
    """Links (lo, hi) of index entries, of all pairs or of those in ``only``; every switch of the configuration counts."""
    shared = pairs.generate(entries, cfg.scope)
    if only is not None:
        shared = shared.join(only, ["lo", "hi"], "left_semi")
    shared = pairs.eliminate(shared, cfg.containment) if drops(cfg) else shared
    found = pairs.threshold(pairs.combine(shared, cfg.a, cfg.b), cfg.tau)
    return verify.verify(found, records, cfg.rule, list(cfg.rule_cols)).select("lo", "hi")


def build_store(records: DataFrame, cfg: Config) -> Store:
    """Resolve ``records`` and keep what later arrivals need."""
    scratch = Scratch(records.sparkSession, "store")
    saved = scratch.save(records, "records")
    posted = scratch.save(postings(saved, cfg), "postings")
    counts = scratch.save(posted.groupBy("sig").agg(F.count("*").alias("k")), "counts")
    good = counts.where(F.col("k").between(2, k_max(cfg.rho, cfg.a, cfg.b)))
    links = scratch.save(_links(posted.join(good, "sig"), saved, cfg), "links")
    return Store(saved, posted, counts, links, scratch.save(partition(links, saved, cfg.transitive), "labels"))


def extend(store: Store, new: DataFrame, cfg: Config) -> Store:
    """The store with new records: the same links and labels as if all had been resolved at once.

    Only candidates of new records change their k.  Pairs that share such a candidate, before or after, are
    scored again: their links may appear or, as k grows, disappear.  The store's tables are scanned for the
    touched candidates, records and components; nothing else of them is joined, paired or closed again.
    Candidates that were above k_max already identify nothing before and after, so lists stay short.
    """
    most = k_max(cfg.rho, cfg.a, cfg.b)
    scratch = Scratch(new.sparkSession, "extended")
    fresh = scratch.save(new.select(*store.records.columns), "records")
    added = scratch.save(postings(fresh, cfg), "added")
    came = scratch.save(added.groupBy("sig").agg(F.count("*").alias("more")), "came")
    known = store.counts.join(small_side(came, TOUCHED), "sig").select("sig", F.col("k").alias("was"))
    touched = came.join(known, "sig", "left").select("sig", F.coalesce("was", F.lit(0)).alias("was"), (F.coalesce("was", F.lit(0)) + F.col("more")).alias("k"))
    touched = scratch.save(touched, "touched")
    live = small_side(scratch.save(touched.where(F.col("was") <= most), "live"), TOUCHED)
    lists = store.postings.join(live, "sig").select(*store.postings.columns, "k").unionByName(
        added.join(live, "sig").where(F.col("k") <= most).select(*added.columns, "k"))
    changed = scratch.save(pairs.generate(lists, cfg.scope).select("lo", "hi").distinct(), "changed")
    ends = scratch.save(changed.select(F.explode(F.array("lo", "hi")).alias("rid")).distinct(), "ends")
    everyone, posted = store.records.unionByName(fresh), store.postings.unionByName(added)
    mine = scratch.save(posted.join(small_side(ends, TOUCHED), "rid", "left_semi"), "mine")
    asked = small_side(scratch.save(mine.select("sig").distinct(), "asked"), TOUCHED)
    counts = store.counts.join(small_side(came, TOUCHED), "sig", "left_anti").unionByName(touched.select("sig", "k"))
    good = counts.join(asked, "sig", "left_semi").where(F.col("k").between(2, most))
    sides = everyone.join(small_side(ends, TOUCHED), "rid", "left_semi")
    renewed = scratch.save(_links(mine.join(good, "sig"), sides, cfg, changed), "renewed")
    links = scratch.save(store.links.join(small_side(changed, TOUCHED), ["lo", "hi"], "left_anti").unionByName(renewed), "links")
    if not cfg.transitive:
        labels = partition(links, everyone, False)
    else:
        # components with an end of a changed pair are closed again, with the new records; all others stay
        open_ = scratch.save(store.labels.join(small_side(ends, TOUCHED), "rid", "left_semi").select("entity_id").distinct(), "open")
        inside = store.labels.join(small_side(open_, TOUCHED), "entity_id", "left_semi").select("rid")
        nodes = scratch.save(inside.unionByName(fresh.select("rid")), "nodes")
        near = links.join(small_side(nodes.withColumnRenamed("rid", "lo"), TOUCHED), "lo", "left_semi").select("lo", "hi")
        labels = store.labels.join(small_side(nodes, TOUCHED), "rid", "left_anti").select("rid", "entity_id").unionByName(partition(near, nodes))
    return Store(everyone, posted, scratch.save(counts, "counts"), links, scratch.save(labels, "labels"))


def resolve_incremental(old: DataFrame, new: DataFrame, cfg: Config) -> DataFrame:
    """(rid, entity_id) over old and new records, equal to a batch run: the old ones are resolved, then extended."""
    return extend(build_store(old, cfg), new, cfg).labels


def tumbling(events: DataFrame, width: str, late: str) -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n")).select(
        F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str, slide: str, late: str) -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, slide).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str, late: str) -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(
        "user_id", F.col("w.start").alias("start"), "n")


def distinct_events(events: DataFrame, late: str) -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def recurrence_state(postings: DataFrame, scratch_schema: str = "sig string, k long") -> DataFrame:
    """A stream of (sig, rid) -> (sig, k): the count of each candidate kept as state and sent on change."""
    def count(key: tuple, rows: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        k = (state.get[0] if state.exists else 0) + sum(len(r) for r in rows)
        state.update((k,))
        yield pd.DataFrame({"sig": [key[0]], "k": [k]})
    return postings.groupBy("sig").applyInPandasWithState(count, scratch_schema, "k long", "update", "NoTimeout")


def interval_join(views: DataFrame, buys: DataFrame, within: str) -> DataFrame:
    """Each purchase with the clicks of the same user in the interval before it; both sides bounded by watermarks."""
    v = views.withWatermark("ts", "1 hour").select(F.col("user_id").alias("vu"), F.col("ts").alias("vts"), F.col("event_id").alias("click"))
    b = buys.withWatermark("ts", "1 hour").select("user_id", "ts", F.col("event_id").alias("buy"))
    return b.join(v, F.expr(f"user_id = vu and vts < ts and vts >= ts - interval {within}")).select("buy", "click")
