"""Connected components by group-by and equi-join only.

Phase 1 turns the edge set into a forest: of the parents of a node the least one stays, and the
other parents are hung below it.  Phase 2 halves the height of the forest in each round by jumping
to the grandparent.  Each round is a Parquet table in the shared scratch folder, so a lost executor
costs one task; the driver sees one counter per round.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sigres.plans.scratch import Scratch


@dataclass
class Trace:
    """Rounds of both phases and, for each round, (edges, sum of ids)."""

    forest_rounds: int = 0
    flatten_rounds: int = 0
    sizes: list[tuple[str, int, int]] = field(default_factory=list)


def normalise(edges: DataFrame) -> DataFrame:
    """(a, b) in any order, with loops, repeats and nulls -> distinct (parent, child), parent < child."""
    return (edges.select(F.least("a", "b").alias("parent"), F.greatest("a", "b").alias("child"))
            .where("parent < child").distinct())


def least_parents(edges: DataFrame) -> DataFrame:
    """child -> least parent and number of parents; min and count combine before the shuffle."""
    return edges.groupBy("child").agg(F.min("parent").alias("least"), F.count("*").alias("parents"))


def rehang(edges: DataFrame, least: DataFrame) -> DataFrame:
    """One forest round: the edge to the least parent stays, other parents go below that parent."""
    keep = F.col("parent") == F.col("least")
    return (edges.join(least.select("child", "least"), "child")
            .select(F.col("least").alias("parent"),
                    F.when(keep, F.col("child")).otherwise(F.col("parent")).alias("child"))
            .distinct())


def _observe(trace: Trace, phase: str, table: DataFrame) -> None:
    n, total = table.agg(F.count("*"), F.sum("child") + F.sum("parent")).first()
    trace.sizes.append((phase, n, total or 0))


def to_forest(edges: DataFrame, scratch: Scratch, trace: Trace, measure: bool = False) -> DataFrame:
    """Rounds until every node has at most one parent; ``edges`` are normalised."""
    now = scratch.save(edges, "edges")
    while True:
        if measure:
            _observe(trace, "forest", now)
        least = scratch.save(least_parents(now), "least")
        if not least.where("parents > 1").take(1):
            scratch.drop(now)
            return least.select(F.col("least").alias("parent"), "child")
        then = scratch.save(rehang(now, least), "edges")
        scratch.drop(now, least)
        now = then
        trace.forest_rounds += 1


def jump(forest: DataFrame) -> DataFrame:
    """One flattening round: every child moves to its grandparent where there is one."""
    up = forest.select(F.col("child").alias("parent"), F.col("parent").alias("grand"))
    return forest.join(up, "parent", "left").select(
        F.coalesce("grand", "parent").alias("parent"), "child", F.col("grand").isNotNull().alias("moved"))


def flatten(forest: DataFrame, scratch: Scratch, trace: Trace, measure: bool = False) -> DataFrame:
    """Rounds until no node is both a parent and a child."""
    now = forest
    while True:
        then = scratch.save(jump(now), "jump")
        if measure:
            _observe(trace, "flatten", then)
        if not then.where("moved").take(1):
            return then.select("parent", "child")
        trace.flatten_rounds += 1
        now = then.select("parent", "child")


def connected_components(edges: DataFrame, nodes: DataFrame | None = None, trace: Trace | None = None,
                         measure: bool = False) -> DataFrame:
    """edges (a, b) and optional nodes (rid) -> (rid, entity_id), the least id of each component.

    Nodes without an edge are their own component; without ``nodes`` only nodes of edges appear.
    An empty edge set gives only the isolated nodes.
    """
    scratch = Scratch(edges.sparkSession, "components")
    trace = trace if trace is not None else Trace()
    stars = flatten(to_forest(normalise(edges), scratch, trace, measure), scratch, trace, measure)
    if nodes is None:
        found = stars.select(F.col("child").alias("rid"), F.col("parent").alias("entity_id"))
        roots = stars.select("parent").distinct().select(F.col("parent").alias("rid"), F.col("parent").alias("entity_id"))
        return found.unionByName(roots)
    return (nodes.select("rid").join(stars.withColumnRenamed("child", "rid"), "rid", "left")
            .select("rid", F.coalesce("parent", "rid").alias("entity_id")))
