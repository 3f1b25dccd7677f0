"""The end-to-end resolver and its switches."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sigres.functions.posterior import k_max
from sigres.operators import candidates, index, pairs, verify
from sigres.operators.components import connected_components
from sigres.plans.scratch import Scratch


@dataclass
class Config:
    """Parameters of one run; names follow the model: p = 1 / (1 + a^k b), p > rho, product > tau.

    ``hashed``: candidates travel as two 64-bit hashes, unless elimination needs their words.
    """

    families: list[candidates.Family]
    a: float = 2.0
    b: float = 0.1
    rho: float = 0.5
    tau: float = 0.9
    scope: str = "dedupe"
    eliminate: str = "auto"  # auto, always, never
    containment: str = "gapped"
    rule: Callable[[str, str], Column] | None = None
    rule_cols: tuple[str, ...] = ()
    transitive: bool = True
    hashed: bool = True
    namespace: bool = False


def drops(cfg: Config) -> bool:
    """Whether contained candidates are eliminated: on demand, or if one family's candidate can be part of another's."""
    return cfg.eliminate == "always" or cfg.eliminate == "auto" and candidates.nested(cfg.families)


def postings(records: DataFrame, cfg: Config) -> DataFrame:
    """(rid, source, sig); hashes unless elimination needs the words."""
    rows = candidates.emit(records, cfg.families, cfg.namespace)
    return candidates.hashed(rows) if cfg.hashed and not drops(cfg) else rows


def entries(records: DataFrame, cfg: Config, scratch: Scratch | None = None) -> DataFrame:
    """The inverted index of a configuration; with ``scratch`` the postings are made once and written."""
    rows = postings(records, cfg)
    rows = scratch.save(rows, "postings") if scratch else rows
    return index.build_index(rows, cfg.a, cfg.b, cfg.rho, scratch)


def potential_links(records: DataFrame, cfg: Config, scratch: Scratch | None = None) -> DataFrame:
    """(lo, hi, sig, k) after the rho filter and, if families are nested, elimination."""
    shared = pairs.generate(entries(records, cfg, scratch), cfg.scope)
    return pairs.eliminate(shared, cfg.containment) if drops(cfg) else shared


def _probable(records: DataFrame, cfg: Config, scratch: Scratch | None = None) -> DataFrame:
    return pairs.threshold(pairs.combine(potential_links(records, cfg, scratch), cfg.a, cfg.b), cfg.tau)


def links(records: DataFrame, cfg: Config, scratch: Scratch | None = None) -> DataFrame:
    """(lo, hi, n_sig, ln_doubt, prob) above tau, verified if the configuration has a rule.

    Records and postings are written once, as several steps read them.
    """
    scratch = scratch or Scratch(records.sparkSession, "links")
    saved = scratch.save(records, "records")
    return verify.verify(_probable(saved, cfg, scratch), saved, cfg.rule, list(cfg.rule_cols))


def blocks(records: DataFrame, cfg: Config) -> DataFrame:
    """Candidate pairs only, for another matcher: links without rule and closure."""
    scratch = Scratch(records.sparkSession, "blocks")
    return _probable(scratch.save(records, "records"), cfg, scratch).select("lo", "hi")


def partition(found: DataFrame, nodes: DataFrame, transitive: bool = True) -> DataFrame:
    """Links (lo, hi) and nodes (rid) -> (rid, entity_id); without closure a record takes its smallest partner."""
    found = found.select(F.col("lo").alias("a"), F.col("hi").alias("b"))
    if not transitive:
        best = found.groupBy(F.col("b").alias("rid")).agg(F.min("a").alias("entity_id"))
        return nodes.select("rid").join(best, "rid", "left").select("rid", F.coalesce("entity_id", "rid").alias("entity_id"))
    found = Scratch(nodes.sparkSession, "links").save(found, "links")
    return connected_components(found, nodes.select("rid"))


def resolve(records: DataFrame, cfg: Config) -> DataFrame:
    """records (rid, source, attributes) -> (rid, entity_id); every record once."""
    scratch = Scratch(records.sparkSession, "resolve")
    saved = scratch.save(records, "records")
    found = verify.verify(_probable(saved, cfg, scratch), saved, cfg.rule, list(cfg.rule_cols))
    return partition(found, saved, cfg.transitive)


def with_fallback(records: DataFrame, cfg: Config, longer: list[candidates.Family]) -> DataFrame:
    """Postings of surviving candidates; records without any get the longer families in a second pass."""
    most = k_max(cfg.rho, cfg.a, cfg.b)
    first = candidates.emit(records, cfg.families)
    good = first.join(index.dictionary(first, most, least=1), "sig")
    rest = records.join(good.select("rid").distinct(), "rid", "left_anti")
    second = candidates.emit(rest, longer)
    return good.select("rid", "source", "sig").unionByName(second)


def starred(cfg: Config) -> bool:
    """Whether a star stands for all pairs of a candidate: elimination must never replace a candidate by a less probable one.

    It does not if nothing is eliminated, or if all families are runs of one attribute and containment is
    contiguous: a longer run then recurs at most as often as its parts.
    """
    runs = [f.run for f in cfg.families]
    return not drops(cfg) or cfg.containment == "contiguous" and None not in runs and len({r[0] for r in runs}) == 1


def star_resolve(records: DataFrame, cfg: Config) -> DataFrame:
    """The partition of ``resolve``, linking records to signatures where one is enough.

    Pairs that need several candidates are still combined.  A rule judges pairs, and without closure
    there is no hub, so both are refused; where ``starred`` does not hold all pairs are combined.
    """
    if cfg.rule is not None or not cfg.transitive:
        raise ValueError("star linking needs closure and no rule")
    if not starred(cfg):
        return resolve(records, cfg)
    scratch = Scratch(records.sparkSession, "stars")
    saved = scratch.save(records, "records")
    index_ = scratch.save(entries(saved, cfg, scratch), "entries")
    stars = pairs.star_links(index_, cfg.a, cfg.b, cfg.tau, cfg.scope)
    shared = pairs.generate(index_, cfg.scope)
    shared = pairs.eliminate(shared, cfg.containment) if drops(cfg) else shared
    joint = pairs.threshold(pairs.combine(shared, cfg.a, cfg.b), cfg.tau).select("lo", "hi")
    return partition(stars.unionByName(joint), saved)
