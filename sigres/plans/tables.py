"""The experiments' summary tables: the best of a sweep on each workload, and F by matcher and workload."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sigres.functions.text import jaccard
from sigres.operators import baselines, candidates, index, metrics, pairs, resolve, tuning
from sigres.operators.resolve import Config
from sigres.plans import comparisons as c
from sigres.plans import methods as m
from sigres.plans.scratch import Scratch
from sigres.sources import fixtures as fx

QUERIES: dict = {}
ORACLES: dict[str, str] = {}

#: Points of the sweep, and folds of which each is scored at the point that is best on the others.
POINTS = tuning.grid([1.3, 2.0, 3.0], [0.1, 0.5], [0.1, 0.3, 0.5], [0.3, 0.5, 0.7, 0.9])
FOLDS = 5
#: Similarity of an attribute from which on two records agree on it.
AGREE = 0.8


def _offers(s, d):
    return fx.prod_a(s, d).unionByName(fx.prod_offers(s, d).select("rid", "source", "name"))


def _offer_truth(s, d, rec):
    return fx.prod_offers(s, d).select((F.col("p_partkey") * 2).alias("lo"), F.col("rid").alias("hi"))


_OWN = lambda s, d, rec: fx.own_truth(rec)
#: name -> records, candidate families, attributes that matchers compare, true pairs
WORKLOADS = {
    "bibliography_pages": (fx.bib_pair, c._BIB_FAMILIES, ("title", "authors"), lambda s, d, rec: fx.bib_truth(s, d)),
    "bibliography_light": (fx.bib_light, c._BIB_FAMILIES, ("title", "authors"), _OWN),
    "products": (fx.prod_pair, m.PROD_FAMILIES, ("name",), _OWN),
    "offers": (_offers, m.PROD_FAMILIES, ("name",), _offer_truth),
    "people": (fx.people, m.PERSON_FAMILIES, ("name", "res", "mail", "phone", "birth_state", "age"), _OWN),
}


def _candidates(rec: DataFrame, families: list, scratch: Scratch) -> DataFrame:
    """(lo, hi, sig, k) of two sources up to the largest k of the sweep, after elimination if families are nested.

    Elimination does not depend on the point: what contains a candidate of a pair recurs at most as often.
    """
    cfg = Config(families, scope="cross")
    posts = scratch.save(resolve.postings(rec, cfg), "postings")
    most = scratch.save(index.dictionary(posts, max(p[4] for p in POINTS)), "counts")
    shared = pairs.generate(posts.join(most, "sig"), "cross")
    return scratch.save(pairs.eliminate(shared) if resolve.drops(cfg) else shared, "shared")


def _prepared(s, d, name):
    fixture, families, attrs, truth = WORKLOADS[name]
    scratch = Scratch(s, f"table-{name}")
    rec = scratch.save(fixture(s, d), "records")
    true = scratch.save(truth(s, d, rec).select("lo", "hi"), "truth")
    return rec, true, _candidates(rec, families, scratch), attrs, scratch


def _row(s, tp: int, fp: int, fn: int, **more) -> DataFrame:
    return metrics.with_rates(s.createDataFrame([(tp, fp, fn)], "tp long, fp long, fn long")).withColumns({k: F.lit(v) for k, v in more.items()})


def features(rec: DataFrame, shared: DataFrame, truth: DataFrame, attrs: tuple[str, ...]) -> DataFrame:
    """Pairs that share a candidate: label, and for each attribute its set similarity, containment, likeness as text, and agreement."""
    both = shared.select("lo", "hi").distinct().join(truth.withColumn("t", F.lit(1)), ["lo", "hi"], "left")
    side = lambda p, key: rec.select(F.col("rid").alias(key), *[F.col(a).alias(f"{p}_{a}") for a in attrs])
    both = both.join(side("x", "lo"), "lo").join(side("y", "hi"), "hi")
    cols = {}
    for a in attrs:
        x, y = F.col(f"x_{a}"), F.col(f"y_{a}")
        tx, ty = F.array_join(x, " "), F.array_join(y, " ")
        cols[f"set_{a}"] = jaccard(x, y)
        cols[f"part_{a}"] = F.size(F.array_intersect(x, y)) / F.greatest(F.least(F.size(x), F.size(y)), F.lit(1))
        cols[f"text_{a}"] = 1 - F.levenshtein(tx, ty) / F.greatest(F.length(tx), F.length(ty), F.lit(1))
    out = both.withColumns(cols).withColumns({f"agree_{a}": (F.col(f"set_{a}") >= AGREE).cast("int") for a in attrs})
    return out.select("lo", "hi", F.floor(F.col("lo") / 2).alias("key"), F.coalesce("t", F.lit(0)).alias("label"), *cols, *[f"agree_{a}" for a in attrs])


for _name in WORKLOADS:
    def _best(s, d, name=_name):
        """The sweep on one workload: the point with the best F on all pairs, and the F of points chosen on other folds."""
        _, true, shared, _, _ = _prepared(s, d, name)
        held = tuning.tune_held_out(shared, true, POINTS, FOLDS)
        return tuning.best(tuning.tune(shared, true, POINTS)).withColumn("held_out_f", F.round(F.lit(tuning.f_measure(*held)), 6))
    QUERIES[f"t1_{_name}"] = _best


def matchers(s, d, name: str) -> DataFrame:
    """(workload, matcher, tp, fp, fn, rates): every matcher judges the same candidate pairs; learned ones, thresholds
    and the sweep's point come from the other folds."""
    rec, true, shared, attrs, scratch = _prepared(s, d, name)
    feat = scratch.save(features(rec, shared, true, attrs), "features")
    sims = [f"{kind}_{a}" for a in attrs for kind in ("set", "part", "text")]
    found = {
        "weighted similarity": baselines.tuned_similarity_link(feat, [f"set_{a}" for a in attrs], FOLDS),
        "log-likelihood": baselines.llr_link(feat, [f"agree_{a}" for a in attrs]),
        "svm": baselines.supervised_link(feat, sims, "svm", FOLDS),
        "boosted trees": baselines.supervised_link(feat, sims, "tree", FOLDS),
    }
    out = _row(s, *tuning.tune_held_out(shared, true, POINTS, FOLDS), workload=name, matcher="signatures")
    for matcher, links in found.items():
        out = out.unionByName(metrics.pair_quality(links, true).withColumns({"workload": F.lit(name), "matcher": F.lit(matcher)}))
    return out


for _name in ("bibliography_pages", "bibliography_light", "products", "offers"):
    QUERIES[f"t2_{_name}"] = lambda s, d, name=_name: matchers(s, d, name)
