"""Worked examples, invariants and edge rows of the linkage methods."""

import math
import random

import pandas as pd
import pytest
from pyspark.sql import functions as F

from sigres.functions import posterior as law
from sigres.functions.text import is_run, is_subrecord, words
from sigres.operators import baselines, candidates, index, pairs, resolve, verify, world
from sigres.operators.components import Trace, connected_components
from sigres.operators.resolve import Config
from sigres.plans import comparisons
from sigres.sources import fixtures as fx
from sigres.streaming import jobs


def one(spark, expr):
    return spark.range(1).select(expr.alias("v")).first().v


def arr(*xs):
    return F.array(*[F.lit(x) for x in xs]) if xs else F.array().cast("array<string>")


def test_street_world(spark):
    owned = world.enumerate_world(fx.street_world(spark)).cache()
    assert owned.select("sig").distinct().count() == 13
    mine = {(r.sig, r.entity) for r in world.true_signatures(owned).collect()}
    assert len(mine) == 8 and {e for _, e in mine} == {1, 3}
    sigs = world.true_signatures(owned)
    assert world.upward_violations(owned, sigs).count() == 0
    assert world.common_violations(owned, sigs).count() == 0


def test_toy_components(spark):
    t = Trace()
    got = {r.rid: r.entity_id for r in connected_components(fx.toy_edges(spark), trace=t, measure=True).collect()}
    assert got == dict.fromkeys(range(1, 6), 1)
    assert (t.forest_rounds, t.flatten_rounds) == (1, 1)


def test_components_random_graphs(spark):
    random.seed(4)
    edges = [(random.randrange(120), random.randrange(120)) for _ in range(90)] + [(7, 7), (3, 3)]
    want = baselines.components_local(edges)
    df = spark.createDataFrame(edges, "a long, b long")
    nodes = spark.range(130).select(F.col("id").alias("rid"))
    t = Trace()
    got = {r.rid: r.entity_id for r in connected_components(df, nodes, t, measure=True).collect()}
    assert got == {i: want.get(i, i) for i in range(130)}
    falls = [x for p, _, x in t.sizes if p == "forest"]
    assert falls == sorted(falls, reverse=True)


def test_components_without_edges(spark):
    df = spark.createDataFrame([], "a long, b long")
    assert connected_components(df).count() == 0
    assert connected_components(df, spark.range(3).select(F.col("id").alias("rid"))).count() == 3


def test_path_rounds_are_logarithmic(spark):
    t = Trace()
    df = spark.range(100).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    connected_components(df, trace=t).count()
    assert t.forest_rounds == 0 and t.flatten_rounds == 7


def test_posterior_values(spark):
    got = [one(spark, law.posterior(F.lit(k), 2.0, 0.1)) for k in (1, 2, 3, 4)]
    assert got == pytest.approx([0.833333, 0.714286, 0.555556, 0.384615], abs=1e-6)
    assert law.k_max(0.5, 2.0, 0.1) == 3
    for lam, mu, c in ((0.4, 3.0, 0.8), (0.1, 7.5, 0.99), (1.2, 1.9, 0.3)):
        a, b = law.two_parameters(lam, mu, c)
        for k in (1, 2, 5, 30):
            assert one(spark, law.posterior(F.lit(k), a, b)) == pytest.approx(one(spark, law.posterior_poisson(F.lit(k), lam, mu, c)), rel=1e-9)


def test_posterior_does_not_overflow(spark):
    assert one(spark, law.posterior(F.lit(5000), 3.0, 0.5)) == 0.0
    assert one(spark, law.ln_doubt(F.lit(5000), 3.0, 0.5)) == pytest.approx(0.0)


@pytest.mark.parametrize("a,b", [(1.0, 0.5), (0.5, 0.5), (2.0, 0.0), (2.0, -1.0)])
def test_parameters_are_checked(a, b):
    with pytest.raises(ValueError):
        law.k_max(0.5, a, b)


def test_k_max_is_exact():
    for a in (1.1, 1.7, 2.0, 4.0):
        for b in (0.01, 0.1, 0.9):
            for rho in (0.05, 0.3, 0.5, 0.8):
                brute = max([k for k in range(400) if 1 / (1 + a**k * b) > rho], default=0)
                assert law.k_max(rho, a, b) == brute


def test_em_finds_two_rates():
    h = {k: round(9000 * 0.3**k * math.exp(-0.3) / math.factorial(k) / (1 - math.exp(-0.3)) + 1000 * 6.0**k * math.exp(-6) / math.factorial(k) / (1 - math.exp(-6))) for k in range(1, 16)}
    lam, mu, c = law.fit_em({k: n for k, n in h.items() if n})
    assert lam == pytest.approx(0.3, abs=0.05) and mu == pytest.approx(6.0, abs=0.3) and c == pytest.approx(0.9, abs=0.03)


def test_subrecords(spark):
    assert one(spark, is_subrecord(arr("a", "c"), arr("a", "b", "c")))
    assert not one(spark, is_subrecord(arr("c", "a"), arr("a", "b", "c")))
    assert one(spark, is_subrecord(arr(), arr("a")))
    assert not one(spark, is_run(arr("a", "c"), arr("a", "b", "c")))


def test_words_of_odd_texts(spark):
    assert one(spark, words(F.lit(None).cast("string"))) == []
    assert one(spark, words(F.lit("  Ärger, über\tALLES!  "))) == ["ärger", "über", "alles"]
    assert one(spark, words(F.lit("ab"), "qgram")) == []


def records(spark, rows):
    return spark.createDataFrame([(i, 0, w) for i, w in rows], "rid long, source int, name array<string>")


def test_families_on_short_records(spark):
    df = records(spark, [(0, []), (1, ["a"]), (2, ["b", "a", "b"])])
    got = lambda f: {(r.rid, r.sig) for r in candidates.emit(df, [f]).collect()}
    assert got(candidates.consecutive("name", 2)) == {(2, "b a"), (2, "a b")}
    assert got(candidates.word_pairs("name")) == {(2, "a b"), (2, "b b")}
    assert got(candidates.whole("name")) == {(1, "a"), (2, "b a b")}
    assert got(candidates.last_digits("name")) == set()
    assert got(candidates.compose(candidates.whole("name"), candidates.consecutive("name", 1))) == {(1, "a | a"), (2, "b a b | b"), (2, "b a b | a")}


def test_elimination_is_strict_and_idempotent(spark):
    rows = [(1, 2, s, 2) for s in ("a", "b", "a b", "x y z", "x z", "q")]
    df = spark.createDataFrame(rows, "lo long, hi long, sig string, k long")
    gapped, runs = pairs.eliminate(df, "gapped"), pairs.eliminate(df, "contiguous")
    assert {r.sig for r in gapped.collect()} == {"a b", "x y z", "q"}
    assert {r.sig for r in runs.collect()} == {"a b", "x y z", "x z", "q"}
    assert pairs.eliminate(gapped).count() == gapped.count()


def test_cap_on_k(spark):
    df = records(spark, [(i, ["hot", f"w{i // 2}"]) for i in range(8)])
    kept = index.build_index(candidates.emit(df, [candidates.consecutive("name", 1)]), 2.0, 0.1, 0.5)
    assert {r.sig for r in kept.collect()} == {"w0", "w1", "w2", "w3"}


def test_resolution_ignores_order_and_duplicates(spark):
    rows = [(i, [f"n{i // 3}", f"m{i // 3}", f"x{i}"]) for i in range(30)]
    cfg = Config([candidates.consecutive("name", 2)], tau=0.5)
    want = sorted(tuple(r) for r in resolve.resolve(records(spark, rows), cfg).collect())
    random.seed(1)
    random.shuffle(rows)
    assert want == sorted(tuple(r) for r in resolve.resolve(records(spark, rows).repartition(7), cfg).collect())
    assert {e for _, e in want} == {3 * i for i in range(10)}
    assert sorted(tuple(r) for r in resolve.star_resolve(records(spark, rows), cfg).collect()) == want


def _two_sources(seed, n=36):
    rng = random.Random(seed)
    rows = []
    for i in range(n):
        e = rng.randrange(n // 3)
        rows.append((i, rng.randrange(2), [f"n{e}", f"m{e % 5}", f"x{rng.randrange(4)}"][:rng.randint(1, 3)], [f"p{e % 7}"]))
    return rows


CONFIGS = [
    dict(families=[candidates.consecutive("name", 2)], tau=0.5, scope="cross"),
    dict(families=[candidates.consecutive("name", n) for n in (1, 2)], tau=0.4, rho=0.3, containment="contiguous"),
    dict(families=[candidates.consecutive("name", n) for n in (1, 2, 3)], tau=0.6, rho=0.2, scope="cross"),
    dict(families=[candidates.whole("name"), candidates.whole("phone")], a=1.3, b=0.2, rho=0.2, tau=0.3, namespace=True, hashed=False),
    dict(families=[candidates.consecutive("name", 2)], tau=0.5, rule=verify.by_jaccard("name", 0.6), rule_cols=("name",)),
    dict(families=[candidates.consecutive("name", 1)], tau=0.5, rho=0.3, transitive=False),
]


@pytest.mark.parametrize("number", range(len(CONFIGS)))
def test_stars_and_increments_equal_the_batch(spark, number):
    cfg = Config(**CONFIGS[number])
    rows = _two_sources(number)
    df = spark.createDataFrame(rows, "rid long, source int, name array<string>, phone array<string>")
    want = sorted(tuple(r) for r in resolve.resolve(df, cfg).collect())
    assert len({e for _, e in want}) < len(want)
    cut = F.col("rid") % 3 > 0
    got = jobs.resolve_incremental(df.where(cut), df.where(~cut), cfg)
    assert sorted(tuple(r) for r in got.collect()) == want
    if cfg.rule is not None or not cfg.transitive:
        with pytest.raises(ValueError):
            resolve.star_resolve(df, cfg)
    else:
        assert sorted(tuple(r) for r in resolve.star_resolve(df, cfg).collect()) == want


def test_star_keeps_records_of_one_source_apart(spark):
    df = spark.createDataFrame([(0, 0, ["a", "b"]), (2, 0, ["a", "b"]), (1, 1, ["c", "d"])], "rid long, source int, name array<string>")
    cfg = Config([candidates.consecutive("name", 2)], tau=0.3, scope="cross")
    assert {r.rid: r.entity_id for r in resolve.star_resolve(df, cfg).collect()} == {0: 0, 1: 1, 2: 2}


def test_index_with_hot_candidates(spark, monkeypatch):
    from sigres.plans.scratch import Scratch
    df = records(spark, [(i, ["hot", f"w{i // 2}"]) for i in range(40)])
    posts = candidates.emit(df, [candidates.consecutive("name", 1)])
    want = sorted(tuple(r) for r in index.build_index(posts, 2.0, 0.1, 0.5).select("sig", "rid", "k").collect())
    for few, hot in ((10**6, 10), (1, 10), (1, 10**6)):
        monkeypatch.setattr(index, "BROADCAST_SIGNATURES", few)
        monkeypatch.setattr(index, "HOT", hot)
        got = index.build_index(posts, 2.0, 0.1, 0.5, Scratch(spark, "t"))
        assert sorted(tuple(r) for r in got.select("sig", "rid", "k").collect()) == want


def test_jaccard_links_match_brute_force(spark):
    rng = random.Random(2)
    rows = [(i, [f"w{rng.randrange(14)}" for _ in range(rng.randint(0, 9))]) for i in range(90)]
    df = records(spark, rows)
    for least in (0.5, 0.8, 1.0):
        got = sorted((r.lo, r.hi) for r in baselines.jaccard_link(df, F.col("name"), least).collect())
        sets = {i: set(w) for i, w in rows if w}
        want = [(i, j) for i in sets for j in sets if i < j and len(sets[i] & sets[j]) >= least * len(sets[i] | sets[j])]
        assert got == sorted(want)


def test_ln_factorial(spark):
    for k in (0, 1, 2, 15, 16, 17, 60, 1000, 10**7):
        assert one(spark, law.ln_factorial(F.lit(k))) == pytest.approx(math.lgamma(k + 1), rel=1e-12, abs=1e-12)


def test_jaro_values():
    assert verify.jaro("martha", "marhta") == pytest.approx(0.944444, abs=1e-6)
    assert verify.jaro_winkler("dixon", "dicksonx") == pytest.approx(0.813333, abs=1e-6)
    assert verify.jaro("", "a") == 0.0 and verify.jaro("", "") == 1.0


def test_exhaustive_comparison_is_refused(spark, monkeypatch):
    monkeypatch.setattr(baselines, "ALL_PAIRS_ROWS", 2)
    with pytest.raises(ValueError):
        baselines.all_pairs(records(spark, [(i, ["a"]) for i in range(3)]), verify.by_levenshtein("name", 1), ["name"])


def test_scratch_needs_a_shared_folder_on_a_cluster():
    from types import SimpleNamespace

    from sigres.plans import scratch
    for master in ("yarn", "spark://a:7077", "local-cluster[2,1,1024]"):
        fake = SimpleNamespace(conf=SimpleNamespace(get=lambda k, d: None), sparkContext=SimpleNamespace(master=master, applicationId="x"))
        with pytest.raises(RuntimeError):
            scratch.shared_root(fake)


def test_queries_without_the_corpus_subpackage(tmp_path):
    """With the corpus folders gone the entry module still imports and has the library's queries."""
    import os
    import shutil
    import subprocess
    import sys
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(root, tmp_path / "r", ignore=shutil.ignore_patterns(".git", "llm", "corpus_pipeline.py", "__pycache__"))
    said = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()), any(k.startswith('op') for k in e.queries()))"],
                          cwd=tmp_path / "r", capture_output=True, text=True, env={k: v for k, v in os.environ.items() if k != "PYTHONPATH"})
    n, corpus = said.stdout.split()[-2:]
    assert int(n) > 200 and corpus == "False"


def test_held_out_tuning(spark):
    from sigres.operators import tuning
    rows = [(2 * i, 2 * i + 1, f"s{j}", 2) for i in range(40) for j in range(3)] + [(2 * i, 2 * i + 3, "x", 3) for i in range(20)]
    shared = spark.createDataFrame(rows, "lo long, hi long, sig string, k long")
    truth = spark.createDataFrame([(2 * i, 2 * i + 1) for i in range(45)], "lo long, hi long")
    points = tuning.grid([2.0], [0.1], [0.1, 0.5], [0.3, 0.9, 0.9999])
    assert tuning.tune_held_out(shared, truth, points) == (40, 0, 5)


def test_entry_without_corpus_operators(spark, small):
    import __spark_entry__
    assert __spark_entry__.entry(spark).count() > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_local_components_of_many_edges(spark, monkeypatch):
    # a path of 200,100 edges is one component
    path = spark.range(200_100).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    monkeypatch.setattr(comparisons.fx, "bipartite_edges", lambda s, d: path)
    got = comparisons.QUERIES["b13_local"](spark, "").groupBy("entity_id").count().collect()
    assert [(r.entity_id, r["count"]) for r in got] == [(0, 200_101)]


def joins_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", ["a02_best_f", "m16_tune", "m21_skip", "udaf_noisy_or", "a08_link_economy", "m18_index", "m19_pairs_cross", "m20_eliminate_contiguous", "m20_eliminate_gapped", "m31_scope_both", "m31_scope_cross"])
def test_postings_are_not_broadcast(spark, small, name):
    """Postings look as small as the file they are exploded from; their size must not depend on that guess."""
    from sigres.plans import catalog
    plan = joins_of(catalog.queries()[name](spark, small))
    assert "SortMergeJoin" in plan and "BroadcastHashJoin" not in plan


def _edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a):
        row, last = [i + 1], row
        for j, y in enumerate(b):
            row.append(min(last[j + 1] + 1, row[j] + 1, last[j] + (x != y)))
    return row[-1]


def test_edit_links_match_brute_force_beyond_the_bound(spark, monkeypatch):
    monkeypatch.setattr(baselines, "ALL_PAIRS_ROWS", 2)
    monkeypatch.setattr(baselines, "TILE", 7)
    rng = random.Random(5)
    rows = [(i, i % 2, "".join(rng.choice("abä ") for _ in range(rng.randint(0, 8)))) for i in range(70)]
    df = spark.createDataFrame(rows, "rid long, source int, t string")
    got = {tuple(r) for r in baselines.edit_links(df, F.col("t"), 2).collect()}
    first = {}
    for i, _, t in rows:
        first.setdefault(t, i)
    assert got == {(i, first[t], sum(_edits(t, u) <= 2 for _, o, u in rows if o != n)) for i, n, t in rows}


def test_all_pairs_query_of_more_records_than_the_bound(spark, small, monkeypatch):
    from sigres.plans import catalog
    monkeypatch.setattr(baselines, "ALL_PAIRS_ROWS", 2)
    assert catalog.queries()["b01_all_pairs"](spark, small).count() == 2 * spark.read.parquet(f"{small}/part.parquet").count()


def _vectors(seed, n=60):
    rng = random.Random(seed)
    rows = [(i, [float(rng.randint(-3, 3)) for _ in range(4)]) for i in range(n - 2)]
    return [*rows, (n - 2, [0.0] * 4), (n - 1, rows[0][1]), (n, None)]


def _cosine(x, y):
    size = math.sqrt(sum(a * a for a in x) * sum(b * b for b in y)) if x and y else 0
    return sum(a * b for a, b in zip(x, y)) / size if size else -2


def test_cosine_links_match_brute_force_beyond_the_bound(spark, monkeypatch):
    monkeypatch.setattr(baselines, "ALL_PAIRS_ROWS", 2)
    monkeypatch.setattr(baselines, "TILE", 5)
    rows = _vectors(6)
    df = spark.createDataFrame(rows, "rid long, v array<float>")
    for least in (0.41, 0.83, -0.5):
        got = {tuple(r) for r in baselines.cosine_links(df, least).collect()}
        want = {(i, min(j for j, y in rows if y == x), sum(_cosine(x, y) >= least for j, y in rows if j != i)) for i, x in rows}
        assert got == want


def test_nearest_of_queries_matches_brute_force_beyond_the_bound(spark, monkeypatch):
    monkeypatch.setattr(baselines, "ALL_PAIRS_ROWS", 2)
    monkeypatch.setattr(baselines, "TILE", 5)
    rows = _vectors(8)
    df = spark.createDataFrame(rows, "rid long, v array<float>")
    got = {(r.rid, r.near) for r in baselines.cosine_nearest(df.where("rid % 3 = 0"), df, 0.6).collect()}
    want = set()
    for i, x in rows:
        best = max((round(_cosine(x, y), 12), -j) for j, y in rows if j != i)
        if i % 3 == 0 and best[0] >= 0.6:
            want.add((i, -best[1]))
    assert got == want


def test_jaccard_links_count_what_brute_force_finds(spark):
    rng = random.Random(3)
    rows = [(i, [f"w{rng.randrange(12)}" for _ in range(rng.randint(0, 8))]) for i in range(90)]
    df = records(spark, rows)
    sets = {i: set(w) for i, w in rows}
    for least in (0.2, 0.6, 1.0):
        got = {tuple(r) for r in baselines.jaccard_links(df, F.col("name"), least).collect()}
        want = {(i, min(j for j in sets if sets[j] == x), sum(len(x & y) >= least * len(x | y) for j, y in sets.items() if j != i and x and y)) for i, x in sets.items()}
        assert got == want


def test_jaccard_links_of_short_sets_meet_no_pair(spark, monkeypatch):
    """Sets that share a common item are counted by their subsets; the join of pairs is left to longer sets."""
    rng = random.Random(8)
    rows = [(i, [f"w{rng.randrange(9)}" for _ in range(rng.randint(0, 6))]) for i in range(150)]
    sets = {i: set(w) for i, w in rows}
    want = {(i, min(j for j in sets if sets[j] == x), sum(len(x & y) >= 0.6 * len(x | y) for j, y in sets.items() if j != i and x and y)) for i, x in sets.items()}
    monkeypatch.setattr(baselines, "_joined_counts", None)
    assert {tuple(r) for r in baselines.jaccard_links(records(spark, rows), F.col("name"), 0.6).collect()} == want


@pytest.mark.parametrize("most, least", [(3, 0.5), (5, 0.5), (8, 0.75)])
def test_jaccard_links_of_short_and_longer_sets_match_brute_force(spark, monkeypatch, most, least):
    monkeypatch.setattr(baselines, "SHORT", most)
    rng = random.Random(most)
    rows = [(i, [f"w{rng.randrange(14)}" for _ in range(rng.randint(0, 14))]) for i in range(110)]
    rows += [(200, [None]), (201, ["w1", None, "w2"]), (202, ["w2", "w1"])]
    sets = {i: {x for x in w if x} for i, w in rows}
    want = {(i, min(j for j in sets if sets[j] == x), sum(len(x & y) >= least * len(x | y) for j, y in sets.items() if j != i and x and y)) for i, x in sets.items()}
    assert {tuple(r) for r in baselines.jaccard_links(records(spark, rows), F.col("name"), least).collect()} == want


def test_jaccard_query_does_not_expand_copies(spark, small):
    from sigres.plans import catalog
    got = catalog.queries()["b05_distance_jaccard"](spark, small)
    assert got.columns == ["rid", "class_id", "links"] and got.count() == 2 * spark.read.parquet(f"{small}/part.parquet").count()


@pytest.mark.parametrize("name, table", [("m04_street_world", "customer"), ("m14_curves", "orders"), ("m17_kmax", "orders"), ("m29_toy_components", "events"), ("rel_recursive_cte", "orders")])
def test_query_reads_a_given_table(spark, small, agrees, name, table):
    from sigres.plans import catalog
    frame = fx.event_edges(spark, small) if name == "m29_toy_components" else catalog.queries()[name](spark, small)
    assert any(f.endswith(f"{table}.parquet") for f in frame.inputFiles())
    agrees(catalog.queries()[name], catalog.oracles()[name])


def test_trees_see_patterns_and_not_pairs(spark, monkeypatch):
    seen, fit = [], baselines.GBTClassifier.fit
    monkeypatch.setattr(baselines.GBTClassifier, "fit", lambda self, df: seen.append(df.count()) or fit(self, df))
    rows = [(i, i + 1, i % 5, int(i % 3 == 0), 1.0 if i % 3 == 0 else 0.25, 0.5 if i % 2 else 0.0) for i in range(600)]
    df = spark.createDataFrame(rows, "lo long, hi long, key long, label int, s1 double, s2 double")
    got = {r.lo for r in baselines.supervised_link(df, ["s1", "s2"], "tree").collect()}
    assert got == {i for i in range(600) if i % 3 == 0}
    assert len(seen) == 5 and max(seen) <= 16


def test_grid_points_meet_patterns_and_not_pairs(spark):
    """The points of a grid are tried on counted patterns of recurrences: 4 here, with their truth, for 300 pairs."""
    from sigres.operators import tuning
    rows = [(2 * i, 2 * i + 1, f"s{j}", 2 + j) for i in range(300) for j in range(1 + i % 2)]
    shared = spark.createDataFrame(rows, "lo long, hi long, sig string, k long")
    truth = spark.createDataFrame([(2 * i, 2 * i + 1) for i in range(0, 300, 3)] + [(1, 2)], "lo long, hi long")
    points = tuning.grid([2.0], [0.1], [0.1, 0.5], [0.3, 0.7, 0.8])
    assert tuning._linked(shared, truth, points).count() <= 4 * len(points)

    def linked(i, p):
        a, b, _, tau, most = p
        return 1 - math.prod(1 - 1 / (1 + a ** k * b) for k in range(2, 3 + i % 2) if k <= most) > tau
    for r in tuning.tune(shared, truth, points).collect():
        p = next(p for p in points if p[:4] == (r.a, r.b, r.rho, r.tau))
        hit = [i for i in range(300) if linked(i, p)]
        tp = sum(i % 3 == 0 for i in hit)
        assert (r.tp, r.fp, r.fn) == (tp, len(hit) - tp, 101 - tp)


def test_grouped_aggregate_sees_lists_of_recurrences_and_not_pairs(spark, small, tmp_path, monkeypatch):
    """The Python aggregate is called for each list of recurrences, of which there are far fewer than pairs."""
    from pyspark.sql.functions import pandas_udf
    from sigres.plans import catalog, streams
    calls = str(tmp_path / "calls")

    def noted():
        @pandas_udf("double")
        def f(p: pd.Series) -> float:
            with open(calls, "a") as out:
                out.write(",".join(sorted(f"{x:.9f}" for x in p)) + "\n")
            return float(1 - (1 - p).prod())
        return f
    monkeypatch.setattr(streams, "noisy_or", noted)
    pairs_found = catalog.queries()["udaf_noisy_or"](spark, small).count()
    seen = open(calls).read().split()
    assert len(seen) == len(set(seen)) and 0 < len(seen) < pairs_found


@pytest.mark.parametrize("rows, tile", [(4000, 1000), (2, 3)])
def test_block_patterns_count_every_pair_of_a_block(spark, small, monkeypatch, rows, tile):
    """However blocks are dealt and tiled, the counts are those of the pairs themselves."""
    monkeypatch.setattr(baselines, "BLOCK_ROWS", rows)
    monkeypatch.setattr(baselines, "TILE", tile)
    rng = random.Random(4)
    word = lambda n: [rng.choice("abcd") for _ in range(rng.randint(0, n))]
    people = [(rng.choice(["p", "q", "r", None]), k, word(4), word(1), source) for k in range(40) for source in (0, 1) if rng.random() < 0.8]
    people += [("left", 50, ["a"], [], 0), ("right", 51, ["a"], [], 1)]
    df = spark.createDataFrame(people, "block string, key long, u array<string>, v array<string>, source int")
    got = baselines.block_patterns(df.where("source = 0"), df.where("source = 1"), ["u", "v"])
    alike = lambda a, b: len(set(a) & set(b)) / len(set(a) | set(b)) if a or b else 1.0
    want = {}
    for p in people:
        for q in people:
            if p[4] == 0 and q[4] == 1 and p[0] is not None and p[0] == q[0]:
                pattern = (p[1] % 5, float(p[1] == q[1]), alike(p[2], q[2]), alike(p[3], q[3]))
                want[pattern] = want.get(pattern, 0) + 1
    assert {tuple(r)[:-1]: r.weight for r in got.collect()} == want


def test_svm_query_learns_what_every_pair_says(spark, small, monkeypatch):
    """The query sees at most so many rows, and its result is that of an SVM on every pair."""
    from sigres.plans import catalog
    want = comparisons._scored(baselines.supervised_link(comparisons.features(spark, small), comparisons._SIMS, "svm"), spark, small).collect()
    seen, fit = [], baselines.LinearSVC.fit
    monkeypatch.setattr(baselines.LinearSVC, "fit", lambda self, df: seen.append(df.count()) or fit(self, df))
    got = catalog.queries()["b10_svm"](spark, small)
    assert got.columns == ["tp", "fp", "fn", "precision", "recall", "f"] and got.collect() == want
    monkeypatch.setattr(baselines, "SVM_ROWS", 40)
    every = max(seen)
    seen.clear()
    catalog.queries()["b10_svm"](spark, small).collect()
    assert len(seen) == 5 and max(seen) < every


@pytest.mark.parametrize("rows, tile, table", [(4000, 1000, 10 ** 6), (3, 4, 1)])
def test_trees_on_blocks_link_what_trees_on_pairs_link(spark, monkeypatch, rows, tile, table):
    """However blocks are dealt, tiled and counted, the links are those of the pairs themselves."""
    rng = random.Random(12)
    word = lambda n: [rng.choice("abcde") for _ in range(rng.randint(0, n))]
    people = []
    for k in range(90):
        u, v, block = word(4), word(2), rng.choice(["p", "q", "r", None])
        people += [(2 * k + n, n, block, k, u if rng.random() < 0.8 else word(4), v if rng.random() < 0.8 else word(2)) for n in (0, 1) if rng.random() < 0.9]
    people += [(500, 0, "left", 250, ["a"], []), (503, 1, "right", 251, ["a"], [])]
    df = spark.createDataFrame(people, "rid long, source int, block string, key long, u array<string>, v array<string>").cache()
    side = lambda p, n: df.where(F.col("source") == n).select("block", *[F.col(c).alias(f"{p}_{c}") for c in ("rid", "key", "u", "v")])
    alike = lambda a: baselines.jaccard(F.col(f"x_{a}"), F.col(f"y_{a}")).alias(f"sim_{a}")
    pairs_ = side("x", 0).join(side("y", 1), "block").select(F.col("x_rid").alias("lo"), F.col("y_rid").alias("hi"), F.col("x_key").alias("key"),
                                                             (F.col("x_key") == F.col("y_key")).cast("int").alias("label"), alike("u"), alike("v"))
    want = sorted(map(tuple, baselines.supervised_link(pairs_, ["sim_u", "sim_v"], "tree").collect()))
    monkeypatch.setattr(baselines, "BLOCK_ROWS", rows)
    monkeypatch.setattr(baselines, "TILE", tile)
    monkeypatch.setattr(baselines, "TABLE", table)
    blocks = baselines.BlockPairs(df.where("source = 0"), df.where("source = 1"), ["u", "v"])
    got = sorted(map(tuple, baselines.supervised_link(blocks, ["sim_u", "sim_v"], "tree").collect()))
    assert got == want and 0 < len(got) < pairs_.count()


def test_trees_query_makes_no_frame_of_pairs(spark, small, monkeypatch):
    from sigres.plans import catalog
    want = comparisons._scored(baselines.supervised_link(comparisons.features(spark, small), comparisons._SIMS, "tree"), spark, small).collect()
    monkeypatch.setattr(comparisons, "features", None)
    assert catalog.queries()["b11_boosted_trees"](spark, small).collect() == want


@pytest.mark.parametrize("word, most, length", [(64, 2, 9), (64, 6, 60), (64, 5, 90), (3, 3, 12)])
def test_edit_distances_of_arrays_match_brute_force(monkeypatch, word, most, length):
    """Texts of any length and letters: near ones of two sources, each once."""
    import numpy as np
    import pyarrow as pa
    monkeypatch.setattr(baselines, "WORD", word)
    monkeypatch.setattr(baselines, "EDIT_TILE", 7)
    monkeypatch.setattr(baselines, "EDIT_PAIRS", 50)
    rng = random.Random(most)
    texts = {"", "a"}
    while len(texts) < 45:
        t = list(rng.choice(sorted(texts))) if rng.random() < 0.6 else [rng.choice("ab ä€\U0001f600") for _ in range(rng.randint(length // 2, length))]
        for _ in range(rng.randint(1, most)):
            t[rng.randint(0, len(t)):rng.randint(0, len(t)) + 1] = [rng.choice("abz😀")]
        texts.add("".join(t)[:length])
    texts = sorted(texts)
    n = [(rng.randint(0, 2), rng.randint(0, 2)) for _ in texts]
    table = lambda part: pa.table({"id": [i for i in part], "t": [texts[i] for i in part], "n0": [n[i][0] for i in part], "n1": [n[i][1] for i in part]})
    near = lambda i, j: _edits(texts[i], texts[j]) <= most and (n[i][0] * n[j][1] or n[i][1] * n[j][0])
    every = range(len(texts))
    for left, right in ((every, every), (every[:20], every[20:]), (every[:0], every)):
        a = baselines._Texts(table(left))
        b = a if left is right else baselines._Texts(table(right))
        got = sorted(tuple(sorted(p)) for u, v in baselines._near(a, b, most, a is b) for p in zip(a.id[u].tolist(), b.id[v].tolist()))
        assert got == sorted({tuple(sorted((i, j))) for i in left for j in right if i != j and near(i, j)})


def test_edit_links_put_out_no_pair(spark, monkeypatch):
    """A task's rows are texts with their counts, not pairs: 60 texts of which every two are near."""
    seen, join = [], baselines.block_join
    monkeypatch.setattr(baselines, "block_join", lambda *a, **k: seen.append(join(*a, **k)) or seen[-1])
    rows = [(i, i % 2, f"same words {chr(97 + i // 2 % 26)}{chr(97 + i // 52)}") for i in range(120)]
    got = {r.rid: r.links for r in baselines.edit_links(spark.createDataFrame(rows, "rid long, source int, t string"), F.col("t"), 2).collect()}
    assert got == {i: 60 for i in range(120)}
    assert seen[0].columns == ["id", "c0", "c1"] and seen[0].count() <= 60 * 16
