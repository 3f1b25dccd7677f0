"""The corpus operators on odd rows and against brute force or SQL."""

import math
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from sigres.llm import (catalog, crf, decontaminate, exact_dedup, html_text, language_id, mixing, pii, quality, simhash, toxicity,
                        url_filter)
from sigres.operators.baselines import components_local
from sigres.plans.scratch import Scratch

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, key string, score double"
LONG = "word " * 30_000
ODD = [(1, None, "en", "a", 0, "k", 0.1), (2, "", None, None, 0, None, None), (3, " \t\n", "en", "a", 3, "k", 0.2), (4, LONG, "en", "b", 1, "k", 0.3),
       (5, "The same text here.", "en", None, 1, "k", 0.4), (6, "The same\ttext  here.", "en", "b", 1, "k", 0.5), (7, "12 34 !!", "de", "c", 1, "k", 0.6),
       (8, "The same text here.", "fr", "a", 1, "k", 0.7), (8, "The same text here.", "fr", "a", 1, "k", 0.7), (None, "No id at all", None, "a", 1, "k", 0.8)]
LABELS = "doc_id long, quality int, toxic int"


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.mark.parametrize("name", sorted(catalog.ORACLES))
def test_agrees_with_oracle(name, agrees):
    agrees(catalog.QUERIES[name], catalog.ORACLES[name])


# ---- exact copies ----

def test_exact_duplicates_of_odd_rows(odd, none):
    rows = exact_dedup.exact_duplicates(odd).collect()
    assert len(rows) == len(ODD)
    by = {}
    for r in rows:
        by.setdefault(r.text_sha256, []).append(r)
    blank = by["e3b0c44298fc1c149afbf4c8996fb92427ae41e4649b934ca495991b7852b855"]
    assert {r.doc_id for r in blank} == {1, 2, 3} and {r.keep_id for r in blank} == {3}  # most code points
    same = [r for r in rows if r.group_size == 4]
    assert {r.doc_id for r in same} == {5, 6, 8} and {r.keep_id for r in same} == {6} and sum(r.kept for r in same) == 1
    assert exact_dedup.exact_duplicates(none).count() == 0


def test_exact_duplicates_by_shuffle_joins(spark):
    random.seed(2)
    texts = ["p" * random.choice([3, 64, 65, 300]) + random.choice(["", "x", "y" * 400]) for _ in range(200)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(5)
    want = {i: min(j for j, u in enumerate(texts) if u == t) for i, t in enumerate(texts)}
    for limit in (0, 100_000):
        assert {r.doc_id: r.keep_id for r in exact_dedup.exact_duplicates(df, limit).collect()} == want


def test_radix_classes():
    texts = [b"", b"a" * 64, b"a" * 64, b"a" * 65, b"a" * 320 + b"b", b"a" * 320 + b"c", b"a" * 320 + b"b", b""]
    assert sorted(map(sorted, exact_dedup.radix_classes(texts))) == [[0, 7], [1, 2], [3], [4, 6], [5]]


# ---- mixing ----

def test_mix_of_odd_rows(odd, none):
    rows = mixing.mix(odd).collect()
    assert len(rows) == len(ODD) and all(0 <= r.taken <= 2 * r.size for r in rows)
    for source in {r.source for r in rows}:
        mine = [r for r in rows if r.source == source]
        assert abs(sum(r.taken for r in mine) - mine[0].target) <= 0.5
    total = sum(r.size for r in rows)
    assert sum({r.source: r.target for r in rows}.values()) == pytest.approx(1.5 * total)
    assert mixing.mix(none).count() == 0 and mixing.curriculum(none).count() == 0


def test_curriculum_follows_the_schedule(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    rows = mixing.curriculum(docs).collect()
    mixed = {r.doc_id: r for r in mixing.mix(docs).collect()}
    words = {}
    for r in rows:
        words[r.doc_id] = words.get(r.doc_id, 0) + r.words
        assert 0 <= r.position <= 1
    assert words == {k: r.taken for k, r in mixed.items() if r.taken}
    assert rows == mixing.curriculum(docs.repartition(3)).orderBy("position", "doc_id", "epoch").collect()


def test_mixing_query_follows_the_training_order(spark, small):
    first = {}
    for r in mixing.curriculum(spark.read.parquet(f"{small}/documents.parquet")).collect():
        first[r.doc_id] = min(r.position, first.get(r.doc_id, 2.0))
    rows = catalog.op1_mixing(spark, small).collect()
    placed = [first.get(r.doc_id, 2.0) for r in rows]
    assert len(first) > 100 and placed == sorted(placed)
    assert all((r.taken > 0) == (r.doc_id in first) for r in rows)


def test_demand_inverse(spark):
    knots = ((0.0, 0.5), (0.5, 1.0), (1.0, 1.5))
    for share in (0.0, 0.1, 0.375, 0.5, 0.9, 1.0):
        t = spark.range(1).select(mixing.demand_inverse(F.lit(share), knots).alias("t")).first().t
        assert 0.5 * t + t * t / 2 == pytest.approx(share, abs=1e-9)


# ---- near copies ----

def brute_fingerprint(text):
    w = simhash.words_of(text)
    h = simhash.shingle_hashes(w, 3).tolist()
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


@pytest.mark.parametrize("run", [4096, 12])
def test_links_match_brute_force(spark, run):
    random.seed(1)
    prints = set()
    for _ in range(3):
        base = random.getrandbits(64)
        for _ in range(120):
            x = base
            for b in random.sample(range(64), random.choice([1, 2, 3, 5, 6])):
                x ^= 1 << b
            prints.add(x - (1 << 64) if x >> 63 else x)
    prints = sorted(prints)
    df = spark.createDataFrame([(p,) for p in prints], "fp long")
    got = [(r.a, r.b) for r in simhash.exact_links(df, Scratch(spark, "t"), run).collect()]
    far = lambda a, b: bin((a ^ b) & (2**64 - 1)).count("1")
    assert all(far(a, b) <= 3 for a, b in got)
    from sigres.operators.baselines import components_local
    brute = components_local([(a, b) for i, a in enumerate(prints) for b in prints[:i] if far(a, b) <= 3])
    assert components_local(got) == brute


def test_components_of_odd_rows(odd, none):
    rows = simhash.linked_components(odd).collect()
    assert len(rows) == len(ODD)
    for r, text in ((r, t[1]) for r in rows for t in ODD if t[0] == r.doc_id):
        assert r.fp % (1 << 64) == brute_fingerprint(text)
    assert {r.component_id for r in rows if r.doc_id in (1, 2, 3)} == {1}
    assert {r.component_id for r in rows if r.doc_id in (5, 6, 8)} == {5}
    assert simhash.linked_components(none).count() == 0 and simhash.near_duplicates(none).count() == 0


def test_near_duplicates(spark):
    random.seed(3)
    rows = []
    for g in range(25):
        w = [f"w{random.randrange(5000)}" for _ in range(200)]
        rows.append((g * 10, " ".join(w)))
        for c in (1, 2):
            v = list(w)
            v[random.randrange(200)] = "changed"
            rows.append((g * 10 + c, " ".join(v)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in simhash.near_duplicates(df).collect()}
    found = sum(got.get(i) == i // 10 * 10 for i, _ in rows)
    assert found >= 0.97 * len(rows) and all(v == k // 10 * 10 for k, v in got.items())


def test_near_duplicates_count_each_shingle_once(spark):
    rng = random.Random(8)
    words = lambda n: " ".join(f"w{rng.randrange(5000)}" for _ in range(n))
    base, line = words(200), words(12)
    rows = [(1, base), (2, base + (" " + base[-40:]) + (" " + line) * 40), (3, base + " " + line)]  # repeats weigh nothing
    rows += [(10, line * 60 + words(60)), (11, line * 60 + words(60))]  # only what is repeated is shared
    got = {r.doc_id: r.component_id for r in simhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: 1, 2: 1, 3: 1}


def jaccard_links(sets, least=0.8):
    """All links of brute force."""
    return [(a, b) for b in range(len(sets)) for a in range(b)
            if (same := len(np.intersect1d(sets[a], sets[b]))) >= least * (len(sets[a]) + len(sets[b]) - same)]


@pytest.mark.parametrize("run,block", [(16, 8), (simhash.RUN, simhash.BLOCK)])
def test_near_duplicates_in_large_buckets(spark, run, block):
    # edits of one text at mixed similarity: all links of brute force count, not only a forest's edges
    rng = random.Random(1)
    word = lambda: "".join(rng.choices("abcdefghij", k=6))
    base, texts = [word() for _ in range(400)], []
    while len(texts) < 150:
        new = list(base)
        for _ in range(rng.randint(4, 10)):
            new[rng.randrange(len(new))] = word()
        texts.append(new)
    rows = list(enumerate(" ".join(t) for t in texts))
    sets = [np.unique(simhash.shingle_hashes(simhash.words_of(t), 5)) for _, t in rows]
    want = components_local(jaccard_links(sets))
    assert 20 < len(want) and len(set(want.values())) < 150
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert {r.doc_id: r.component_id for r in simhash.near_duplicates(df, run=run, block=block).collect()} == want


def test_recall_by_size_of_class(spark):
    rng = random.Random(6)
    word = lambda: "".join(rng.choices("abcdefghij", k=5))
    texts = []
    for size in [2] * 60 + [5] * 20 + [14] * 6 + [40] * 3:
        base = [word() for _ in range(150)]
        for _ in range(size):
            new = list(base)
            for _ in range(rng.randint(0, 4)):
                new[rng.randrange(len(new))] = word()
            texts.append(new)
    rows = [(i, " ".join(t)) for i, t in enumerate(texts)]
    sets = [np.unique(simhash.shingle_hashes(simhash.words_of(t), 5)) for _, t in rows]
    want = components_local(jaccard_links(sets))
    got = {r.doc_id: r.component_id for r in simhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    sizes = {}
    for i, c in want.items():
        sizes.setdefault(c, []).append(i)
    for low, high in ((2, 4), (5, 13), (14, 39), (40, 10**6)):
        gone = [i for c, m in sizes.items() if low <= len(m) <= high for i in m if i != c]
        assert sum(got.get(i, i) != i for i in gone) >= 0.97 * len(gone)
    assert all(want.get(i) == want.get(c) for i, c in got.items())


def test_thinned_edges_reach_as_far(spark):
    rng = random.Random(8)
    edges = [(rng.randrange(150), rng.randrange(150)) for _ in range(170)] * 3
    want = components_local(edges)
    for most in (1, 7, 60, 10_000):
        frame = Scratch(spark, "t").save(spark.createDataFrame(edges, "a long, b long"), "edges")
        got = [tuple(r) for r in simhash._thinned(frame, most).collect()]
        assert components_local(got) == {k: v for k, v in want.items() if k in {x for e in got for x in e}}
        assert {frozenset(x) for x in got} <= {frozenset(x) for x in edges}
        assert {k for k, v in want.items() if list(want.values()).count(v) > 1} <= {x for e in got for x in e}
    assert len(got) < 150
    assert simhash._thinned(Scratch(spark, "t").save(spark.createDataFrame([], "a long, b long"), "edges")).count() == 0


def test_forests_do_not_depend_on_the_order_of_rows():
    rng = np.random.default_rng(3)
    sketch, ids = rng.integers(0, 1 << 6, 60).astype(np.uint64), rng.permutation(1000)[:60]
    edges = lambda order: {frozenset(e) for e in simhash._spanning(sketch[order], ids[order], 2)}
    first = edges(np.arange(60))
    assert first and all(edges(rng.permutation(60)) == first for _ in range(20))


def test_links_across_classes_that_no_forest_has(spark):
    # a and b are alike, x is between them and like neither: only the comparison inside the cluster joins a and b
    whole = list(range(100))
    sets = {1: whole, 2: whole[:95], 3: whole[:60] + list(range(200, 240)), 4: whole[:95] + [500], 5: list(range(900, 950))}
    df = spark.createDataFrame([(i, sorted(h)) for i, h in sets.items()], "id long, hashes array<long>")
    members = spark.createDataFrame([(1, i, i) for i in sets], "cluster long, id long, label long")
    want = {frozenset(e) for e in ((1, 2), (1, 4), (2, 4))}
    for block in (1, 2, 256):
        got = {frozenset((r.a, r.b)) for r in simhash._across(members, df, 0.8, Scratch(spark, "t"), block).collect()}
        assert got <= want and components_local([tuple(e) for e in got]) == {1: 1, 2: 1, 4: 1}
    one = members.withColumn("label", F.lit(1).cast("long"))
    assert simhash._across(one, df, 0.8, Scratch(spark, "t")).count() == 0


def test_repeated_ids_with_different_texts(spark):
    texts = [" ".join(f"{p}{i}" for i in range(60)) for p in "ab"]
    rows = [(1, texts[0]), (1, texts[1]), (2, texts[1]), (3, texts[0] + " more")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    one = sorted(tuple(r) for r in simhash.near_duplicates(df).collect())
    assert one == sorted(tuple(r) for r in simhash.near_duplicates(df.orderBy(F.desc("doc_id"), F.desc("text")).repartition(3)).collect())


def test_quantiles_of_binned_counts(spark):
    rows = [(k, b, n) for k in ("x", None) for b, n in ((0, 90), (5, 5), (5, 4), (9, 1))]
    bins = spark.createDataFrame(rows, "lang string, bin long, n long")
    for keys, total in (([], 200), (["lang"], 100)):
        for share, at in ((0.9, 0), (0.91, 5), (0.99, 5), (1.0, 9)):
            got = quality.quantiles(bins, keys, share).collect()
            assert len(got) == (2 if keys else 1) and all(r.total == total for r in got)
            assert all(abs(r.q - math.exp((at + 1) / quality.GRID)) < 1e-9 for r in got)
    assert quality.quantiles(bins.limit(0), [], 0.5).count() == 0


# ---- benchmark passages ----

def test_contamination(spark, odd, none):
    rng = random.Random(5)
    words = lambda n: [f"t{rng.randrange(3000)}" for _ in range(n)]
    items = [(i, " ".join(words(30))) for i in range(20)] + [(99, "too short"), (98, None), (None, "no id " * 20), (97, "")]
    docs, want = [], {}
    for i in range(60):
        w = words(150)
        if i % 3 == 0:
            item = items[i % 20]
            part = item[1].split()
            if i % 2:
                part[rng.randrange(5, 25)] = "replaced"
            w[40:40] = part
            want[i] = item[0]
        docs.append((i, " ".join(w).upper() if i % 5 == 0 else ", ".join(w)))
    df, bench = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    for limit in (0, 1_000_000):
        rows = decontaminate.judge(df, bench, broadcast_seeds=limit).collect()
        assert {r.doc_id: r["items"][0] for r in rows if r.contaminated} == want
    assert decontaminate.judge(odd, bench).where("contaminated").count() == 0
    assert decontaminate.judge(none, bench).count() == 0
    assert decontaminate.judge(df, bench.limit(0)).where("contaminated").count() == 0
    assert decontaminate.decontaminate(odd, bench).columns == odd.columns


@pytest.mark.parametrize("size,counts", [(5, (0,)), (8, (0,)), (9, (0, 1)), (11, (1, 2)), (14, (3,)), (17, (4,)), (20, (4, 5)), (30, (5,))])
def test_recall_of_seeds(spark, size, counts):
    rng = random.Random(size)
    words = lambda n: [f"t{rng.randrange(100_000)}" for _ in range(n)]
    items = {i: words(size) for i in range(150)}
    docs, many = [], {}
    for i, item in items.items():
        part = list(item)
        gone = counts[i % len(counts)]
        for j in rng.sample(range(min(size, 20)), gone):
            part[j] = "replaced"
        docs.append((i, " ".join(words(30) + part + words(30))))
        many[i] = gone
    # one word too many is one word too many, unless a window of a longer item is left
    bench = spark.createDataFrame([(i, " ".join(w)) for i, w in items.items()], "item_id long, text string")
    got = {r.doc_id: r["items"] for r in decontaminate.contaminated(spark.createDataFrame(docs, "doc_id long, text string"), bench).collect()}
    for n in counts:
        mine = [i for i in many if many[i] == n]
        assert sum(got.get(i) == [i] for i in mine) >= 0.93 * len(mine)
    if size <= 20:
        worst = spark.createDataFrame([(i, " ".join(words(9) + ["x"] * (max(counts) + 1) + w[max(counts) + 1:] + words(9))) for i, w in items.items()], "doc_id long, text string")
        assert decontaminate.contaminated(worst, bench).count() == 0


def test_native_plan(spark, small):
    plan = decontaminate.judge(spark.read.parquet(f"{small}/documents.parquet"), spark.read.parquet(f"{small}/benchmark.parquet"))
    assert not re.search("Python|Pandas|Arrow", plan._jdf.queryExecution().toString())


# ---- language ----

def test_gradients_of_the_network():
    rng = np.random.default_rng(0)
    net = language_id._fresh(["a", "b", "c"], rng, 4)
    net.arrays = {k: v.astype(np.float64) for k, v in net.arrays.items()}
    x, n, y = rng.integers(0, 256, (6, 4)).astype(np.uint8), np.array([6, 4, 2, 6]), np.array([0, 1, 2, 0])
    _, g = language_id.gradients(net, x, n, y)
    for k, v in net.arrays.items():
        at = np.unravel_index(np.abs(g[k]).argmax(), v.shape)
        v[at] += 1e-3
        up = language_id.gradients(net, x, n, y)[0]
        v[at] -= 2e-3
        down = language_id.gradients(net, x, n, y)[0]
        v[at] += 1e-3
        assert g[k][at] == pytest.approx((up - down) / 2e-3, rel=1e-2)


def test_language_held_out(spark, small, odd, none):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    truth = {r.doc_id: r.lang for r in docs.select("doc_id", "lang").collect()}
    rows = language_id.identify(docs).collect()
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) and 0 <= r.score <= 1 for r in rows)
    held = [r for r in rows if r.held_out]
    assert sum(truth[r.doc_id] == r.lang_pred for r in held) >= 0.9 * len(held)
    got = {r.doc_id: r.lang_pred for r in language_id.identify(odd).collect()}
    assert all(got[i] == "und" for i in (1, 2, 3, 7)) and got[4] != "und"
    assert language_id.identify(none).count() == 0


def test_network_matches_a_scalar_loop():
    rng = np.random.default_rng(3)
    net = language_id._fresh(["a", "b"], rng, 3)
    a, x = net.arrays, rng.integers(0, 256, 7).astype(np.uint8)
    sig = lambda v: 1 / (1 + math.exp(-v))

    def states(way):
        h, out = [0.0] * 3, [None] * 7
        for t in range(7) if way == 0 else range(6, -1, -1):
            drive = [float(a["embed"][way][k][x[t]]) for k in range(9)]
            back = [sum(float(a["turn"][way][k][i]) * h[i] for i in range(3)) for k in range(9)]
            new = []
            for k in range(3):
                reset, update = sig(drive[k] + back[k]), sig(drive[3 + k] + back[3 + k])
                candidate = math.tanh(drive[6 + k] + reset * (back[6 + k] + float(a["bias"][way][k][0])))
                new.append(candidate + update * (h[k] - candidate))
            h = new
            out[t] = h
        return out
    ahead, behind = states(0), states(1)
    total = [0.0, 0.0]
    for t in range(5):  # of seven positions the first five count
        z = [math.exp(sum(float(a["out"][0][k][i]) * ahead[t][i] + float(a["out"][1][k][i]) * behind[t][i] for i in range(3)) + float(a["level"][k][0])) for k in range(2)]
        total = [v + w / sum(z) for v, w in zip(total, z)]
    got = language_id.position_sums(net, x[:, None], np.array([5]))
    assert got[:, 0] == pytest.approx(total, abs=1e-4)


def test_letters_and_sample_of_languages(spark):
    assert not any(map(language_id.has_letter, ("\u00bd", "\u00b2", "\u2167", "\u2460", "12 _ !", ""))) and language_id.has_letter("1a") and language_id.has_letter("\u00e9")
    rows = [(i, "one and the same text " * 20, "en") for i in range(500)] + [(1000 + i, f"text number {i} " * 30, "en") for i in range(50)] + [(2000, "kurz", "de")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(5)
    segments, langs = language_id.sample(df, docs_each=10, segments_each=3)
    assert langs.count("de") == 1 and langs.count("en") <= 30 and len(set(segments)) > 10
    assert language_id.sample(df.repartition(2), docs_each=10, segments_each=3) == (segments, langs)


# ---- personal data ----

PATTERNS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
            "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def brute_spans(text):
    out = []
    for kind, p in PATTERNS.items():
        for m in re.finditer(p, text):
            d = re.sub("[^0-9]", "", m[0])
            if (kind == "email" or kind == "ip" and all(int(x) <= 255 for x in m[0].split("."))
                    or kind == "card" and 13 <= len(d) <= 19 and pii._luhn(d) or kind == "phone" and 9 <= len(d) <= 15):
                out.append((kind, m.start(), m.end()))
    return out


def test_base_spans():
    rng = random.Random(3)
    for _ in range(20_000):
        text = "".join(rng.choice("ab@.@.-1 2+3()_é") for _ in range(rng.randint(0, 24)))
        assert pii.base_spans(text) == brute_spans(text)
    text = "4111 1111 1111 1111 and 0000000000000 or 1.2.3.0255 " + "9" * 5000 + " " + "a" * 5000 + "@"
    assert pii.base_spans(text) == brute_spans(text)
    assert pii.base_spans(None) == []


def test_personal_data_of_odd_rows(spark, odd, none):
    rows = pii.find_personal_data(odd).collect()
    assert len(rows) == len(ODD) and all(r.spans == "" for r in rows if r.doc_id != 7)
    assert pii.find_personal_data(none).count() == 0
    df = spark.createDataFrame([(1, "write to a.b@c.example, or token = \"24be64439e3e49cf46b2d7c90f3602a3d0b907ff\" now")], "doc_id long, text string")
    r = pii.find_personal_data(df).first()
    assert r.n_email == 1 and r.spans == "email:9:22,secret:36:76"
    assert pii.masked(df).first().text == "write to <email>, or token = \"<secret>\" now"


def test_viterbi_and_marginals_match_enumeration():
    from itertools import product
    rng = np.random.default_rng(1)
    m = crf.LinearChain(["a", "b", "c"], {})
    m.moves = rng.standard_normal((3, 3))
    lengths = [4, 1, 3]
    e, chain = rng.standard_normal((8, 3)), crf.Chain(lengths)
    tags, p = m.viterbi(e, chain), m.marginals(e, chain)
    at = 0
    for n in lengths:
        paths = {y: sum(e[at + i, y[i]] for i in range(n)) + sum(m.moves[y[i], y[i + 1]] for i in range(n - 1)) for y in product(range(3), repeat=n)}
        assert tuple(tags[at:at + n]) == max(paths, key=paths.get)
        z = sum(np.exp(v) for v in paths.values())
        for i in range(n):
            for k in range(3):
                assert p[at + i, k] == pytest.approx(sum(np.exp(v) for y, v in paths.items() if y[i] == k) / z)
        at += n


# ---- quality ----

def test_quality(spark, odd, none):
    rng = random.Random(7)
    syllables = ["th", "er", "an", "in", "on", "re", "st", "ly"]
    good = lambda: " ".join("".join(rng.choices(syllables, k=rng.randint(1, 4))) for _ in range(120)).capitalize() + "."
    rows = [(i, good(), "en") for i in range(300)]
    bad = [(1000 + i, re.sub(r" ", "### ", good()).upper(), "en") for i in range(30)]
    docs = spark.createDataFrame(rows + bad, "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, 1, 0) for i in range(200)], LABELS)
    got = {r.doc_id: r for r in quality.classify(docs, labels).collect()}
    assert sum(got[i].keep for i, *_ in rows) >= 297 and not any(got[i].keep for i, *_ in bad)
    shards = {r.doc_id: r for r in quality.classify(docs, labels, shard_grams=200).collect()}
    assert all(shards[i].perplexity == got[i].perplexity for i in got)
    assert quality.classify(odd, labels.limit(0)).where("not keep").count() == 0
    assert len(quality.classify(odd, spark.createDataFrame([(4, 1, 0)], LABELS)).collect()) == len(ODD)
    assert quality.classify(none, labels).count() == 0


class BruteKneserNey:
    """Interpolated modified Kneser-Ney of order four by dictionaries of strings."""

    def __init__(self, texts):
        grams = {4: {}}
        for t in texts:
            t = "\0\0\0" + t
            for i in range(3, len(t)):
                grams[4][t[i - 3:i + 1]] = grams[4].get(t[i - 3:i + 1], 0) + 1
        for k in (3, 2, 1):
            grams[k] = {}
            for g in grams[k + 1]:
                grams[k][g[1:]] = grams[k].get(g[1:], 0) + 1
        self.grams, self.symbols, self.d = grams, len(set("".join(texts))) + 2, {}
        for k, table in grams.items():
            n = [max(1, sum(v == i for v in table.values())) for i in (1, 2, 3, 4)]
            y = n[0] / (n[0] + 2 * n[1])
            self.d[k] = [min(max(i - (i + 1) * y * n[i] / n[i - 1], 0.05), i - 0.05) for i in (1, 2, 3)]

    def p(self, context, w):
        if context is None:
            return 1 / self.symbols
        k = len(context) + 1
        lower = self.p(context[1:] if context else None, w)
        row = {g: n for g, n in self.grams[k].items() if g[:-1] == context}
        total = sum(row.values())
        if not total:
            return lower
        cut = lambda n: self.d[k][min(n, 3) - 1]
        mine = row.get(context + w, 0)
        return ((mine - cut(mine) if mine else 0) + sum(map(cut, row.values())) * lower) / total


def test_model_matches_dictionaries(spark):
    texts = ["abcab cabca bcaab " * 5, "the cat sat on the mat", "\u4e2d\u6587\u5b57\u7b26 \u4e2d\u6587", "a\U0001f600b" * 3, ""]
    brute = BruteKneserNey(texts)
    seen = [*texts, "the dog sat", "\u4e2d\u5b57\u6587 unseen \u00df", "", None]
    docs = spark.createDataFrame([(i, "x", t) for i, t in enumerate(seen)], "doc_id long, lang string, text string")
    trusted = docs.where(F.col("doc_id") < len(texts))
    for most in (10**6, 20):
        scratch = Scratch(spark, "t")
        model = quality.train(trusted, scratch, most)
        assert (model.shards > 1) == (most == 20)
        for r in quality.score(docs, model, scratch).collect():
            t = "\0\0\0" + (seen[r.doc_id] or "")
            want = -sum(math.log(brute.p(t[i - 3:i], t[i])) for i in range(3, len(t)))
            assert r.n_chars == len(t) - 3 and r.nll / quality.STEP == pytest.approx(want, rel=1e-5, abs=1e-6)
    for context in ("the", "cab", "\0\0a", "zzz"):
        total = sum(brute.p(context, w) for w in set("".join(texts))) + 2 * brute.p(context, "\1")
        assert total == pytest.approx(1)


# ---- HTML ----

@pytest.mark.parametrize("page,text", [
    ("<p>a<p>b <b>c</b>d<ul><li>x<li>y<ul><li>z</ul></ul>tail", "a\n\nb cd\n\n- x\n- y\n  - z\n\ntail"),
    ("<table><tr><th>Name<th>Qty<tr><td>apple<td>3<tr><td>fig<td colspan=2>12</table>after", "Name   Qty\napple  3\nfig    12\n\nafter"),
    ("<div hidden>no</div><p style='display: none'>n</p>yes<br>next<ol start=3><li>q<li>r</ol>", "yes\nnext\n\n3. q\n4. r"),
    ("x < y & z &lt;b&gt;", "x < y & z <b>"), ("<script>var t='</p>'</script>ok<!-- c --> fin", "ok fin"), ("", ""), ("<", "<"),
    ("<table><tr><td rowspan=2>a<td>b<tr><td>c</table>", "a  b\n   c"), ("x<![CDATA[gone]]>y", "xy"),
    ("<table><tr><td>a<td rowspan=3>b<td>c<tr><td>d<td>e<tr><td>f</table>", "a  b  c\nd     e\nf"),
    ("<div style='visibility:hidden'>no<b style='visibility: visible'>yes</b></div>", "yes"),
    ("<details><summary>s</summary>body</details><details open><summary>t</summary>more</details>", "s\nt\nmore"),
    ("<style>.ad, #x{display:none} @media print{p{display:none}} p.q{display:none}</style><p class='ad b'>n<p id=x>n<p>see<p class=q>n", "see"),
    ("<table><tr><td>" + "L" * 90 + "<td>z<tr><td>short<td>y<tr><td>longer<td>x</table>", "L" * 90 + "  z\nshort   y\nlonger  x"),
    ("<pre> a\n  b</pre>", " a\n  b"), ("</div></p>loose<li>item", "loose\n- item"), (None, None)])
def test_rendering(page, text):
    assert html_text.extract(page) == text


def test_rendering_is_linear_and_deep():
    assert html_text.extract("<div>" * 20_000 + "x") == "x"
    assert html_text.extract("<b>" * 20_000 + "</i>" * 20_000 + "x") == "x"


def test_pages_of_odd_rows(spark):
    df = spark.createDataFrame([(1, "u", None), (2, None, ""), (None, "u", "<p>x"), (3, "u", "<p>x"), (3, "u", "<p>x")], "page_id long, url string, html string")
    assert sorted((r.text or "-") for r in html_text.extract_pages(df).collect()) == ["-", "-", "x", "x", "x"]
    assert html_text.extract_pages(df.limit(0)).count() == 0


# ---- URLs ----

def test_urls_of_odd_rows(spark):
    urls = [None, "", "no scheme", "http://", "http://A.Net", "http://a.NET/x?y", "x://example.net/en/1", "https://b.example.com/de/", "https://b.example.com/de",
            "http://q.org/fr/z#f", "http://spam-farm.example.org/x", "http://notspam-farm.example.org/", "://net/", "http://net?/"]
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = {urls[r.page_id]: (r.host, r.path, r.rule, r.verdict) for r in url_filter.filter_urls(df).collect()}
    assert got["http://a.NET/x?y"] == ("a.net", "/x", "net/", "block") and got["http://A.Net"] == ("a.net", "", None, "allow")
    assert got["x://example.net/en/1"][2:] == ("example.net/en/", "allow") and got["https://b.example.com/de"][2] is None
    assert got["http://q.org/fr/z#f"][2:] == ("org/fr/", "allow") and got["http://spam-farm.example.org/x"][3] == "block"
    assert got["http://notspam-farm.example.org/"][3] == "allow" and got[None][:2] == ("", "") and got["://net/"][2] == "net/"


def test_colliding_digests(tmp_path):
    same = lambda entry: len(entry) % 2
    stem = str(tmp_path / "x")
    url_filter.DigestArray.write(stem, [("a", 1), ("b", 2), ("cc", 3), ("ddd", 4)], same)
    assert url_filter.DigestArray(stem).find(["a", "b", "cc", "ddd", "e", "ff"], same).tolist() == [1, 2, 3, 4, -1, -1]
    url_filter.DigestArray.write(stem, [])
    assert url_filter.DigestArray(stem).find(["a"]).tolist() == [-1]


# ---- toxicity ----

def test_seeds_of_documents_with_one_opening():
    rng = random.Random(3)
    words = ["".join(rng.choices("abcdefgh", k=7)) for _ in range(400)]
    head = " ".join(words[:30])
    toxic = [f"{head} {' '.join(rng.choices(words, k=60))} grumblewort {' '.join(rng.choices(words, k=60))}" for _ in range(12)]
    clean = [f"{head} {' '.join(rng.choices(words, k=120))}" for _ in range(60)]
    assert "w=grumblewort" in toxicity.seeds(toxic + clean, [1] * 12 + [0] * 60)
    # one document in twelve nearly equal copies is one document
    one = toxic[0].split()
    same = [" ".join(one[:-1] + [words[i]]) for i in range(12)]
    assert toxicity.copies(same) == [False] + [True] * 11
    assert "w=grumblewort" not in toxicity.seeds(same + clean, [1] * 12 + [0] * 60)


def test_toxicity(spark, odd, none):
    rng = random.Random(9)
    plain = lambda n: [f"w{rng.randrange(400)}" for _ in range(n)]
    docs, labels = [], []
    for i in range(400):
        w = plain(60)
        if i % 4 == 0:
            w[rng.randrange(60)] = rng.choice(["vileword", "nasty!", "Badlybuilt" + rng.choice(["en", "er", "est"])])
        docs.append((i, " ".join(w)))
        labels.append((i, 1, int(i % 4 == 0)))
    df = spark.createDataFrame(docs, "doc_id long, text string")
    rows = toxicity.score(df, spark.createDataFrame(labels, LABELS)).collect()
    held = [r for r in rows if r.held_out]
    assert held and all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows)
    assert sum(r.predicted == int(r.doc_id % 4 == 0) for r in held) >= 0.97 * len(held)
    text = dict(docs)
    spans = [text[r.doc_id][slice(*map(int, r.spans.split(",")[0].split(":")))] for r in held if r.predicted]
    assert all(s.lower().startswith(("vile", "nasty", "badly")) for s in spans)
    assert toxicity.score(odd, spark.createDataFrame(labels, LABELS)).count() == len(ODD)
    assert toxicity.score(odd, spark.createDataFrame([], LABELS)).where("score <> 0").count() == 0
    assert toxicity.score(none, spark.createDataFrame(labels, LABELS)).count() == 0
