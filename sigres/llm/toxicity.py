"""Toxicity: a linear-chain conditional random field tags toxic words; marginals give document scores.

Labels exist for documents only.  From a bounded sample of labelled documents, words and word
beginnings that many toxic documents and almost no others have become seeds; a word of a toxic
document that has a seed is labelled toxic.  The field learns from lines labelled so.  Forward-backward
marginals of all words of a text (lines are
cut into sequences of at most 128 words) give the text's largest and summed probability, which a logistic
curve, fitted on the same sample, turns into the score.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sigres.llm import crf
from sigres.llm.batches import map_text
from sigres.llm.simhash import NEAR_JACCARD, NEAR_SHINGLE, shingle_hashes, words_of
from sigres.plans.scratch import Scratch, small_side

#: Toxic and other documents that are learned from, at most.
SAMPLE_TOXIC, SAMPLE_OTHER = 1000, 2000
#: A seed is in at least so many different toxic documents, in such a share of them, and is so many
#: times as frequent in them as in others.
SEED_DOCS, SEED_SHARE, SEED_RATIO = 4, 0.01, 60.0
#: Words of lines of either kind that the field learns from, and words of one sequence at most.
WORDS, SEQUENCE = 25_000, 128
_EDGE = "\"'.,;:!?()[]#$%&*|"
_LETTERS = re.compile(r"[^\W_]+")
_TAGGED = 0.5


def stem(word: str) -> str:
    return word.strip(_EDGE).lower()


def describe(word: str) -> list[str]:
    """Features: the word without edge signs, in lower case, and its beginnings."""
    w = stem(word)
    return ["bias", f"w={w}", *(f"p{n}={w[:n]}" for n in (4, 5, 6) if len(w) >= n)]


def _marks(word: str) -> list[str]:
    """What may be a seed: the word, or five or six letters that it begins with."""
    return [f"w={word}", *(f"p{n}={word[:n]}" for n in (5, 6) if len(word) > n)]


def copies(texts: list[str], least: float = NEAR_JACCARD) -> list[bool]:
    """Whether a text repeats an earlier one that is no copy: all letters agree, or the shingle sets by ``least``.

    Of two such sets some of the rarest shingles are common, so only those are looked up.
    """
    sets = [np.unique(shingle_hashes(words_of(t), NEAR_SHINGLE)).tolist() for t in texts]
    often = Counter(h for s in sets for h in s)
    have, rare, out = set(), {}, []
    for i, (text, hashes) in enumerate(zip(texts, sets)):
        letters = "".join(_LETTERS.findall(text.lower()))
        first = sorted(hashes, key=lambda h: (often[h], h))[:len(hashes) - math.ceil(least * len(hashes)) + 1]
        found, mine = letters in have, set(hashes)
        for j in () if found else {j for h in first for j in rare.get(h, ())}:
            shared = len(mine.intersection(sets[j]))
            if shared >= least * (len(mine) + len(sets[j]) - shared):
                found = True
                break
        if not found:
            have.add(letters)
            for h in first:
                rare.setdefault(h, []).append(i)
        out.append(found)
    return out


def seeds(texts: list[str], toxic: list[int]) -> set[str]:
    """Marks that are frequent in toxic documents and rare in others."""
    have: tuple[Counter, Counter] = (Counter(), Counter())
    after: dict[str, set[str]] = {}  # words before a mark: few, if a passage that documents share has it
    n = [0, 0]
    again: list[Iterator[bool]] = [iter(copies([t for t, y in zip(texts, toxic) if y == side])) for side in (0, 1)]
    for text, y in zip(texts, toxic):
        if next(again[y]):  # copies count once
            continue
        n[y] += 1
        stems = [stem(x) for x in text.split()]
        have[y].update({m for w in set(stems) if len(w) >= 3 for m in _marks(w)})
        if y:
            for before, w in zip(["", *stems], stems):
                for m in _marks(w) if len(w) >= 3 else ():
                    after.setdefault(m, set()).add(before)
    n = [max(1, k) for k in n]
    return {m for m, k in have[1].items()
            if k >= max(SEED_DOCS, SEED_SHARE * n[1]) and len(after[m]) >= k / 2 and (k / n[1]) / ((have[0][m] + 0.2) / n[0]) >= SEED_RATIO}


def _cut(words: list[str]) -> list[list[str]]:
    return [words[i:i + SEQUENCE] for i in range(0, len(words), SEQUENCE)]


@dataclass
class Model:
    field: crf.LinearChain
    curve: np.ndarray

    def scores(self, most: np.ndarray, total: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-(summary(most, total) @ self.curve)))


def summary(most: np.ndarray, total: np.ndarray) -> np.ndarray:
    """Inputs of the curve: log-odds of the largest marginal and the log of their sum."""
    p = np.clip(most, 1e-4, 1 - 1e-4)
    return np.stack([np.ones_like(p), np.log(p / (1 - p)), np.log(total + 1e-2)], 1)


def fit_curve(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, rounds: int = 40) -> np.ndarray:
    """Logistic regression by Newton steps."""
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        h = (x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w))
        w = w - np.linalg.solve(h, x.T @ (p - y) + ridge * w)
    return w


def train(texts: list[str], toxic: list[int], rounds: int = 60, words_each: int = WORDS, seed: int = 5) -> Model | None:
    """A model from documents and their labels; None unless both labels occur."""
    if len(set(toxic)) < 2:
        return None
    # every third document is kept for the curve: marginals of texts that the field knows are too sharp
    known = [i for i in range(len(texts)) if i % 3] if len(texts) >= 300 else list(range(len(texts)))
    marks = seeds([texts[i] for i in known], [toxic[i] for i in known])
    rows: tuple[list, list] = ([], [])
    for text, y in ((texts[i], toxic[i]) for i in known):
        for words in (w for line in text.split("\n") for w in _cut(line.split())):
            tags = ["toxic" if y and any(m in marks for m in _marks(stem(w))) else "clean" for w in words]
            rows["toxic" in tags].append((words, tags))
    rng, chosen = np.random.default_rng(seed), []
    for side in rows:
        room = words_each
        for i in rng.permutation(len(side)):
            if room > 0:
                chosen.append(side[i])
                room -= len(side[i][0])
    field = crf.train(chosen, describe, ["clean", "toxic"], rounds=rounds, rate=0.2, ridge=1e-4)
    # what has no weight to speak of is forgotten, so that most words share a class
    kept = [f for f, i in field.features.items() if np.abs(field.weights[i]).max() > 0.1]
    field.weights = np.concatenate([field.weights[[field.features[f] for f in kept]], np.zeros((0, 3, 2))])
    field.features = {f: i for i, f in enumerate(kept)}
    rest = sorted(set(range(len(texts))) - set(known)) or known
    most, total, _ = Scorer(Model(field, np.zeros(3))).marginals([texts[i] for i in rest])
    return Model(field, fit_curve(summary(most, total), np.array([toxic[i] for i in rest], float)))


class Scorer:
    """Scores texts with a model; remembers the classes of words."""

    def __init__(self, model: Model):
        self.model = model
        known = model.field.features

        def key(word: str) -> str:
            w = stem(word)
            return w if len(w) <= 6 or f"w={w}" in known else w[:6] + "\0"

        self.classes = crf.TokenClasses(model.field, describe, key)

    def marginals(self, texts: list[str | None]):
        """Largest and summed probability of each text, and its tagged spans (start, end)."""
        lines, where = [], []
        for i, text in enumerate(texts):
            at = 0
            for line in (text or "").split("\n"):
                words = line.split()
                if words:
                    lines.append(words)
                    where.append((i, at, line))
                at += len(line) + 1
        most, total = np.zeros(len(texts)), np.zeros(len(texts))
        spans: list[list[tuple[int, int]]] = [[] for _ in texts]
        if not lines:
            return most, total, spans
        cls = self.classes.numbers([w for words in lines for w in words])
        lengths = np.array([len(w) for w in lines])
        chain = crf.Chain([min(SEQUENCE, n - i) for n in lengths for i in range(0, n, SEQUENCE)])
        field = self.model.field
        p = field.marginals(field.emissions(self.classes.rows, cls, chain), chain)[:, 1]
        ends = np.cumsum(lengths)
        text_of = np.array([w[0] for w in where])
        np.maximum.at(most, text_of, np.maximum.reduceat(p, ends - lengths))
        np.add.at(total, text_of, np.add.reduceat(p, ends - lengths))
        tagged = np.flatnonzero(p >= _TAGGED)
        for k in np.unique(np.searchsorted(ends, tagged, side="right")):
            i, at, line = where[k]
            row = p[ends[k] - lengths[k]:ends[k]]
            for word, q in zip(re.finditer(r"\S+", line), row):
                if q >= _TAGGED:
                    core = _LETTERS.search(word[0])
                    a = word.start() + (core.start() if core else 0)
                    spans[i].append((at + a, at + (word.start() + core.end() if core else word.end())))
        return most, total, spans


def sample(docs: DataFrame, labels: DataFrame, usable, toxic: int = SAMPLE_TOXIC, other: int = SAMPLE_OTHER) -> tuple[list[str], list[int]]:
    """Texts and labels of the documents of either kind with the smallest hashes of their id, so many at most.

    A document with both labels counts as toxic; of rows that repeat an id the smallest text counts.
    """
    known = labels.where("doc_id is not null and toxic in (0, 1)").where(usable).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    place = F.row_number().over(Window.partitionBy("toxic").orderBy(F.xxhash64("doc_id"), "doc_id"))  # limited in each task before the shuffle
    most = F.when(F.col("toxic") == 1, F.lit(toxic)).otherwise(F.lit(other))
    chosen = known.withColumn("n", place).where((F.col("n") <= max(toxic, other)) & (F.col("n") <= most)).select("doc_id", "toxic")
    chosen = small_side(Scratch(docs.sparkSession, "toxic").save(chosen, "sample"), 1_000_000)
    rows = docs.select("doc_id", "text").where("text is not null").join(chosen, "doc_id").groupBy("doc_id", "toxic").agg(F.min("text").alias("text")).collect()
    rows.sort(key=lambda r: (r.doc_id, r.text))
    return [r.text for r in rows], [int(r.toxic) for r in rows]


def score(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """One row per row of ``docs`` (doc_id, text): doc_id, held_out, score, predicted, spans.

    Labels of rows whose CRC-32 of doc_id as text is 0 modulo 5 are held out; rows without a doc_id
    are not held out and not learned from.  ``spans`` lists the words with a marginal of 0.5 or more
    as start:end in code points.  Null and empty texts have marginals 0 and the score that the curve
    gives them.  If not both labels can be learned from, every score is 0.  Repeated rows are scored
    each; an empty table gives an empty result.
    """
    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False))
    model = train(*sample(docs, labels, ~held_out))
    if model is None:
        return docs.select("doc_id", held_out.alias("held_out"), F.lit(0.0).alias("score"), F.lit(0).alias("predicted"), F.lit("").alias("spans"))
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(part: pa.RecordBatch, scorer: Scorer) -> dict:
        most, total, spans = scorer.marginals(part.column("text").to_pylist())
        return {"doc_id": part.column("doc_id"), "score": scorer.model.scores(most, total),
                "spans": [",".join(f"{a}:{b}" for a, b in s) for s in spans]}

    out = map_text(docs.select("doc_id", "text"), run, "doc_id long, score double, spans string", setup=lambda: Scorer(shared.value))
    return out.select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "spans")
