"""Language identification by a bidirectional gated recurrent network over bytes.

Two gated recurrent units read a segment of bytes, one from either end; every position gets a
distribution over the languages from both states, and a document gets the mean over all positions of
all its segments.  The network is trained in numpy by backpropagation through time on a bounded
sample of labelled segments; whole texts are labelled in Arrow batches, segments side by side.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sigres.llm.batches import map_text
from sigres.plans.scratch import Scratch, small_side

#: Bytes after which the states start anew, and hidden units of either direction.
SEGMENT, HIDDEN = 64, 12
#: Documents a language gives to training at most, and segments of each; both bound the sample.
SAMPLE_DOCS, SAMPLE_SEGMENTS = 300, 8
STEPS, BATCH, RATE = 260, 128, 0.015
#: Segments that are labelled side by side.
WIDTH = 1024
UNKNOWN = "und"


@dataclass
class Network:
    """Arrays by name, each with one slice per direction where a direction has its own."""

    languages: list[str]
    arrays: dict[str, np.ndarray]


def _fresh(languages: list[str], rng: np.random.Generator, hidden: int = HIDDEN) -> Network:
    n = len(languages)
    draw = lambda *shape: (rng.standard_normal(shape) * 0.3).astype(np.float32)
    # rows of "embed" and "turn": reset gate, update gate, candidate
    return Network(languages, {"embed": draw(2, 3 * hidden, 256), "turn": draw(2, 3 * hidden, hidden),
                               "bias": np.zeros((2, hidden, 1), np.float32), "out": draw(2, n, hidden),
                               "level": np.zeros((n, 1), np.float32)})


def _sigmoid(x: np.ndarray) -> np.ndarray:
    np.multiply(x, 0.5, out=x)
    np.tanh(x, out=x)
    np.multiply(x, 0.5, out=x)
    return np.add(x, 0.5, out=x)


def _states(net: dict, way: int, x: np.ndarray, keep: list | None = None):
    """Yield (position, state) of one direction over x (positions, segments)."""
    embed, turn, bias = net["embed"][way], net["turn"][way], net["bias"][way]
    hidden = bias.shape[0]
    h = np.zeros((hidden, x.shape[1]), np.float32)
    drive, back = np.empty((3 * hidden, x.shape[1]), np.float32), np.empty((3 * hidden, x.shape[1]), np.float32)
    for t in range(len(x)) if way == 0 else range(len(x) - 1, -1, -1):
        np.take(embed, x[t], axis=1, out=drive, mode="clip")
        np.matmul(turn, h, out=back)
        gates = _sigmoid(drive[:2 * hidden] + back[:2 * hidden])
        reset, update = gates[:hidden], gates[hidden:]
        carried = back[2 * hidden:] + bias
        candidate = np.tanh(drive[2 * hidden:] + reset * carried)
        before, h = h, candidate + update * (h - candidate)
        if keep is not None:
            keep.append((t, before, reset, update, candidate, carried))
        yield t, h


def _softmax(x: np.ndarray) -> np.ndarray:
    x = np.exp(x - x.max(0, keepdims=True))
    return x / x.sum(0, keepdims=True)


def position_sums(net: Network, x: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Sum of the distributions of the first ``lengths`` positions of each segment: (languages, segments)."""
    a = net.arrays
    logits = np.empty((len(x), len(net.languages), x.shape[1]), np.float32)
    for t, h in _states(a, 0, x):
        np.matmul(a["out"][0], h, out=logits[t])
    total = np.zeros((len(net.languages), x.shape[1]), np.float64)
    for t, h in _states(a, 1, x):
        total += _softmax(logits[t] + a["out"][1] @ h + a["level"]) * (t < lengths)
    return total


def gradients(net: Network, x: np.ndarray, lengths: np.ndarray, label: np.ndarray) -> tuple[float, dict]:
    """Mean cross-entropy over the labelled positions and its derivatives, by backpropagation through time."""
    a = net.arrays
    g = {k: np.zeros_like(v) for k, v in a.items()}
    tapes: tuple[list, list] = ([], [])
    after = [dict(_states(a, way, x, tapes[way])) for way in (0, 1)]
    truth = np.eye(len(net.languages), dtype=np.float32)[label].T
    count = max(1, int(np.minimum(lengths, len(x)).sum()))
    loss, dlogits = 0.0, {}
    for t in range(len(x)):
        p = _softmax(a["out"][0] @ after[0][t] + a["out"][1] @ after[1][t] + a["level"])
        on = (t < lengths).astype(np.float32)
        loss -= float((np.log((p * truth).sum(0) + 1e-9) * on).sum())
        dlogits[t] = (p - truth) * on / count
        g["level"] += dlogits[t].sum(1, keepdims=True)
    hidden = a["bias"].shape[1]
    hot = np.eye(256, dtype=np.float32)
    for way in (0, 1):
        dh = np.zeros_like(after[way][0])
        for t, before, reset, update, candidate, carried in reversed(tapes[way]):
            g["out"][way] += dlogits[t] @ after[way][t].T
            dh = dh + a["out"][way].T @ dlogits[t]
            dn = dh * (1 - update) * (1 - candidate * candidate)
            dz = dh * (before - candidate) * update * (1 - update)
            dc = dn * reset
            dr = dn * carried * reset * (1 - reset)
            into = np.concatenate([dr, dz, dn])
            through = np.concatenate([dr, dz, dc])
            g["embed"][way] += into @ hot[x[t]]
            g["turn"][way] += through @ before.T
            g["bias"][way] += dc.sum(1, keepdims=True)
            dh = dh * update + a["turn"][way].T @ through
    assert hidden == len(dh)
    return loss / count, g


def train(segments: list[bytes], labels: list[str], steps: int = STEPS, seed: int = 7) -> Network | None:
    """A network from labelled segments of at most ``SEGMENT`` bytes, by Adam; None without segments."""
    if not segments:
        return None
    languages = sorted(set(labels))
    rng = np.random.default_rng(seed)
    net = _fresh(languages, rng)
    data = np.zeros((len(segments), SEGMENT), np.uint8)
    for i, s in enumerate(segments):
        data[i, :len(s)] = np.frombuffer(s, np.uint8)
    lengths = np.array([len(s) for s in segments])
    label = np.array([languages.index(x) for x in labels])
    by = [np.flatnonzero(label == k) for k in range(len(languages))]
    m = {k: np.zeros_like(v) for k, v in net.arrays.items()}
    v = {k: np.zeros_like(x) for k, x in net.arrays.items()}
    for step in range(1, steps + 1):
        # as many segments of each language, whatever their share of the sample
        pick = np.concatenate([rng.choice(k, -(-BATCH // len(by))) for k in by])
        _, g = gradients(net, np.ascontiguousarray(data[pick].T), lengths[pick], label[pick])
        scale = min(1.0, 1.0 / (np.sqrt(sum(float((x * x).sum()) for x in g.values())) + 1e-9))
        rate = RATE * (1 - step / (steps + 1)) * np.sqrt(1 - 0.999**step) / (1 - 0.9**step)
        for k, x in g.items():
            m[k] = 0.9 * m[k] + 0.1 * scale * x
            v[k] = 0.999 * v[k] + 0.001 * (scale * x) ** 2
            net.arrays[k] -= (rate * m[k] / (np.sqrt(v[k]) + 1e-8)).astype(np.float32)
    return net


def _cut(text: str) -> list[bytes]:
    """All consecutive segments of a text."""
    data = text.encode("utf-8", "replace")
    return [data[i:i + SEGMENT] for i in range(0, len(data), SEGMENT)]


def sample(docs: DataFrame, docs_each: int = SAMPLE_DOCS, segments_each: int = SAMPLE_SEGMENTS) -> tuple[list[bytes], list[str]]:
    """Labelled segments: the ``docs_each`` different texts of each language with the smallest hashes, and of
    each ``segments_each`` segments evenly spread over the whole text.

    Equal texts count once, whatever their number, and texts are cut before they are sorted, so at most
    ``docs_each`` documents and ``segments_each`` segments of each a language reach the driver.
    """
    known = docs.where("lang is not null and text is not null")
    rank = F.struct(F.xxhash64("text").alias("h"), F.xxhash64(F.lit(1), "text").alias("i"))
    different = known.select("lang", rank.alias("r")).distinct()
    place = F.row_number().over(Window.partitionBy("lang").orderBy("r"))  # Spark limits each task to so many before the shuffle
    chosen = different.withColumn("n", place).where(F.col("n") <= docs_each).drop("n")
    chosen = Scratch(docs.sparkSession, "language").save(chosen, "sample")
    texts = known.select("lang", "text", rank.alias("r")).join(small_side(chosen, SAMPLE_DOCS * 1000), ["lang", "r"])

    def run(piece: pa.RecordBatch) -> dict:
        out: dict[str, list] = {"lang": [], "n": [], "segment": []}
        for lang, text in set(zip(piece.column("lang").to_pylist(), piece.column("text").to_pylist())):
            cuts = _cut(text)
            for i in np.unique(np.linspace(0, len(cuts) - 1, segments_each).astype(int)) if cuts else ():
                out["lang"].append(lang)
                out["n"].append(i)
                out["segment"].append(cuts[i])
        return out

    # a text that several tasks have gives the same segments, which are one
    rows = map_text(texts.select("lang", "text"), run, "lang string, n long, segment binary").groupBy("lang", "n", "segment").agg(F.lit(1).alias("one"))
    rows = sorted((r.lang, bytes(r.segment)) for r in rows.collect())
    return [r[1] for r in rows], [r[0] for r in rows]


def has_letter(text: str) -> bool:
    """Whether a character is a letter of Unicode; signs such as a fraction or a circled or Roman number are none."""
    return any(map(str.isalpha, text))


def label_texts(net: Network, texts: list[str | None]) -> tuple[list[str], list[float]]:
    """Language and mean probability of each text."""
    data = [t.encode("utf-8", "replace") if t and has_letter(t) else b"" for t in texts]
    pieces = [-(-len(d) // SEGMENT) for d in data]
    flat = np.frombuffer(b"".join(d.ljust(n * SEGMENT, b"\0") for d, n in zip(data, pieces)), np.uint8).reshape(-1, SEGMENT)
    lengths = np.full(len(flat), SEGMENT)
    ends = np.cumsum(pieces)
    for d, n, end in zip(data, pieces, ends):
        if n:
            lengths[end - 1] = len(d) - (n - 1) * SEGMENT
    sums = np.zeros((len(net.languages), len(flat)))
    for at in range(0, len(flat), WIDTH):
        sums[:, at:at + WIDTH] = position_sums(net, np.ascontiguousarray(flat[at:at + WIDTH].T), lengths[at:at + WIDTH])
    langs, scores = [], []
    for d, n, end in zip(data, pieces, ends):
        if not n:
            langs.append(UNKNOWN)
            scores.append(0.0)
            continue
        p = sums[:, end - n:end].sum(1) / len(d)
        langs.append(net.languages[int(p.argmax())])
        scores.append(float(min(1.0, p.max())))
    return langs, scores


def identify(docs: DataFrame, train_on=None, docs_each: int = SAMPLE_DOCS) -> DataFrame:
    """One row per row of ``docs`` (doc_id, text, lang): doc_id, held_out, lang_pred, score.

    The network learns from rows with text and lang that ``train_on`` selects (default: the CRC-32 of
    doc_id as text is not 1 modulo 3).  Null texts and texts without a letter are ``und`` with score 0,
    as are all texts if there is nothing to learn from.  Rows without a doc_id are not learned from and
    not held out.  Repeated rows are labelled each; an empty table gives an empty result.
    """
    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False))
    usable = F.col("doc_id").isNotNull() & ~held_out if train_on is None else train_on
    net = train(*sample(docs.select("doc_id", "text", "lang").where(usable), docs_each))
    if net is None:
        return docs.select("doc_id", held_out.alias("held_out"), F.lit(UNKNOWN).alias("lang_pred"), F.lit(0.0).alias("score"))
    shared = docs.sparkSession.sparkContext.broadcast(net)

    def run(part: pa.RecordBatch) -> dict:
        langs, scores = label_texts(shared.value, part.column("text").to_pylist())
        return {"doc_id": part.column("doc_id"), "lang_pred": langs, "score": scores}

    out = map_text(docs.select("doc_id", "text"), run, "doc_id long, lang_pred string, score double")
    return out.select("doc_id", held_out.alias("held_out"), "lang_pred", "score")
