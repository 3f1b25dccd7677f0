"""Quality classifier: an interpolated modified Kneser-Ney model over characters of trusted text.

Every character of the trusted text is a symbol of its own, whatever the script, and every run of four
counts, so the model grows with that text.  Each worker emits counts per slice, which are summed by n-gram;
lower orders count the distinct continuations of the order above.  Probabilities are made by joins of
the count tables: each order's counts with the totals of its contexts and with the next lower order.

For scoring, the two higher orders are cut into shards of bounded size by the last two symbols of the
context, so all that a position needs of them is in one shard.  A shard is joined with the corpus by
broadcasting its sorted keys and looking every position's n-gram up, so no text is shuffled; with several
shards the corpus is read once for each.  Log-probabilities are whole multiples of 2^-20, so their sums do
not depend on the order of rows.  Documents get a perplexity, and languages get thresholds from the
quantiles of their trusted documents.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sigres.llm.batches import map_text, row_counter
from sigres.plans.scratch import Scratch, small_side

#: Bits of a symbol: 0 stands for characters that trusted text does not have, 1 for the beginning of a text.
BITS = 21
#: N-grams of order four in a shard (12 bytes each, and what belongs to them of order three).
SHARD_GRAMS = 3_000_000
#: Quantile of trusted documents' perplexity at which a language's threshold stands, and the factor
#: allowed above it.
QUANTILE, MARGIN = 0.995, 1.05
#: Characters at the average rate that every document is given, so that short texts are not extreme.
PRIOR_CHARS = 40
#: Trusted documents that a language needs for a threshold of its own.
LEAST_TRUSTED = 50
#: Steps of a perplexity's logarithm that quantiles are counted in: 0.05% each.
GRID = 2000
#: Steps of a log-probability.
STEP = 1 << 20
#: Slots of a worker's memory of n-grams that it has looked up.
SLOTS = 1 << 20
#: Labelled ids up to which their table is broadcast.
BROADCAST_LABELS = 1_000_000
_MIX, _SPREAD = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)


def code_points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32)


def _symbols(texts: list[str | None], points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Symbols of all texts, each with three beginnings before it, and where each text begins.

    The i-th of the sorted ``points`` is symbol i + 2.
    """
    table = np.zeros(0x110001, np.int64)
    table[points] = np.arange(2, len(points) + 2)
    return _encode(texts, table)


def _encode(texts: list[str | None], table: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    cuts = [code_points(t or "") for t in texts]
    ends = np.cumsum([0] + [len(p) + 3 for p in cuts])
    out = np.ones(ends[-1], np.int64)
    for p, at in zip(cuts, ends):
        out[at + 3:at + 3 + len(p)] = table[p]
    return out, ends


def character_counts(docs: DataFrame) -> DataFrame:
    """(point, n) over all texts."""
    def run(part: pa.RecordBatch) -> dict:
        points = np.concatenate([code_points(t or "") for t in part.column("text").to_pylist()] + [np.zeros(0, np.uint32)])
        found, n = np.unique(points, return_counts=True)
        return {"point": found.astype(np.int64), "n": n.astype(np.int64)}

    return map_text(docs.select("text"), run, "point long, n long").groupBy("point").agg(F.sum("n").alias("n"))


def ngram_counts(docs: DataFrame, points: np.ndarray) -> DataFrame:
    """(c, w, n): counts of all runs of four symbols, the first three packed into c."""
    shared = docs.sparkSession.sparkContext.broadcast(points)

    def run(part: pa.RecordBatch) -> dict:
        s, ends = _symbols(part.column("text").to_pylist(), shared.value)
        if len(s) < 4:
            return {"c": [], "w": [], "n": []}
        own, local = np.unique(s, return_inverse=True)
        inside = np.ones(len(s) - 3, bool)
        for k in (1, 2, 3):  # runs that reach into the next text
            inside[ends[1:-1] - k] = False
        runs = [local[k:len(s) - 3 + k][inside] for k in range(4)]
        if len(own) < 50_000:  # four symbols of this slice are one number
            code = ((runs[0] * len(own) + runs[1]) * len(own) + runs[2]) * len(own) + runs[3]
            found, n = np.unique(code, return_counts=True)
            parts = [found // len(own) ** (3 - k) % len(own) for k in range(4)]
        else:
            found, n = np.unique(np.stack(runs, 1), axis=0, return_counts=True)
            parts = [found[:, k] for k in range(4)]
        a, b, c, w = (own[p] for p in parts)
        return {"c": ((a << BITS) | b) << BITS | c, "w": w, "n": n.astype(np.int64)}

    return map_text(docs.select("text"), run, "c long, w long, n long").groupBy("c", "w").agg(F.sum("n").alias("n"))


def discounts(of: dict[int, int]) -> list[float]:
    """The three discounts of modified Kneser-Ney from the counts of counts 1 to 4."""
    n = [max(1, of.get(k, 0)) for k in (1, 2, 3, 4)]
    y = n[0] / (n[0] + 2 * n[1])
    d = [k - (k + 1) * y * n[k] / n[k - 1] for k in (1, 2, 3)]
    return [min(max(x, 0.05), k - 0.05) for k, x in enumerate(d, 1)]


def counts_of_counts(table: DataFrame) -> dict[int, int]:
    rows = table.where(F.col("n") <= 4).groupBy("n").count().collect()
    return {r[0]: r[1] for r in rows}


def _shorter(c: Column, order: int) -> Column:
    """The context of the next lower order: the first of ``order`` - 1 symbols goes."""
    return c.bitwiseAND(F.lit((1 << BITS * (order - 2)) - 1))


def probabilities(counts: DataFrame, order: int, lower: DataFrame | None, symbols: int, scratch: Scratch) -> tuple[DataFrame, DataFrame]:
    """Counts (c, w, n) and the next lower order's (c, w, p) -> (c, w, p), and (c, spare): what a context leaves to unseen symbols."""
    d = discounts(counts_of_counts(counts))
    cut = F.element_at(F.array(*[F.lit(x) for x in d]), F.least("n", F.lit(3)).cast("int"))
    # whole numbers are summed, so the sums do not depend on the order of rows
    many = [F.count_if(F.col("n") == 1), F.count_if(F.col("n") == 2), F.count_if(F.col("n") >= 3)]
    totals = counts.groupBy("c").agg(F.sum("n").alias("total"), *[m.alias(f"m{k}") for k, m in enumerate(many)])
    spare = sum((F.col(f"m{k}") * F.lit(x) for k, x in enumerate(d)), F.lit(0.0)) / F.col("total")
    totals = scratch.save(totals.select("c", "total", spare.alias("spare")), f"contexts{order}")
    rows = counts.join(totals, "c")
    if lower is None:
        below = F.lit(1.0 / symbols)
    else:
        low = lower.select(F.col("c").alias("b"), "w", F.col("p").alias("below"))
        rows, below = rows.withColumn("b", _shorter(F.col("c"), order)).join(low, ["b", "w"]), F.col("below")
    p = (F.col("n") - cut) / F.col("total") + F.col("spare") * below
    return scratch.save(rows.select("c", "w", p.alias("p")), f"order{order}"), totals.select("c", "spare")


def _find(keys: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of ``wanted`` in sorted ``keys``, and whether they are there."""
    if not len(keys):
        return np.zeros(len(wanted), np.int64), np.zeros(len(wanted), bool)
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return at, keys[at] == wanted


def _keyed(rows: DataFrame, key: Column, value: str) -> tuple[np.ndarray, np.ndarray]:
    """Sorted keys and the logarithms of their values, from a table of bounded size."""
    got = rows.select(key.alias("key"), F.col(value).alias("value")).toArrow()
    keys, values = got.column("key").to_numpy(), got.column("value").to_numpy()
    order = np.argsort(keys, kind="stable")
    return keys[order], np.log(values[order]).astype(np.float32)


@dataclass
class Base:
    """The symbols and the two lower orders: log p of each symbol, of pairs by key, and what contexts of one symbol leave."""

    points: np.ndarray
    one: np.ndarray
    two: tuple[np.ndarray, np.ndarray]
    left: np.ndarray

    def log_p(self, c: np.ndarray, w: np.ndarray) -> np.ndarray:
        at, there = _find(self.two[0], (c << BITS) | w)
        return np.where(there, self.two[1][at] if len(self.two[1]) else 0.0, self.left[c] + self.one[w])


@dataclass
class Shard:
    """Sorted keys with logarithms: contexts of two symbols, runs of three, contexts of three, runs of four (by the context's place)."""

    left3: tuple[np.ndarray, np.ndarray]
    three: tuple[np.ndarray, np.ndarray]
    left4: tuple[np.ndarray, np.ndarray]
    four: tuple[np.ndarray, np.ndarray]

    def log_p(self, base: Base, c: np.ndarray, w: np.ndarray) -> np.ndarray:
        """Of symbols w after contexts c of three symbols; the longest order that has the run decides."""
        pick = lambda table, at: table[1][at] if len(table[1]) else np.zeros(len(at), np.float32)
        out = base.log_p(c & ((1 << BITS) - 1), w)
        c2 = c & ((1 << 2 * BITS) - 1)
        at, there = _find(self.left3[0], c2)
        out = out + np.where(there, pick(self.left3, at), 0.0)
        at, there = _find(self.three[0], (c2 << BITS) | w)
        out = np.where(there, pick(self.three, at), out)
        ctx, seen = _find(self.left4[0], c)
        out = out + np.where(seen, pick(self.left4, ctx), 0.0)
        at, there = _find(self.four[0], (ctx << BITS) | w)
        return np.where(there & seen, pick(self.four, at), out)


def _shard_of(c2, shards: int):
    """Shard of a context's last two symbols; the same in numpy and in Spark, and without overflow."""
    mixed = c2 * 1_000_003
    return (F.shiftright(mixed, 17) if isinstance(c2, Column) else mixed >> 17) % shards


@dataclass
class Model:
    """The lower orders on the driver, the higher ones as tables with their contexts' last two symbols ``c2``."""

    base: Base
    three: DataFrame
    left3: DataFrame
    four: DataFrame
    left4: DataFrame
    shards: int

    def shard(self, k: int) -> Shard:
        mine = lambda df: df.where(_shard_of(F.col("c2"), self.shards) == k)
        left4 = _keyed(mine(self.left4), F.col("c"), "spare")
        got = mine(self.four).select("c", "w", "p").toArrow()
        key = (np.searchsorted(left4[0], got.column("c").to_numpy()).astype(np.int64) << BITS) | got.column("w").to_numpy()
        order = np.argsort(key, kind="stable")
        four = key[order], np.log(got.column("p").to_numpy()[order]).astype(np.float32)
        three = _keyed(mine(self.three), F.shiftleft("c", BITS).bitwiseOR(F.col("w")), "p")
        return Shard(_keyed(mine(self.left3), F.col("c"), "spare"), three, left4, four)


def train(trusted: DataFrame, scratch: Scratch, shard_grams: int = SHARD_GRAMS) -> Model | None:
    """A model of all trusted texts, or None if they hold no character."""
    letters = scratch.save(character_counts(trusted), "characters")
    # at most one row for each of Unicode's code points
    points = np.sort(letters.select("point").toArrow().column("point").to_numpy())
    if not len(points):
        return None
    symbols = len(points) + 2
    counts = {4: scratch.save(ngram_counts(trusted, points), "grams4")}
    for k in (3, 2, 1):  # distinct left continuations of the order above
        counts[k] = scratch.save(counts[k + 1].groupBy(_shorter(F.col("c"), k + 1).alias("c"), "w").agg(F.count("*").alias("n")), f"grams{k}")
    p, spare = {}, {}
    for k in (1, 2, 3, 4):
        p[k], spare[k] = probabilities(counts[k], k, p.get(k - 1), symbols, scratch)
    free = spare[1].first().spare
    one, left = np.full(symbols, free / symbols), np.ones(symbols)
    got = p[1].toArrow()
    one[got.column("w").to_numpy()] = got.column("p").to_numpy()
    got = spare[2].toArrow()
    left[got.column("c").to_numpy()] = got.column("spare").to_numpy()
    two = _keyed(p[2], F.shiftleft("c", BITS).bitwiseOR(F.col("w")), "p")
    base = Base(points, np.log(one).astype(np.float32), two, np.log(left).astype(np.float32))
    last = lambda df, order: df.withColumn("c2", F.col("c") if order == 3 else _shorter(F.col("c"), 4))
    return Model(base, last(p[3], 3), last(spare[3], 3), last(p[4], 4), last(spare[4], 4), max(1, -(-p[4].count() // shard_grams)))


def _lookup(base: Base) -> tuple[list[int], np.ndarray, np.ndarray, np.ndarray]:
    """State of a task: its row counter, the symbol of each code point, and the n-grams it has looked up with their values."""
    table = np.zeros(0x110001, np.int64)
    table[base.points] = np.arange(2, len(base.points) + 2)
    known = np.zeros(SLOTS, np.uint64)
    known[0] = 1  # no n-gram of slot 0 has this number
    return row_counter(), table, known, np.zeros(SLOTS, np.int64)


def score(docs: DataFrame, model: Model, scratch: Scratch) -> DataFrame:
    """(doc_id, lang, text) -> (doc_id, lang, n_chars, nll in steps): one pass per shard, sums added up."""
    spark = docs.sparkSession.sparkContext
    base, shards = spark.broadcast(model.base), model.shards
    out = None
    for k in range(shards):
        rows = spark.broadcast(model.shard(k))

        def run(part: pa.RecordBatch, state, k=k, rows=rows) -> dict:
            counter, table, known, values = state
            s, ends = _encode(part.column("text").to_pylist(), table)
            n = np.diff(ends) - 3
            cost = np.zeros(len(s), np.int64)
            if len(s) > 3:
                number = s[:-3].astype(np.uint64)
                for j in (1, 2, 3):
                    number = number * _MIX + s[j:len(s) - 3 + j].astype(np.uint64)
                slot = ((number * _SPREAD) >> np.uint64(44)).astype(np.int64)
                found, new = values[slot], known[slot] != number
                if shards > 1:
                    ours = _shard_of((s[1:-2] << BITS) | s[2:-1], shards) == k
                    found, new = np.where(ours, found, 0), new & ours
                at = np.flatnonzero(new)
                if len(at):
                    own, first, back = np.unique(number[at], return_index=True, return_inverse=True)
                    first = at[first]
                    c = (((s[first] << BITS) | s[first + 1]) << BITS) | s[first + 2]
                    steps = np.rint(-rows.value.log_p(base.value, c, s[first + 3]).astype(np.float64) * STEP).astype(np.int64)
                    found[at] = steps[back]
                    known[slot[first]], values[slot[first]] = own, steps
                cost[3:] = found
            for j in (0, 1, 2):
                cost[ends[:-1] + j] = 0
            total = np.add.reduceat(cost, ends[:-1]) if len(n) else np.zeros(0, np.int64)
            counter[0] += len(n)
            return {"doc_id": part.column("doc_id"), "lang": part.column("lang"), "n_chars": n, "nll": total,
                    "row": np.arange(counter[0] - len(n), counter[0])}

        got = map_text(docs.select("doc_id", "lang", "text"), run, "doc_id long, lang string, n_chars long, nll long, row long", setup=lambda: _lookup(base.value))
        # each pass is a job of its own, so that its tasks number their rows alike
        got = scratch.save(got, "pass")
        rows.unpersist()
        out = got if out is None else out.unionByName(got)
    if shards > 1:
        out = out.groupBy("doc_id", "lang", "n_chars", "row").agg(F.sum("nll").alias("nll"))
        out = scratch.save(out, "scores")
    return out.drop("row")


def quantiles(bins: DataFrame, keys: list[str], quantile: float) -> DataFrame:
    """Counts (keys, bin, n) of logarithms on the grid -> (keys, total, q): the upper end of the bin
    that the quantile is in.  Unlike a sketch it does not depend on the order of the rows.
    """
    per = bins.groupBy(*keys, "bin").agg(F.sum("n").alias("n"))
    group = Window.partitionBy(*keys)
    upto = F.sum("n").over(group.orderBy("bin").rowsBetween(Window.unboundedPreceding, 0))
    reached = per.select(*keys, "bin", upto.alias("upto"), F.sum("n").over(group).alias("total")).where(F.col("upto") >= F.lit(quantile) * F.col("total"))
    found = reached.groupBy(*keys, "total").agg(F.min("bin").alias("bin"))
    return found.select(*keys, "total", F.exp((F.col("bin") + 1) / F.lit(float(GRID))).alias("q"))


def classify(docs: DataFrame, labels: DataFrame, quantile: float = QUANTILE, margin: float = MARGIN,
             shard_grams: int = SHARD_GRAMS, broadcast_labels: int = BROADCAST_LABELS) -> DataFrame:
    """One row per row of ``docs``: doc_id, lang, n_chars, perplexity, threshold, keep.

    Trusted documents are those whose id has quality 1 in ``labels``.  The perplexity is per
    character, with ``PRIOR_CHARS`` characters at the trusted average added to every document.  A
    document is kept if its perplexity is at most its language's threshold: ``margin`` times the
    ``quantile`` of the language's trusted documents, or of all trusted ones where the language is
    null or has too few.  Null and empty texts have the average perplexity and are kept.  Without
    trusted text everything is kept and perplexity and threshold are null.  Repeated rows are judged
    each; an empty table gives an empty result.
    """
    scratch = Scratch(docs.sparkSession, "quality")
    rows = docs.select("doc_id", "lang", "text")
    ids = scratch.save(labels.where("quality = 1 and doc_id is not null").select("doc_id").distinct(), "trusted")
    model = train(rows.join(small_side(ids, broadcast_labels), "doc_id", "left_semi"), scratch, shard_grams)
    if model is None:
        none = F.lit(None).cast("double")
        return rows.select("doc_id", "lang", F.coalesce(F.length("text"), F.lit(0)).cast("long").alias("n_chars"),
                           none.alias("perplexity"), none.alias("threshold"), F.lit(True).alias("keep"))
    scores = score(rows, model, scratch)
    known = scratch.save(scores.join(small_side(ids, broadcast_labels), "doc_id", "left_semi"), "known")
    mean = known.agg(F.sum("nll") / F.greatest(F.sum("n_chars"), F.lit(1))).first()[0] or 0.0
    rate = F.exp((F.col("nll") / F.lit(float(STEP)) + mean / STEP * PRIOR_CHARS) / (F.col("n_chars") + PRIOR_CHARS))
    bins = scratch.save(known.groupBy("lang", F.floor(F.log(rate) * GRID).alias("bin")).agg(F.count("*").alias("n")), "bins")
    whole = quantiles(bins, [], quantile).first()
    general = whole.q * margin if whole else float("inf")
    own = scratch.save(quantiles(bins, ["lang"], quantile).where(F.col("lang").isNotNull() & (F.col("total") >= LEAST_TRUSTED))
                       .select("lang", (F.col("q") * margin).alias("own")), "thresholds")
    judged = (scores.join(small_side(own, broadcast_labels // 10), "lang", "left")
              .withColumn("perplexity", rate).withColumn("threshold", F.coalesce("own", F.lit(general))))
    return judged.select("doc_id", "lang", "n_chars", "perplexity", "threshold",
                         (F.col("perplexity") <= F.col("threshold")).alias("keep"))


def keep_good(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """The rows of ``docs`` that are kept, with all their columns, whatever their names; rows without a doc_id stay.

    Of rows that repeat a doc_id all go if one is rejected.
    """
    scratch = Scratch(docs.sparkSession, "good")
    bad = classify(docs, labels, **options).where("not keep and doc_id is not null").select("doc_id").distinct()
    bad = small_side(scratch.save(bad, "bad"), BROADCAST_LABELS).alias("rejected")
    return docs.alias("judged").join(bad, F.col("judged.doc_id") == F.col("rejected.doc_id"), "left_anti")
