"""SimHash near-duplicates through deletion-variant signatures.

A fingerprint is cut into few segments.  If two fingerprints are close, one segment differs by at
most one bit, so both emit the same variant of it: the segment with one bit made a wildcard.
Variants meet in an equality join on (segment, wildcard position, remaining bits) and every pair
that is kept is verified by its whole fingerprint.

Two settings are used.
* ``linked_components``: 64 bits in two segments of 32.  Of three differing bits one segment has at
  most one, so all links at distance 3 or less are found: the index is exact.
* ``near_duplicates``: five-word shingles, Jaccard 0.8 or more.  Such texts differ in about 15% of the
  bits, too many for an exact index, so 18 segments of 20 bits are taken from six independent
  fingerprints of the distinct shingles; a pair at Jaccard 0.8 / 0.85 / 0.9 shares a variant with
  probability 0.966 / 0.994 / 0.9998.  A seventh fingerprint filters and the shingle sets decide.

Skew: copies collapse to one fingerprint before anything is emitted.  A bucket of one variant is a
run of sorted rows that a worker streams; of a large bucket a minimum spanning forest of close
fingerprints leaves the worker, not all pairs.  In the exact setting, where closeness decides, a
run that passes ``RUN`` rows is not held but sent on with more of its bits known; at the third level a
bucket cannot have more than 2,048 different fingerprints.  In the other setting a run above ``RUN`` rows
is dealt anew as pairs of blocks.  There shingle sets decide, so a forest only gathers candidates: classes
of linked texts that a pair of similarity 0.5 or more connects are a cluster, and members of different
classes of a cluster are compared in blocks.  No pair leaves a worker but a forest of the links.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sigres.llm.batches import map_text
from sigres.operators.components import connected_components
from sigres.plans.scratch import Scratch, small_side

SEED = 42
#: Differing bits at which fingerprints link, and words of a shingle, in the exact setting.
MAX_BITS, SHINGLE = 3, 3
#: Near-duplicate setting: words of a shingle, similarity, segments per lane and their bits, lanes.
NEAR_SHINGLE, NEAR_JACCARD = 5, 0.8
SEGMENT_BITS, SEGMENTS_PER_LANE, LANES = 20, 3, 6
#: Differing bits of 64 that the filter lets pass: Jaccard 0.8 has 9.7 on average, deviation 2.9.
SKETCH_BITS = 18
#: Similarity of a verified pair from which on the classes of its ends are compared member by member, and documents of a block that is compared.
FLOOR, BLOCK = 0.5, 256
#: Edges of which a worker makes a forest at once.
FOREST_EDGES = 200_000
#: Rows of a bucket that a worker holds.
RUN = 4096
#: Rows up to which an id table is broadcast (about 16 bytes each).
BROADCAST_ROWS = 500_000
_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_GOLDEN = 0x9E3779B97F4A7C15


def words_of(text: str | None) -> list[bytes]:
    """Words of the text with A-Z in lower case; white space is U+0020 and U+0009 to U+000D."""
    return (text or "").encode().translate(_LOWER).split()


def shingle_hashes(words: list[bytes], n: int) -> np.ndarray:
    """Unsigned XXH64 of every run of ``n`` words; of the whole sequence if it is shorter."""
    if not words:
        return np.zeros(0, np.uint64)
    if len(words) <= n:
        return np.array([xxhash.xxh64_intdigest(b" ".join(words), SEED)], np.uint64)
    of, join = xxhash.xxh64_intdigest, b" ".join
    runs = zip(*(words[i:] for i in range(n)))
    return np.fromiter((of(join(r), SEED) for r in runs), np.uint64, len(words) - n + 1)


def lane(hashes: np.ndarray, j: int) -> np.ndarray:
    """The j-th independent 64-bit hash of a shingle, mixed from the first one."""
    if not j:
        return hashes
    x = hashes + np.uint64(_GOLDEN * j % (1 << 64))
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def fingerprint(hashes: np.ndarray, block: int = 1 << 16) -> int:
    """A bit is 1 if it is set in over half of the hashes; no hashes give zero."""
    counts = np.zeros(64, np.int64)
    for at in range(0, len(hashes), block):
        part = np.ascontiguousarray(hashes[at:at + block])
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits((counts * 2 > len(hashes)).astype(np.uint8), bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, shingle: int, lanes: int, distinct: bool = False) -> DataFrame:
    """(doc_id, f0, f1, ...): one signed 64-bit fingerprint per lane of the whole text.

    Shingles count as often as they occur, or once each if ``distinct``.
    """
    names = [f"f{j}" for j in range(lanes)]

    def run(part: pa.RecordBatch) -> dict:
        found = np.zeros((lanes, part.num_rows), np.uint64)
        for i, text in enumerate(part.column("text").to_pylist()):
            hashes = shingle_hashes(words_of(text), shingle)
            if distinct:
                hashes = np.unique(hashes)
            for j in range(lanes):
                found[j, i] = fingerprint(lane(hashes, j))
        return {"doc_id": part.column("doc_id")} | {n: found[j].view(np.int64) for j, n in enumerate(names)}

    return map_text(docs.select("doc_id", "text"), run, "doc_id long, " + ", ".join(f"{n} long" for n in names))


def variants(nodes: DataFrame, lanes: list[str], bits: int, per_lane: int) -> DataFrame:
    """(id, sketch, lanes) -> (k1, k2, sketch, id), a row per segment and wildcard position."""
    n = bits * per_lane
    places = F.explode(F.sequence(F.lit(0), F.lit(len(lanes) * n - 1))).alias("p")
    at, low = F.col("p") % bits, (1 << bits) - 1
    shift = (F.floor(F.col("p") / bits) % per_lane * bits).cast("int")
    value = F.call_function("shiftrightunsigned", F.get(F.array(*lanes), F.floor(F.col("p") / n).cast("int")), shift).bitwiseAND(F.lit(low))
    hole = F.bitwise_not(F.call_function("shiftleft", F.lit(1).cast("long"), at.cast("int")))
    key = F.col("p").cast("long") * F.lit(1 << bits) + value.bitwiseAND(hole)
    return (nodes.select("id", "sketch", *lanes, places)
            .select(key.alias("k1"), F.lit(0).cast("long").alias("k2"), "sketch", "id"))


def _spanning(sketch: np.ndarray, ids: np.ndarray, most: int) -> list[tuple[int, int]]:
    """Edges of a minimum spanning forest over pairs that differ in ``most`` bits or fewer.

    On the forest's path between two such rows no edge differs in more bits than they do.  Of equally
    close pairs the one of smaller ids comes first, whatever the rows' order.
    """
    n = len(ids)
    forest: list[tuple[int, int]] = []
    if n <= 512 and (np.bitwise_count(sketch[:, None] ^ sketch[None, :]) <= most).sum() == n:
        return forest
    order = np.argsort(ids, kind="stable")
    sketch, ids = sketch[order], ids[order]
    place, step = np.arange(n), n * n  # an edge's rank: bits, then the lesser end, then the other
    none = 65 * step
    best, parent = np.full(n, none), np.zeros(n, np.int64)
    open_ = np.ones(n, bool)
    for _ in range(n):
        at = int(best.argmin())
        if best[at] >= (most + 1) * step:
            at = int(open_.argmax())
        else:
            forest.append((int(ids[parent[at]]), int(ids[at])))
        open_[at], best[at] = False, none
        rank = np.bitwise_count(sketch ^ sketch[at]).astype(np.int64) * step + np.minimum(place, at) * n + np.maximum(place, at)
        nearer = open_ & (rank < best)
        best[nearer], parent[nearer] = rank[nearer], at
    return forest


def _close(batches: Iterator[pa.RecordBatch], most: int, run: int, refine: bool) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (k1, k2) -> edges (a, b), and with ``refine`` rows of runs that are too long: (k1, k2, sketch, id).

    Edges that a worker has just sent are not sent again.
    """
    schema = pa.schema([(n, pa.int64()) for n in ("a", "b", "k1", "k2", "sketch", "id")])
    edges: set[tuple[int, int]] = set()

    def sent(rows=None):
        n = len(edges)
        cols = [np.fromiter((e[i] for e in edges), np.int64, n) for i in (0, 1)]
        edges.clear()
        none = pa.nulls(n, pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array(cols[0]), pa.array(cols[1]), none, none, none, none], schema=schema)
        if rows is not None:
            gone = pa.nulls(len(rows[0]), pa.int64())
            yield pa.RecordBatch.from_arrays([gone, gone, *map(pa.array, rows)], schema=schema)

    def link(a, b):
        edges.update(zip(np.minimum(a, b).tolist(), np.maximum(a, b).tolist()))

    def settle(k1, k2, sketch, ids):
        """All runs in these rows are whole; runs of two to nine rows are compared at once."""
        start = np.flatnonzero(np.r_[True, (k1[1:] != k1[:-1]) | (k2[1:] != k2[:-1])])
        size = np.diff(np.r_[start, len(k1)])
        short = np.repeat(size <= 9, size)
        group = np.repeat(np.arange(len(start)), size)
        bits = sketch.view(np.uint64)
        for d in range(1, min(9, int(size.max()))):
            hit = (group[d:] == group[:-d]) & short[d:]
            hit &= np.bitwise_count(bits[d:] ^ bits[:-d]) <= most
            i = np.flatnonzero(hit)
            if len(i):
                link(ids[i], ids[i + d])
        for r in np.flatnonzero(size > 9):
            part = slice(start[r], start[r] + size[r])
            edges.update((min(e), max(e)) for e in _spanning(bits[part], ids[part], most))

    held: list[tuple[np.ndarray, ...]] = []
    count, over = 0, None  # rows held; the key of a run that is passed on
    for batch in batches:
        cols = [batch.column(n).to_numpy() for n in ("k1", "k2", "sketch", "id")]
        if not len(cols[0]):
            continue
        if over is not None:
            n = int(np.searchsorted((cols[0] != over[0]) | (cols[1] != over[1]), True))
            if n:
                yield from sent([c[:n] for c in cols])
                cols = [c[n:] for c in cols]
            if not len(cols[0]):
                continue
            over = None
        if held:
            cols = [np.concatenate([h[i] for h in held] + [cols[i]]) for i in range(4)]
        last = (cols[0][-1], cols[1][-1])
        cut = len(cols[0]) - int(np.searchsorted(((cols[0] != last[0]) | (cols[1] != last[1]))[::-1], True))
        tail = [c[cut:] for c in cols]
        if cut:
            whole = [c[:cut] for c in cols]
            if refine:
                start = np.flatnonzero(np.r_[True, (whole[0][1:] != whole[0][:-1]) | (whole[1][1:] != whole[1][:-1])])
                size = np.diff(np.r_[start, cut])
                long = np.repeat(size > run, size)
                if long.any():
                    yield from sent([c[long] for c in whole])
                    whole = [c[~long] for c in whole]
            if len(whole[0]):
                settle(*whole)
        held, count = [tuple(tail)], len(tail[0])
        if refine and count > run:
            yield from sent(tail)
            held, count, over = [], 0, last
        elif count > run:
            forest = _spanning(tail[2].view(np.uint64), tail[3], most)
            edges.update((min(e), max(e)) for e in forest)
            roots = ~np.isin(tail[3], np.array([b for _, b in forest], np.int64))
            held = [tuple(c[roots] for c in tail)]
            count = int(roots.sum())
        if len(edges) > 200_000:
            yield from sent()
    if held and count:
        settle(*held[0])
    yield from sent()


_CLOSE = "a long, b long, k1 long, k2 long, sketch long, id long"


def close_pairs(rows: DataFrame, most: int, run: int = RUN, refine: bool = False) -> DataFrame:
    """Edges between ids that meet in a bucket and differ in ``most`` bits of their sketch or fewer."""
    return (rows.repartition("k1", "k2").sortWithinPartitions("k1", "k2")
            .mapInArrow(lambda batches: _close(batches, most, run, refine), _CLOSE))


def _block_pairs(rows: DataFrame, run: int) -> DataFrame:
    """(k1, sketch, id) of buckets above ``run`` rows -> a bucket (k1, k2) for each two of their blocks of about half of ``run`` rows."""
    size = rows.groupBy("k1").agg(F.count("*").alias("n"))
    blocks = F.ceil(F.col("n") * 2 / run).cast("long")
    rows = rows.join(size, "k1").withColumn("blocks", F.greatest(blocks, F.lit(2))).withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks")))
    other = F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("other")
    met = rows.select("k1", "sketch", "id", "blocks", "block", other).where("block <> other")
    return met.select("k1", (F.least("block", "other") * F.col("blocks") + F.greatest("block", "other")).alias("k2"), "sketch", "id")


def _refined(rows: DataFrame, level: int) -> DataFrame:
    """Rows of long runs with more bits known.

    Level 2 cuts the other segment of 32 bits in halves of 16, level 3 the half that is not yet
    known in quarters of 8; at distance 3 or less one of the two parts again differs by at most one
    bit, so the wildcard variants of both parts lose no pair.
    """
    bits = 16 if level == 2 else 8
    segment = F.floor(F.col("k1") / F.lit(32 << 32))  # of the first level: 0 low, 1 high
    if level == 2:
        base = (1 - segment) * 32
        k1 = F.col("k1")
    else:
        half = F.floor(F.col("k2") / F.lit(16 << 16))
        base = (1 - segment) * 32 + (1 - half) * 16
        # 38 bits of the first key and 21 of the second
        k1 = F.col("k1") * F.lit(1 << 21) + F.col("k2")
    p = F.explode(F.sequence(F.lit(0), F.lit(2 * bits - 1))).alias("p")
    rows = rows.select(k1.alias("k1"), base.cast("int").alias("base"), "sketch", "id", p)
    shift = (F.col("base") + F.floor(F.col("p") / bits) * bits).cast("int")
    value = F.call_function("shiftrightunsigned", F.col("sketch"), shift).bitwiseAND(F.lit((1 << bits) - 1))
    hole = F.bitwise_not(F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("p") % bits).cast("int")))
    return rows.select("k1", (F.col("p").cast("long") * F.lit(1 << bits) + value.bitwiseAND(hole)).alias("k2"), "sketch", "id")


def exact_links(prints: DataFrame, scratch: Scratch, run: int = RUN) -> DataFrame:
    """Distinct fingerprints (fp) -> edges (a, b) that span every component at ``MAX_BITS`` or fewer."""
    rows = variants(prints.select(F.col("fp").alias("id"), F.col("fp").alias("sketch"), "fp"), ["fp"], 32, 2)
    out = None
    for level in (1, 2, 3):
        found = scratch.save(close_pairs(rows, MAX_BITS, run, refine=level < 3), f"close{level}")
        edges = found.where("a is not null").select("a", "b")
        out = edges if out is None else out.unionByName(edges)
        rest = found.where("a is null")
        if level == 3 or not rest.take(1):
            return out
        rows = _refined(rest.select("k1", "k2", "sketch", "id"), level + 1)


def _labels(prints: DataFrame, edges: DataFrame, scratch: Scratch) -> DataFrame:
    """(fp, n, first) and edges between fingerprints -> (fp, component_id) where it is not the document itself."""
    linked = scratch.save(connected_components(edges).withColumnRenamed("rid", "fp"), "linked")
    named = (prints.join(small_side(linked, BROADCAST_ROWS), "fp", "left")
             .withColumn("entity", F.coalesce("entity_id", "fp")).where("n > 1 or entity_id is not null"))
    named = scratch.save(named.select("fp", "first", "entity"), "named")
    least = scratch.save(named.groupBy("entity").agg(F.min("first").alias("component_id")), "least")
    return scratch.save(named.join(small_side(least, BROADCAST_ROWS), "entity").select("fp", "component_id"), "labels")


def linked_components(docs: DataFrame, run: int = RUN) -> DataFrame:
    """One row per row of ``docs``: doc_id, fp (signed 64 bits), component_id.

    Fingerprints link at three or fewer differing bits; component_id is the smallest doc_id that
    links reach.  Null, empty and blank texts have fingerprint zero and link like any other.
    Repeated rows are equal rows of one component; a null doc_id is never the smallest, unless all
    are null.  An empty table gives an empty result; other columns are not read.
    """
    scratch = Scratch(docs.sparkSession, "simhash")
    base = scratch.save(fingerprints(docs, SHINGLE, 1).withColumnRenamed("f0", "fp"), "prints")
    prints = scratch.save(base.groupBy("fp").agg(F.count("*").alias("n"), F.min("doc_id").alias("first")), "distinct")
    labels = _labels(prints, exact_links(prints, scratch, run), scratch)
    return (base.join(small_side(labels, BROADCAST_ROWS), "fp", "left")
            .select("doc_id", "fp", F.coalesce("component_id", "doc_id").alias("component_id")))


def shingle_sets(docs: DataFrame, n: int) -> DataFrame:
    """(id, text) -> (id, hashes): the distinct shingle hashes of each text."""
    def run(part: pa.RecordBatch) -> dict:
        return {"id": part.column("id"),
                "hashes": [np.unique(shingle_hashes(words_of(t), n)).view(np.int64) for t in part.column("text").to_pylist()]}

    return map_text(docs, run, "id long, hashes array<long>")


def _judged(pairs: DataFrame, sets: DataFrame, jaccard: float, floor: float) -> DataFrame:
    """The pairs (a, b) whose shingle sets have similarity ``floor`` or more, and whether it is ``jaccard`` or more."""
    both = (pairs.join(sets.select(F.col("id").alias("a"), F.col("hashes").alias("ha")), "a")
            .join(sets.select(F.col("id").alias("b"), F.col("hashes").alias("hb")), "b"))
    shared = F.size(F.array_intersect("ha", "hb"))
    both = both.select("a", "b", shared.alias("shared"), (F.size("ha") + F.size("hb")).alias("total"))
    at_least = lambda least: (F.col("shared") >= F.lit(least) * (F.col("total") - F.col("shared"))) | (F.col("total") == 0)
    return both.where(at_least(floor)).select("a", "b", at_least(jaccard).alias("linked"))


def _labelled(ids: DataFrame, edges: DataFrame, scratch: Scratch) -> DataFrame:
    """(id) and links (a, b) -> (id, label): the smallest id that links reach."""
    linked = scratch.save(connected_components(edges).withColumnRenamed("rid", "id"), "linked")
    return ids.join(small_side(linked, BROADCAST_ROWS), "id", "left").select("id", F.coalesce("entity_id", "id").alias("label"))


def _spanned(edges, up: dict[int, int]) -> list[tuple[int, int]]:
    """The edges that join what those before them, kept in ``up``, did not."""
    def root(v):
        while (above := up.setdefault(v, v)) != v:
            up[v] = up[above]
            v = above
        return v
    out = []
    for a, b in edges:
        ra, rb = root(a), root(b)
        if ra != rb:
            up[max(ra, rb)] = min(ra, rb)
            out.append((a, b))
    return out


def _thinned(edges: DataFrame, most: int = FOREST_EDGES) -> DataFrame:
    """Scratch table (a, b) -> edges that reach as far: a spanning forest of every ``most`` edges or fewer."""
    def run(batches):
        up: dict[int, int] = {}
        for batch in batches:
            out = _spanned(zip(batch.column("a").to_pylist(), batch.column("b").to_pylist()), up)
            yield pa.RecordBatch.from_arrays([pa.array([e[i] for e in out], pa.int64()) for i in (0, 1)], names=["a", "b"])

    return edges.repartition(-(-max(edges.count(), 1) // most)).mapInArrow(run, "a long, b long")


def _compare(batches: Iterator[pa.RecordBatch], jaccard: float) -> Iterator[pa.RecordBatch]:
    """Rows (cluster, first, second, block, id, label, hashes) sorted by the first three -> links (a, b) of labels.

    Pairs of one row of each block, or of one block if first and second are the same; of the links
    that join the same labels a spanning forest is sent.
    """
    keys = ("cluster", "first", "second")

    def settle(part: pa.Table):
        first, second, block, label = (part.column(n).to_numpy() for n in ("first", "second", "block", "label"))
        hashes = part.column("hashes").combine_chunks()
        sizes = pa.compute.list_value_length(hashes).to_numpy(zero_copy_only=False).astype(np.int64)
        values, owner = hashes.flatten().to_numpy(), np.repeat(np.arange(len(sizes)), sizes)
        _, at, often = np.unique(values, return_inverse=True, return_counts=True)
        met = often[at] > 1  # a shingle of one text adds nothing to what two texts share
        owner, at = owner[met], at[met]
        _, at = np.unique(at, return_inverse=True)
        x = np.flatnonzero(block == first[0])
        y = np.flatnonzero(block == second[0])
        shared = np.zeros((len(x), len(y)))
        order = np.argsort(at, kind="stable")
        owner, at = owner[order], at[order]
        for low in range(0, int(at[-1]) + 1 if len(at) else 0, 4096):
            some = slice(*np.searchsorted(at, [low, low + 4096]))
            has = np.zeros((len(sizes), 4096), np.float32)
            has[owner[some], at[some] - low] = 1
            shared += has[x] @ has[y].T
        total = sizes[x][:, None] + sizes[y][None, :]
        i, j = np.nonzero((shared >= jaccard * (total - shared)) & (label[x][:, None] != label[y][None, :]))
        joined = np.unique(np.sort(np.stack([label[x[i]], label[y[j]]], 1), axis=1), axis=0)
        out = _spanned(joined.tolist(), {})
        return pa.RecordBatch.from_arrays([pa.array([e[i] for e in out], pa.int64()) for i in (0, 1)], names=["a", "b"])

    held = None
    for batch in batches:
        if not batch.num_rows:
            continue
        rows = pa.Table.from_batches([batch])
        if held is not None:
            rows = pa.concat_tables([held, rows])
        cols = [rows.column(n).to_numpy() for n in keys]
        start = np.flatnonzero(np.r_[True, np.any([c[1:] != c[:-1] for c in cols], axis=0)])
        for a, b in zip(start, start[1:]):
            yield settle(rows.slice(a, b - a))
        held = rows.slice(start[-1])
    if held is not None:
        yield settle(held)


def _across(members: DataFrame, sets: DataFrame, jaccard: float, scratch: Scratch, block: int = BLOCK) -> DataFrame:
    """(cluster, id, label) -> links (a, b) between labels of one cluster, by comparing all its members of different labels.

    The cluster's largest class and all its other members are cut into blocks; blocks of the largest
    class meet those of the others, and the others' blocks each other.
    """
    sizes = scratch.save(members.groupBy("cluster", "label").agg(F.count("*").alias("n")), "sizes")
    top = sizes.groupBy("cluster").agg(F.sum("n").alias("n"), F.max(F.struct("n", "label")).alias("top")).where("n > 2 and top.n < n")
    top = top.select("cluster", F.col("top.label").alias("top"), F.ceil(F.col("top.n") / block).alias("tops"), F.ceil((F.col("n") - F.col("top.n")) / block).alias("rests"))
    rows = members.join(small_side(scratch.save(top, "tops"), BROADCAST_ROWS // 4), "cluster")
    mine = F.col("label") == F.col("top")
    place = F.when(mine, F.pmod(F.xxhash64("id"), F.col("tops"))).otherwise(F.col("tops") + F.pmod(F.xxhash64("id"), F.col("rests")))
    other = F.explode(F.sequence(F.when(mine, F.col("tops")).otherwise(F.lit(0).cast("long")), F.col("tops") + F.col("rests") - 1))
    rows = scratch.save(rows.select("cluster", "id", "label", place.alias("block"), other.alias("other")), "blocks")
    keys = ["cluster", "first", "second"]
    rows = rows.join(sets, "id").select("cluster", F.least("block", "other").alias("first"), F.greatest("block", "other").alias("second"), "block", "id", "label", "hashes")
    return rows.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(lambda batches: _compare(batches, jaccard), "a long, b long")


def near_duplicates(docs: DataFrame, jaccard: float = NEAR_JACCARD, shingle: int = NEAR_SHINGLE, run: int = RUN, block: int = BLOCK) -> DataFrame:
    """doc_id, component_id of the documents that have a near-duplicate, the class's smallest doc_id included.

    Two texts are near-duplicates if their sets of five-word shingles (A-Z in lower case; the whole
    sequence if shorter) have Jaccard similarity 0.8 or more; classes are closed under links.  Every
    pair that shares a variant and passes the filter is in one cluster of candidates, and all members
    of a cluster that are not linked yet are compared by their sets.  Documents whose seven fingerprints
    are all equal are taken as one text.  Rows without a doc_id are left out; repeated rows are one
    document, which of several texts has the smallest set.  Documents that are in no class are not returned.
    """
    scratch = Scratch(docs.sparkSession, "near")
    names = [f"f{j}" for j in range(LANES + 1)]
    known = docs.where("doc_id is not null")
    base = scratch.save(fingerprints(known, shingle, LANES + 1, distinct=True), "prints")
    reps = scratch.save(base.groupBy(*names).agg(F.min("doc_id").alias("id"), F.count("*").alias("n")), "reps")
    rows = variants(reps.withColumn("sketch", F.col(names[-1])), names[:LANES], SEGMENT_BITS, SEGMENTS_PER_LANE)
    found = scratch.save(close_pairs(rows, SKETCH_BITS, run, refine=True), "close")
    pairs = found.where("a is not null").select("a", "b")
    long = found.where("a is null").select("k1", "sketch", "id")
    if long.take(1):
        pairs = pairs.unionByName(close_pairs(_block_pairs(long, run), SKETCH_BITS, 1 << 62).where("a is not null").select("a", "b"))
    pairs = scratch.save(pairs.distinct(), "pairs")
    needed = scratch.save(pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct(), "needed")
    texts = known.select(F.col("doc_id").alias("id"), "text").join(small_side(needed, BROADCAST_ROWS), "id")
    sets = scratch.save(shingle_sets(texts, shingle).groupBy("id").agg(F.min("hashes").alias("hashes")), "sets")
    judged = scratch.save(_judged(pairs, sets, jaccard, FLOOR), "judged")
    edges = judged.where("linked").select("a", "b")
    labels = scratch.save(_labelled(needed, edges, scratch), "labels")
    # classes that a similar pair connects without linking them are one cluster
    of = lambda end: small_side(labels, BROADCAST_ROWS).select(F.col("id").alias(end), F.col("label").alias(f"{end}_label"))
    weak = scratch.save(_thinned(judged.where("not linked").select("a", "b")), "similar")
    weak = weak.join(of("a"), "a").join(of("b"), "b").where("a_label <> b_label")
    weak = scratch.save(weak.select(F.col("a_label").alias("a"), F.col("b_label").alias("b")).distinct(), "weak")
    if weak.take(1):
        clusters = scratch.save(connected_components(weak).select(F.col("rid").alias("label"), F.col("entity_id").alias("cluster")), "clusters")
        members = scratch.save(labels.join(small_side(clusters, BROADCAST_ROWS), "label"), "members")
        more = scratch.save(_across(members, sets, jaccard, scratch, block), "more")
        if more.take(1):
            labels = scratch.save(_labelled(needed, edges.unionByName(more), scratch), "labels")
    sizes = labels.groupBy("label").agg(F.count("*").alias("m")).where("m > 1").select("label")
    linked = scratch.save(labels.join(sizes, "label", "left_semi"), "classes")
    classes = scratch.save(reps.join(small_side(linked, BROADCAST_ROWS), "id", "left").where("n > 1 or label is not null")
                           .select(*names, F.coalesce("label", "id").alias("component_id")), "named")
    same = base.join(small_side(classes, BROADCAST_ROWS // 4), names)
    return same.select("doc_id", "component_id")
