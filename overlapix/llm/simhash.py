"""Near-duplicates by SimHash fingerprints.

A fingerprint is the bitwise majority of the hashes of a text's word shingles.
Pairs within ``radius`` differing bits link.  The search embeds a fingerprint
as the bit counts of its two-bit segments: the Manhattan distance between two
such count vectors never exceeds the number of differing bits, so it is a lower
bound.  The segments are dealt to ``axes`` grid axes; a pair within Manhattan
distance ``radius`` differs on at most ``radius`` axes, hence shares the cells
of some ``axes - radius`` of them.  The range join is therefore an equi-join on
the grid cells of every choice of ``axes - radius`` axes.  In a bucket, pairs
beyond the Manhattan distance go first, and the exact bit test decides on the
rest.  Counts are kept in unary (0 as 00, 1 as 01, 2 as 11), so that Manhattan
distance is one exclusive-or and one count of bits.  Buckets over ``BUCKET_ROWS``
rows are dealt to tasks as blocks of row parts, every pair of parts once.

``keep_similar_groups`` finds near copies by the similarity of their sets of
five-word shingles: candidates come from the same search over several
fingerprints of word pairs, which few edits move little, and the shingle sets
of each candidate pair decide.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from overlapix.llm.arrow_groups import whole_groups
from overlapix.llm.components import connected_components, least_labels
from overlapix.llm.storage import discard, materialise

SEED = 42
EDGE = "u bigint, v bigint, big int"
SEGMENT_BITS = 2
SEGMENTS = 64 // SEGMENT_BITS
#: Collision entropy in bits of one two-bit segment's count.
SEGMENT_ENTROPY = 1.415
#: Buckets above this size are walked by search from seeds instead of by lags.
SMALL_BUCKET = 128
#: Near pairs a row up to which a small bucket gives them all, where pairs are to be decided on sets.
PAIRS_A_ROW = 4
#: Comparisons held in memory at once.
BLOCK = 1 << 21
#: Rows of a bucket, or of a part of one, that a task compares.
BUCKET_ROWS = 20_000
#: Large buckets are looked for in one fingerprint of so many, and broadcast up to that number.
SEEN, BROADCAST_CELLS = 64, 200_000
#: Work of a comparison against that of a bucket row, which is written, sent, sorted and read.
COMPARISON = 1e-4
#: Bits of hashed ids that are broadcast, at most.
SLOTS = 1 << 26
#: Shingle sets that a task compares with as many others.
SET_BLOCK = 512
#: Near copies by shingle sets: fingerprints a text, differing bits of one of them, and shingles.
WORDS, WORD_RADIUS, SHINGLE, SIMILARITY = 4, 5, 5, 0.8


def fingerprint(text: str | None, k: int = 4, seed: int = SEED) -> int:
    """Unsigned 64-bit majority fingerprint; 0 for a text without words.

    A-Z are lower-cased, words are runs of anything but ASCII white space,
    shingles are ``k`` words joined by one space and count with repeats; a text
    of fewer words has one shingle, all of them.
    """
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    n = max(1, len(words) - k + 1)
    digest = xxhash.xxh64_intdigest
    if n == 1:
        return digest(b" ".join(words), seed)
    joined = memoryview(b" ".join(words))
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = [0, *ends[: n - 1].tolist()]
    hashes = np.array([digest(joined[a : b - 1], seed) for a, b in zip(starts, ends[k - 1 :].tolist(), strict=True)], np.uint64)
    counts = np.zeros(64, np.int64)
    for i in range(0, n, 1 << 16):
        part = hashes[i : i + (1 << 16)]
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(counts * 2 > n, bitorder="little").view(np.uint64)[0])


def _fingerprint_batches(k: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = np.array([fingerprint(x.as_py(), k) for x in batch.column(1)], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(values)], names=["doc_id", "fp"])

    return run


def with_fingerprints(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", k: int = 4) -> DataFrame:
    """``(doc_id, fp)``, one row per input row; ``fp`` holds the 64 bits as a signed integer."""
    return docs.select(F.col(doc_id).cast("bigint").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(_fingerprint_batches(k), "doc_id bigint, fp bigint")


def segment_counts(fps: np.ndarray) -> np.ndarray:
    """n fingerprints -> n x SEGMENTS bit counts, the embedding."""
    bits = np.unpackbits(fps.astype(np.uint64).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return bits.reshape(len(fps), SEGMENTS, SEGMENT_BITS).sum(2, dtype=np.uint8)


LOW = np.uint64(0x5555_5555_5555_5555)
ONE = np.uint64(1)


def unary_counts(fps: np.ndarray) -> np.ndarray:
    """The same counts, two bits each in unary: the bits in which two of them differ are their Manhattan distance."""
    low, high = fps & LOW, (fps >> ONE) & LOW
    return (low | high) | ((low & high) << ONE)


def choose_axes(n: int, radius: int) -> int:
    """The number of grid axes of least expected work for ``n`` distinct fingerprints.

    Every choice is exact; more axes mean more bucket rows, ``comb(axes, radius)`` a
    fingerprint, and fewer comparisons.
    """
    whole = SEGMENT_ENTROPY * SEGMENTS

    def cost(axes: int) -> float:
        choices = comb(axes, radius)
        return choices * n * (1.0 + n / 2 * 2.0 ** (-whole * (axes - radius) / axes) * COMPARISON)

    return min(range(radius + 2, radius + 9), key=cost)


def _cells(axes: int, radius: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """(fp, node, word) -> one row a choice of axes; fingerprints of different words never meet."""
    dealt = [np.arange(a, SEGMENTS, axes) for a in range(axes)]
    choices = list(combinations(range(axes), axes - radius))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base = SEGMENT_BITS + 1
        for batch in batches:
            for part in (batch.slice(i, 4096) for i in range(0, batch.num_rows, 4096)):
                fps = part.column(0).to_numpy(zero_copy_only=False)
                counts = segment_counts(fps.view(np.uint64)).astype(np.int64)
                cell = [counts[:, d] @ (base ** np.arange(len(d), dtype=np.int64)) for d in dealt]
                keys = []
                for number, axes_kept in enumerate(choices):
                    key = part.column(2).to_numpy().astype(np.int64) * len(choices) + number
                    for a in axes_kept:
                        key = key * base ** len(dealt[a]) + cell[a]
                    keys.append(key)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)), pa.array(np.tile(fps, len(choices))), pa.array(np.tile(part.column(1).to_numpy(), len(choices)))], names=["cell", "fp", "node"])

    return run


def _near(a: np.ndarray, b: np.ndarray, radius: int) -> np.ndarray:
    """Within ``radius`` bits: by the Manhattan bound first, then by the bits of what it leaves."""
    near = np.bitwise_count(unary_counts(a) ^ unary_counts(b)) <= radius
    x, y = np.broadcast_arrays(a, b)
    near[near] = np.bitwise_count(x[near] ^ y[near]) <= radius
    return near


Pairs = list[tuple[np.ndarray, np.ndarray]]


def _walk(fps: np.ndarray, nodes: np.ndarray, radius: int) -> Pairs:
    """Stars of the components inside one large bucket, by search from seeds."""
    left = np.arange(len(fps))
    out = []
    while len(left) > 1:
        seed, left = left[0], left[1:]
        front = np.array([seed])
        while len(front) and len(left):
            hit = np.zeros(len(left), bool)
            step = max(1, BLOCK // len(left))
            for i in range(0, len(front), step):
                hit |= _near(fps[front[i : i + step], None], fps[left][None, :], radius).any(0)
            front, left = left[hit], left[~hit]
            if len(front):
                out.append((nodes[front], np.full(len(front), nodes[seed])))
    return out


def _stars(fps: np.ndarray, nodes: np.ndarray, radius: int) -> Pairs:
    """Rows of a large bucket, each linked to a centre that it is near to.  A centre is
    the row nearest to the majority of what is left, the text that most copies come
    from, while such rows have others near them, and then the first that is left."""
    left = np.arange(len(fps))
    out = []
    middling = True
    while len(left) > 1:
        centre = left[0]
        if middling:
            bits = np.unpackbits(fps[left].view(np.uint8).reshape(-1, 8), axis=1)
            middle = np.packbits(bits.sum(0, dtype=np.int64) * 2 > len(left)).view(np.uint64)[0]
            centre = left[np.argmin(np.bitwise_count(fps[left] ^ middle))]
        near = _near(fps[left], fps[centre], radius)
        star = left[near]
        middling = middling and len(star) > 1
        star = star[star != centre]
        out.append((nodes[star], np.full(len(star), nodes[centre])))
        left = left[~near]
    return out


def _lagged(cell: np.ndarray, fps: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Places of all near pairs of small buckets, by lags over the sorted rows."""
    none = np.zeros(0, np.int64)
    out = [(none, none)]
    for lag in range(1, SMALL_BUCKET):
        at = np.flatnonzero(cell[lag:] == cell[:-lag])
        if not len(at):
            break
        at = at[_near(fps[at], fps[at + lag], radius)]
        out.append((at, at + lag))
    return np.concatenate([a for a, _ in out]), np.concatenate([b for _, b in out])


def _cross(fps: np.ndarray, nodes: np.ndarray, part: np.ndarray, radius: int, stars: bool) -> Pairs:
    """Rows of two parts of a bucket: what its near pairs connect as stars of least
    nodes or, with ``stars``, each row with the nearest of the other part."""
    a, b = np.flatnonzero(part == part.min()), np.flatnonzero(part != part.min())
    label, out = nodes.copy(), []
    step = max(1, BLOCK // max(1, len(b)))
    best = np.full(len(b), -1)
    least = np.full(len(b), 255, np.uint8)
    while len(a) and len(b):
        before = label.copy()
        for i in range(0, len(a), step):
            at = a[i : i + step]
            near = _near(fps[at, None], fps[b][None, :], radius)
            if stars:
                far = np.where(near, np.bitwise_count(fps[at, None] ^ fps[b][None, :]), 255)
                hit = near.any(1)
                out.append((nodes[at[hit]], nodes[b[far.argmin(1)[hit]]]))
                closer = far.min(0) < least
                best[closer], least[closer] = at[far.argmin(0)[closer]], far.min(0)[closer]
            else:
                most = np.iinfo(np.int64).max
                label[b] = np.minimum(label[b], np.where(near, label[at, None], most).min(0))
                label[at] = np.minimum(label[at], np.where(near, label[b][None, :], most).min(1))
        if stars or (label == before).all():
            break
    if stars:
        return [*out, (nodes[b[best >= 0]], nodes[best[best >= 0]])]
    return [(nodes[label != nodes], label[label != nodes])]


def _edges(found: Pairs, big: int = 0) -> pa.RecordBatch | None:
    found = [x for x in found if len(x[0])]
    if not found:
        return None
    u, w = (np.concatenate([x[i] for x in found]) for i in (0, 1))
    pairs = np.unique(np.stack([np.maximum(u, w), np.minimum(u, w)], 1), axis=0)
    return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1]), pa.array(np.full(len(pairs), big, np.int32))], names=["u", "v", "big"])


def _bucket_edges(radius: int, stars: bool) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """(cell, i, j, part, fp, node) groups -> edges.  Small buckets give all near
    pairs.  Large ones give the stars of their components, marked by a ``big`` of 2,
    and with ``stars`` those of centres too, marked by 1."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (_, first, second, part, fps, nodes), starts in whole_groups(batches, 3):
            fps = fps.view(np.uint64)
            sizes = np.diff(np.concatenate([starts, [len(fps)]]))
            group = np.repeat(np.arange(len(starts)), sizes)
            apart = first[starts] != second[starts]
            small = np.flatnonzero(np.repeat((sizes <= SMALL_BUCKET) & ~apart, sizes))
            a, b = (small[x] for x in _lagged(group[small], fps[small], radius))
            large = (sizes > SMALL_BUCKET) | apart
            if stars:
                dense = np.bincount(group[a], minlength=len(starts)) > PAIRS_A_ROW * sizes
                large |= dense
                a, b = a[~dense[group[a]]], b[~dense[group[a]]]
            if out := _edges([(nodes[a], nodes[b])]):
                yield out
            for g in np.flatnonzero(large):
                f, v, p = (x[starts[g] : starts[g] + sizes[g]] for x in (fps, nodes, part))
                if out := _edges(_cross(f, v, p, radius, False) if apart[g] else _walk(f, v, radius), 2):
                    yield out
                if stars and (out := _edges(_cross(f, v, p, radius, True) if apart[g] else _stars(f, v, radius), 1)):
                    yield out

    return run


def _large_buckets(reps: DataFrame, n: int, radius: int, axes: int) -> DataFrame | None:
    """``cell, parts`` of buckets of more than ``BUCKET_ROWS`` rows, as one fingerprint in
    ``SEEN`` shows them.  One that it does not show is compared whole by one task."""
    if n <= BUCKET_ROWS:
        return None
    some = reps.where(F.pmod(F.xxhash64("node"), F.lit(SEEN)) == 0)
    counted = _cell_rows(some, radius, axes).groupBy("cell").agg(F.count("*").alias("n")).where(F.col("n") * SEEN > BUCKET_ROWS)
    large = materialise(counted.select("cell", F.ceil(F.col("n") * SEEN / BUCKET_ROWS).cast("int").alias("parts")), "large-buckets")
    return large if large.limit(1).count() else None


def _dealt(cells: DataFrame, large: DataFrame | None) -> DataFrame:
    """Rows of ``(cell, fp, node)`` by bucket, those of large ones by every pair of their parts."""
    if large is None:
        rows = cells.select("cell", *[F.lit(0).alias(c) for c in ("i", "j", "part")], "fp", "node")
    else:
        few = F.broadcast(large) if large.limit(BROADCAST_CELLS + 1).count() <= BROADCAST_CELLS else large
        sized = cells.join(few, "cell", "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
        parted = sized.withColumn("part", F.pmod(F.xxhash64("node", F.lit(1)), F.col("parts")).cast("int"))
        other = parted.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
        rows = other.select("cell", F.least("part", "other").alias("i"), F.greatest("part", "other").alias("j"), "part", "fp", "node")
    parts = int(cells.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.repartition(parts, "cell", "i", "j").sortWithinPartitions("cell", "i", "j")


def _cell_rows(reps: DataFrame, radius: int, axes: int) -> DataFrame:
    word = F.col("word") if "word" in reps.columns else F.lit(0).alias("word")
    return reps.select("fp", "node", word).mapInArrow(_cells(axes, radius), "cell bigint, fp bigint, node bigint")


def fingerprint_links(reps: DataFrame, radius: int = 4, axes: int | None = None, n: int | None = None, stars: bool = False) -> DataFrame:
    """Edges ``(u, v, big)`` between nodes of ``(fp, node)``, or of ``(fp, node, word)``.

    By default they are enough to connect all fingerprints that chains of links
    within ``radius`` connect (a large bucket yields the stars of its components,
    never all its pairs).  With ``stars``, it yields those of centres as well.
    """
    n = reps.count() if n is None else n
    axes = axes or choose_axes(n, radius)
    cells = _cell_rows(reps, radius, axes)
    return _dealt(cells, _large_buckets(reps, n, radius, axes)).mapInArrow(_bucket_edges(radius, stars), EDGE)


def near_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", k: int = 4, radius: int = 4) -> DataFrame:
    """``(doc_id, fp, component_id)``, one row per input row.

    ``component_id`` is the smallest doc_id that links of at most ``radius``
    differing bits reach.  Null or empty texts have fingerprint zero and link
    like any other.  A null doc_id names nothing: its row joins the component of
    its fingerprint, or gets null where all ids of that component are null.
    Repeated rows stay.  Distinct fingerprints alone enter the search, so exact
    copies cost one row however many there are.
    """
    marks = materialise(with_fingerprints(docs, text, doc_id, k), "fingerprints")
    reps = materialise(marks.groupBy("fp").agg(F.min("doc_id").alias("node")).where("node is not null"), "distinct-fp")
    found = connected_components(fingerprint_links(reps, radius))
    named = reps.join(found, "node", "left").select("fp", F.coalesce("component", "node").alias("component_id"))
    named = materialise(named, "fp-components")
    discard(reps)
    return marks.join(named, "fp", "left").select("doc_id", "fp", "component_id")


def _single(docs: DataFrame, doc_id: str) -> DataFrame:
    """Rows that repeat an id count as copies of each other: one stays."""
    named = docs.where(F.col(doc_id).isNotNull())
    if named.groupBy(doc_id).count().where("count > 1").limit(1).count():
        return named.dropDuplicates([doc_id]).unionByName(docs.where(F.col(doc_id).isNull()))
    return docs


def _slotted(rows: DataFrame, name: str, ids: DataFrame, n: int) -> DataFrame:
    """``rows`` with ``__met``: false where the slots of the ``n`` hashed ``ids`` (one column),
    a bit each and ``SLOTS`` at most, show that ``name`` is none of them.  So that the rest
    alone meets ``ids`` in a shuffle."""
    slots = max(1 << 15, min(SLOTS, 1 << (32 * n).bit_length()))
    slot = lambda c: F.pmod(F.xxhash64(F.col(c).cast("bigint")), F.lit(slots))
    bits = ids.toDF("__id").select(slot("__id").alias("__slot")).selectExpr("__slot div 32768 AS __page", "__slot % 32768 AS __at").groupBy("__page").agg(F.bitmap_construct_agg("__at").alias("__bits"))
    placed = rows.withColumn("__slot", slot(name)).withColumn("__page", F.expr("__slot div 32768"))
    met = F.expr("coalesce(shiftright(cast(conv(hex(substring(__bits, cast(__slot % 32768 div 8 AS int) + 1, 1)), 16, 10) AS int), cast(__slot % 8 AS int)) & 1, 0) = 1")
    return placed.join(F.broadcast(bits), "__page", "left").select(*rows.columns, met.alias("__met"))


def _without(docs: DataFrame, doc_id: str, marks: DataFrame) -> DataFrame:
    gone = materialise(marks.where("doc_id <> component_id").select(F.col("doc_id").alias("__gone")).distinct(), "gone")
    sorted_out = _slotted(docs, doc_id, gone, gone.count())
    left = sorted_out.where("__met").join(gone, F.col(doc_id) == F.col("__gone"), "left_anti")
    return sorted_out.where("not __met").unionAll(left).drop("__met")


def keep_one_per_group(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", k: int = 4, radius: int = 4) -> DataFrame:
    """The rows of ``docs`` whose id is the smallest of its near-duplicate group.

    Rows with a null id stay (nothing can name their group).  Rows that repeat
    an id count as copies of each other: one stays.
    """
    docs = _single(docs, doc_id)
    return _without(docs, doc_id, near_duplicates(docs, text, doc_id, k, radius))


# near copies by the similarity of shingle sets


MIX = (np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB), np.uint64(0x9E3779B97F4A7C15))


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * MIX[0]
    x = (x ^ (x >> np.uint64(27))) * MIX[1]
    return x ^ (x >> np.uint64(31))


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.array([xxhash.xxh64_intdigest(w, SEED) for w in words], np.uint64)


def shingles_of(hashed: np.ndarray, k: int) -> np.ndarray:
    """Distinct 64-bit hashes of runs of ``k`` words, from those of the words; fewer words make one run, none make none."""
    if not len(hashed):
        return np.zeros(0, np.uint64)
    k = min(k, len(hashed))
    out = np.zeros(len(hashed) - k + 1, np.uint64)
    for i in range(k):
        out = _mixed(out * MIX[2] + hashed[i : len(hashed) - k + 1 + i])
    return np.unique(out)


def shingle_hashes(words: list[bytes], k: int) -> np.ndarray:
    return shingles_of(word_hashes(words), k)


def odd_bits(hashes: np.ndarray) -> bytes:
    """Which of a set's hash slots hold an odd number of its elements, in whole bytes, a
    power of two of them with two bits an element at least."""
    width = max(64, 1 << (2 * len(hashes) - 1).bit_length()) if len(hashes) else 64
    uses = np.bincount((hashes & np.uint64(width - 1)).astype(np.int64), minlength=width)
    return np.packbits((uses & 1).astype(np.uint8), bitorder="little").tobytes()


def odd_slots(a: bytes, b: bytes) -> int:
    """The slots in which two sets' ``odd_bits`` differ, the wider folded to the other's
    width: never more than the elements that are in one set only."""
    if len(a) < len(b):
        a, b = b, a
    x, bits = int.from_bytes(a, "little"), 8 * len(a)
    while bits > 8 * len(b):
        bits //= 2
        x = (x >> bits) ^ (x & ((1 << bits) - 1))
    return (x ^ int.from_bytes(b, "little")).bit_count()


def _wide_batches(k: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """(doc_id, text) -> (doc_id, key, fps, size, odd): a digest of the words, ``WORDS``
    fingerprints of the word pairs, and of the set of ``k``-word shingles its size and odd bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, fps, size, odd = [], [], [], []
            for x in batch.column(1):
                words = (x.as_py() or "").encode("utf-8", "surrogatepass").lower().split()
                keys.append(xxhash.xxh3_128_digest(b" ".join(words)))
                hashed = word_hashes(words)
                shingles = shingles_of(hashed, k)
                size.append(len(shingles))
                odd.append(odd_bits(shingles))
                pairs = shingles_of(hashed, 2)
                for w in range(WORDS):
                    hashes = _mixed(pairs + MIX[2] * np.uint64(w + 1))
                    counts = np.zeros(64, np.int64)
                    for i in range(0, len(hashes), 1 << 16):
                        counts += np.unpackbits(hashes[i : i + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
                    fps.append(np.packbits(counts * 2 > len(hashes), bitorder="little").view(np.int64)[0])
            fixed = pa.ListArray.from_arrays(pa.array(np.arange(0, len(fps) + 1, WORDS, dtype=np.int32)), pa.array(np.array(fps, np.int64)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(keys, pa.binary()), fixed, pa.array(size, pa.int64()), pa.array(odd, pa.binary())], names=["doc_id", "key", "fps", "size", "odd"])

    return run


def _set_batches(k: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [shingle_hashes((x.as_py() or "").encode("utf-8", "surrogatepass").lower().split(), k).view(np.int64) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.list_(pa.int64()))], names=["node", "elems"])

    return run


def _possible(similarity: float) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """(u, v, size, odd, size, odd) -> (u, v) of pairs whose odd bits differ in no more slots
    than sets of these sizes and ``similarity`` have elements that are not common."""
    share = (1 - similarity) / (1 + similarity)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            apart = np.fromiter(map(odd_slots, batch.column(3).to_pylist(), batch.column(5).to_pylist()), np.int64, batch.num_rows)
            good = apart <= share * (batch.column(2).to_numpy() + batch.column(4).to_numpy()) + 1e-6
            yield pa.RecordBatch.from_arrays([batch.column(i).filter(pa.array(good)) for i in (0, 1)], names=["u", "v"])

    return run


def _likely(pairs: DataFrame, odd: DataFrame, similarity: float) -> DataFrame:
    """``(u, v)`` of ``pairs``, without those that sizes and odd bits (``node, size, odd``)
    prove to be less alike: no alike pair goes."""
    left, right = odd.toDF("u", "m", "a"), odd.toDF("v", "n", "b")
    met = pairs.where("u <> v").select("u", "v").distinct().join(left, "u").join(right, "v")
    sized = met.where(F.least("m", "n") >= similarity * F.greatest("m", "n"))
    return sized.select("u", "v", "m", "a", "n", "b").mapInArrow(_possible(similarity), "u bigint, v bigint")


def _alike(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """``(u, v)`` of ``pairs`` whose sets' intersection is at least ``similarity`` of their union."""
    left, right = sets.toDF("u", "a"), sets.toDF("v", "b")
    met = pairs.join(left, "u").join(right, "v")
    sized = met.where(F.least(F.size("a"), F.size("b")) >= similarity * F.greatest(F.size("a"), F.size("b")))
    common = F.size(F.array_intersect("a", "b"))
    return sized.withColumn("n", common).where(F.col("n") >= similarity * (F.size("a") + F.size("b") - F.col("n")) - 1e-9).select("u", "v")


def _set_blocks(similarity: float) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """(group, i, j, own, node, elems) groups -> stars of what the alike pairs between two blocks connect."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (_, first, second, own, node, elems), starts in whole_groups(batches, 3, 2 * SET_BLOCK):
            for a, b in zip(starts, [*starts[1:], len(node)], strict=True):
                sizes = np.array([len(x) for x in elems[a:b]])
                if not sizes.sum():
                    continue
                _, column, uses = np.unique(np.concatenate(elems[a:b]), return_inverse=True, return_counts=True)
                shared = uses[column] > 1
                row, column = np.repeat(np.arange(b - a), sizes)[shared], np.unique(column[shared], return_inverse=True)[1]
                p, q = np.flatnonzero(own[a:b] == first[a]), np.flatnonzero(own[a:b] == second[a])
                common = np.zeros((len(p), len(q)), np.float32)
                for c in range(0, int(column.max(initial=-1)) + 1, 4096):
                    here = (column >= c) & (column < c + 4096)
                    x = np.zeros((b - a, 4096), np.float32)
                    x[row[here], column[here] - c] = 1
                    common += x[p] @ x[q].T
                alike = common >= similarity * (sizes[p][:, None] + sizes[q][None, :] - common) - 1e-6
                alike &= (sizes[p] > 0)[:, None]
                low_p, low_q = least_labels(alike, node[a:b][p], node[a:b][q])
                ends, low = np.concatenate([node[a:b][p], node[a:b][q]]), np.concatenate([low_p, low_q])
                if out := _edges([(ends[ends != low], low[ends != low])]):
                    yield out

    return run


def _left_apart(found: DataFrame, links: DataFrame, sets_of: Callable[[DataFrame], DataFrame], similarity: float) -> DataFrame:
    """Links inside candidate groups of large buckets that the links to centres leave in
    several parts: of each group, all rows outside its largest part meet all rows."""
    whole = connected_components(found.select("u", "v"))
    hot = found.where("big > 0").select(F.col("u").alias("node")).distinct().join(whole, "node").select("component").distinct()
    parts = connected_components(links).withColumnRenamed("component", "label")
    members = whole.join(hot, "component", "left_semi").join(parts, "node", "left").select("component", "node", F.coalesce("label", "node").alias("label"))
    members = materialise(members, "members")
    sizes = members.groupBy("component", "label").agg(F.count("*").alias("n")).groupBy("component").agg(F.sum("n").alias("n"), F.max(F.struct("n", "label")).alias("most"))
    sizes = sizes.where(F.col("n") > F.col("most.n")).select("component", F.col("most.label").alias("main"), F.ceil((F.col("n") - F.col("most.n")) / SET_BLOCK).cast("int").alias("few"), F.ceil(F.col("most.n") / SET_BLOCK).cast("int").alias("many"))
    sized = members.join(sizes, "component").withColumn("outside", F.col("label") != F.col("main"))
    hashed = F.xxhash64("node")
    own = F.when(F.col("outside"), F.pmod(hashed, F.col("few"))).otherwise(F.col("few") + F.pmod(hashed, F.col("many"))).cast("int")
    meets = F.sequence(F.lit(0), F.when(F.col("outside"), F.col("few") + F.col("many")).otherwise(F.col("few")) - 1)
    rows = sized.withColumn("own", own).withColumn("other", F.explode(meets)).select("component", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "node")
    sets = sets_of(sized.select("node"))
    dealt = rows.join(sets, "node").select("component", "i", "j", "own", "node", "elems").repartition("component", "i", "j").sortWithinPartitions("component", "i", "j")
    return dealt.mapInArrow(_set_blocks(similarity), EDGE).select("u", "v")


def similar_groups(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", k: int = SHINGLE, similarity: float = SIMILARITY, radius: int = WORD_RADIUS) -> DataFrame:
    """``(doc_id, component_id)`` of rows with an id: the smallest id that chains of
    documents reach whose sets of ``k``-word shingles are ``similarity`` alike.

    Candidates lie within ``radius`` bits in one of ``WORDS`` fingerprints; those whose
    sizes and odd bits do not rule them out are decided on their shingle sets.  In large buckets, rows meet a centre first; then
    those that this left outside the largest part meet the rest in blocks.  Texts of
    the same words are one, texts without words too.
    """
    rows = docs.where(F.col(doc_id).isNotNull()).select(F.col(doc_id).cast("bigint").alias("doc_id"), F.col(text).cast("string").alias("text"))
    marks = materialise(rows.mapInArrow(_wide_batches(k), "doc_id bigint, key binary, fps array<bigint>, size bigint, odd binary"), "fingerprints")
    reps = materialise(marks.groupBy("key").agg(F.min("doc_id").alias("node"), *[F.first(c).alias(c) for c in ("fps", "size", "odd")]), "distinct-texts")
    n = reps.count()
    each = reps.select("node", F.posexplode("fps").alias("word", "fp"))
    found = materialise(fingerprint_links(each, radius, choose_axes(n, radius), n, True), "candidates")
    made = []

    def sets_of(nodes: DataFrame) -> DataFrame:
        ends = materialise(nodes.distinct(), "ends")
        met = _slotted(rows, "doc_id", ends, ends.count()).where("__met")
        texts = met.join(ends, met["doc_id"] == ends["node"], "left_semi").select("doc_id", "text")
        made.append(materialise(texts.mapInArrow(_set_batches(k), "node bigint, elems array<bigint>"), "shingle-sets"))
        return made[-1]

    likely = materialise(_likely(found.where("big < 2"), reps.select("node", "size", "odd"), similarity), "likely")
    ends = likely.select(F.col("u").alias("node")).unionByName(likely.select(F.col("v").alias("node")))
    links = materialise(_alike(likely, sets_of(ends), similarity), "alike")
    if found.where("big > 0").limit(1).count():
        links = links.unionByName(materialise(_left_apart(found, links, sets_of, similarity), "alike"))
    comps = connected_components(links)
    classes = reps.join(comps, "node", "left").select("key", F.coalesce("component", "node").alias("component_id"))
    out = materialise(marks.join(classes, "key").select("doc_id", "component_id"), "groups")
    for done in (marks, reps, found, likely, *made):
        discard(done)
    return out


def keep_similar_groups(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", k: int = SHINGLE, similarity: float = SIMILARITY) -> DataFrame:
    """The rows of ``docs`` whose id is the smallest of its group of near copies.

    Rows with a null id stay; of rows that repeat an id, one stays.
    """
    docs = _single(docs, doc_id)
    return _without(docs, doc_id, similar_groups(docs, text, doc_id, k, similarity))
