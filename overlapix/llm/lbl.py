"""Language-model scores by a log-bilinear model trained with noise-contrastive estimation.

Word counts come from all training documents, by distributed aggregation.  The
model's outputs are the words that occur most (at most ``VOCAB``; how many depends
on the corpus), the end of a text, and ``REST`` classes of all other words by their
last letters.  The vectors of the ``CONTEXT`` outputs before a token, each scaled by
its position's vector, add up to a vector that is compared with those of the outputs.

Outputs are dealt to about the square root of their number of groups; a token's
probability is that of its group among the groups times its own within the group,
so two narrow matrix products a batch of tokens give exactly normalised scores.  A
share of the unigram distribution is mixed in.  A word of a rest class has that
class's probability times its share of the class, in which one use is set aside for
every word never seen.

Every training document is learned from: each learner (a task over about
``LEARNER_TOKENS`` tokens) starts from the same model and takes adaptive steps on
the noise-contrastive objective, in expectation over the noise, which is the
unigram distribution of groups and within groups.  The learners' models are
averaged by tokens in blocks of parameters, so that a model's size bounds what one
task or the driver holds.

Counts of the most frequent ``COMMON`` words travel to the executors; the others
meet their documents in a join on a 64-bit hash.
"""

from __future__ import annotations

import ctypes
import zlib
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from overlapix.llm.fm_quality import fold
from overlapix.llm.storage import materialise

VOCAB = 4096
REST = 512
COMMON = 200_000
SIZE = 16
CONTEXT = 3
NOISE = 12
RATE = 0.15
MIX = 0.05
#: The end of a text, and as a context what comes before its start; the rest classes follow, then the words.
END = 0
FLUSH_WORDS = 400_000
#: Tokens of one step, of one batch that is scored, and of one learner.
STEP, BATCH, LEARNER_TOKENS = 8192, 8192, 4_000_000
#: Tokens whose scores are worked on at once, so that they stay in a core's cache.
COLUMNS = 1024
#: Biases of places that hold an output are above the first, and exponents up to the other are summed as they are.
UNUSED, SAFE = -5e3, 60.0
#: Parameters in one row between learners and their average.
BLOCK = 8192


def tokens(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


def rest_class(word: bytes, rest: int) -> int:
    return 1 + zlib.crc32(word[-3:]) % rest


class Outputs(dict):
    """Words to outputs; a word that is not listed is looked up once, until many are held."""

    def __init__(self, words: list[bytes], rest: int):
        super().__init__((w, i + 1 + rest) for i, w in enumerate(words))
        self.rest, self.most = rest, len(words) + FLUSH_WORDS

    def __missing__(self, word: bytes) -> int:
        made = 1 + zlib.crc32(word[-3:]) % self.rest  # as rest_class, without a call
        if len(self) < self.most:
            self[word] = made
        return made


def _rest_column(word: Column, rest: int) -> Column:
    return F.crc32(F.substring(word, -3, 3)) % rest + 1


def _count_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    train, held = Counter(), Counter()

    def out() -> pa.RecordBatch:
        words = list(train.keys() | held.keys())
        made = pa.RecordBatch.from_arrays([pa.array(words, pa.binary()), pa.array([train[w] for w in words], pa.int64()), pa.array([train[w] + held[w] for w in words], pa.int64())], names=["word", "c", "total"])
        train.clear()
        held.clear()
        return made

    for batch in batches:
        for text, away in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
            (held if away else train).update(tokens(text.as_py()))
            if len(train) + len(held) > FLUSH_WORDS:
                yield out()
    if train or held:
        yield out()


def word_counts(rows: DataFrame) -> DataFrame:
    """``(word, c, total)``: uses in training rows and in all rows of ``(text, held)``."""
    made = rows.select("text", "held").mapInArrow(_count_batches, "word binary, c bigint, total bigint")
    return made.groupBy("word").agg(F.sum("c").alias("c"), F.sum("total").alias("total"))


def most_frequent(counts: DataFrame, by: str, bound: int) -> DataFrame:
    """The words of the highest levels of ``by`` (64 to a doubling), as many whole
    levels as ``bound`` words hold, found by a count a level, without a sort."""
    level = F.floor(F.log2(by) * 64)
    sizes = dict(counts.where(F.col(by) > 0).groupBy(level.alias("level")).count().collect())
    least, held = None, 0
    for at in sorted(sizes, reverse=True):
        held += sizes[at]
        if held > bound:
            break
        least = at
    return counts.where(F.col(by) > 0).where(level >= least) if least is not None else counts.where(F.lit(False))


@dataclass
class LogBilinear:
    """``word`` and ``bias`` are by group and place within it: output ``o`` of ``groups``
    groups is in group ``o % groups`` at ``o // groups``."""

    context: np.ndarray
    position: np.ndarray
    group: np.ndarray
    group_bias: np.ndarray
    word: np.ndarray
    bias: np.ndarray
    unigram: np.ndarray

    PARAMS = ("context", "position", "group", "group_bias", "word", "bias")

    @classmethod
    def start(cls, uses: np.ndarray, seed: int = 3) -> LogBilinear:
        """The model that every learner starts from: ``uses`` counts each output."""
        groups = max(1, round(len(uses) ** 0.5))
        depth = -(-len(uses) // groups)
        unigram = np.zeros(groups * depth, np.float64)
        unigram[: len(uses)] = (uses + 1) / (uses + 1).sum()
        rng = np.random.default_rng(seed)
        small = lambda *shape: rng.normal(0, 0.1, shape).astype(np.float32)
        by_group = unigram.reshape(depth, groups).T
        mass = by_group.sum(1)
        inside = by_group / mass[:, None]
        bias = np.where(inside > 0, np.log(np.maximum(inside, 1e-30)), -1e4)  # no output there
        return cls(small(len(uses), SIZE), np.ones((CONTEXT, SIZE), np.float32) / CONTEXT**0.5, small(groups, SIZE), np.log(mass).astype(np.float32), small(groups, depth, SIZE), bias.astype(np.float32), unigram.astype(np.float32))

    def vector(self, before: list[np.ndarray]) -> np.ndarray:
        return sum(b * self.position[p] for p, b in enumerate(before))

    def before(self, flat: np.ndarray, at: np.ndarray) -> list[np.ndarray]:
        """The vectors of the outputs before each place, nearest first."""
        return [self.context[flat[at - 1 - p]] for p in range(CONTEXT)]

    def in_groups(self, outputs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The order of tokens by their outputs' groups, and where each group begins in it; one more for the end."""
        mine = outputs % len(self.group)
        order = _order(mine, len(self.group))
        return order, np.searchsorted(mine[order], np.arange(len(self.group) + 1))

    def log_probs(self, flat: np.ndarray, at: np.ndarray) -> np.ndarray:
        """log10 probabilities of the outputs at ``at``, given those before them."""
        out = np.empty(len(at))
        group, word = _with_bias(self.group, self.group_bias), _with_bias(self.word, self.bias)
        long = [max(float(np.linalg.norm(rows, axis=-1).max()), 1e-9) for rows in (self.group, self.word)]
        high = [float(np.abs(bias[bias > UNUSED]).max(initial=0)) for bias in (self.group_bias, self.bias)]
        for begin in range(0, len(at), BATCH):
            here = at[begin : begin + BATCH]
            order, edges = self.in_groups(flat[here])
            here = here[order]  # the tokens of a group next to one another
            h, target = self.vector(self.before(flat, here)), flat[here]
            mine, place = target % len(self.group), target // len(self.group)
            p = np.empty(len(here), np.float32)
            most = float(np.linalg.norm(h, axis=1).max())
            bounded = [most * x + b < SAFE for x, b in zip(long, high, strict=True)]
            h = _with_one(h)
            for own in _slices(0, len(here)):
                p[own] = _share(group @ h[:, own], mine[own], bounded[0])
            for g in np.flatnonzero(np.diff(edges)):
                for own in _slices(edges[g], edges[g + 1]):
                    p[own] *= _share(word[g] @ h[:, own], place[own], bounded[1])
            out[begin + order] = np.log10((1 - MIX) * p + MIX * self.unigram[target])
        return out

    def flat_params(self) -> np.ndarray:
        return np.concatenate([getattr(self, k).ravel() for k in self.PARAMS])

    def with_params(self, values: np.ndarray) -> LogBilinear:
        made, begin = {}, 0
        for k in self.PARAMS:
            old = getattr(self, k)
            made[k] = values[begin : begin + old.size].reshape(old.shape).astype(np.float32)
            begin += old.size
        return LogBilinear(**made, unigram=self.unigram)


def keep_memory(most: int = 64 << 20) -> None:
    """Up to ``most`` freed bytes stay with the process, so that the arrays of one step are
    not given back and faulted in again, page by page, by the next; glibc only."""
    mallopt = getattr(ctypes.CDLL(None), "mallopt", None)
    if mallopt:
        mallopt(-1, most)  # M_TRIM_THRESHOLD
        mallopt(-3, most // 2)  # M_MMAP_THRESHOLD


def _order(values: np.ndarray, bound: int) -> np.ndarray:
    # NumPy sorts integers of 16 bits by radix
    return np.argsort(values.astype(np.uint16) if bound <= 1 << 16 else values, kind="stable")


def _slices(begin: int, end: int) -> Iterator[slice]:
    for a in range(begin, end, COLUMNS):
        yield slice(a, min(a + COLUMNS, end))


def _with_bias(rows: np.ndarray, bias: np.ndarray) -> np.ndarray:
    """Vectors with a bias as one more component, which meets the one of ``_with_one``."""
    return np.concatenate([rows, bias[..., None].astype(np.float32)], -1)


def _with_one(h: np.ndarray) -> np.ndarray:
    """A column a vector, with a one below."""
    out = np.ones((h.shape[1] + 1, len(h)), np.float32)
    out[:-1] = h.T
    return out


def _share(score: np.ndarray, chosen: np.ndarray, bounded: bool = False) -> np.ndarray:
    """The softmax of each column at its chosen row; ``bounded`` scores need no shift."""
    if not bounded:
        score -= score.max(0)
    np.exp(score, out=score)
    return score[chosen, np.arange(score.shape[1])] / score.sum(0)


def _pull(odds: np.ndarray, noise: np.ndarray, chosen: np.ndarray) -> np.ndarray:
    """Gradient of the noise-contrastive objective for every score, one row an output
    and one column a token: what a token adds to its own output, less what the expected
    noise takes from each.  ``odds`` holds the noise's logarithms less the scores and biases."""
    score = odds
    np.exp(score, out=score)
    score += 1
    columns = np.arange(score.shape[1])
    own = 1 - 1 / score[chosen, columns]
    np.divide(-noise[:, None], score, out=score)
    score[chosen, columns] += own
    return score


class Learner:
    """Adaptive steps from a shared model; its arrays are its own copies."""

    def __init__(self, model: LogBilinear):
        self.m = model.with_params(model.flat_params().copy())
        groups, depth = self.m.bias.shape
        by_group = self.m.unigram.reshape(depth, groups).T
        self.noise = NOISE * by_group.sum(1)
        self.inside = NOISE * by_group / by_group.sum(1)[:, None]
        self.log_noise = np.log(self.noise)
        self.log_inside = np.where(self.inside > 0, np.log(np.maximum(self.inside, 1e-30)), 0.0).astype(np.float32)
        self.seen = {k: np.full(getattr(self.m, k).shape[:-1] if k in ("context", "word") else getattr(self.m, k).shape, 1e-6, np.float32) for k in LogBilinear.PARAMS}

    def _move(self, name: str, at, grad: np.ndarray) -> None:
        seen, by_row = self.seen[name], name in ("context", "word")
        seen[at] += np.einsum("...d,...d->...", grad, grad) / grad.shape[-1] if by_row else grad * grad
        rate = RATE / np.sqrt(seen[at])
        grad *= rate[..., None] if by_row else rate
        getattr(self.m, name)[at] += grad

    def step(self, flat: np.ndarray, at: np.ndarray) -> None:
        m = self.m
        order, edges = m.in_groups(flat[at])
        at = at[order]  # the tokens of a group next to one another
        target, before = flat[at], m.before(flat, at)
        mine, place = target % len(m.group), target // len(m.group)
        h = m.vector(before)
        back = np.empty_like(h)
        grads = {k: np.zeros_like(getattr(m, k)) for k in ("word", "bias")}
        columns = _with_one(h)
        h = np.ascontiguousarray(columns.T)  # its last component gathers a bias's gradient
        with np.errstate(over="ignore"):
            odds = _with_bias(-m.group, self.log_noise - m.group_bias)
            total = np.zeros((len(m.group), h.shape[1]), np.float32)
            for own in _slices(0, len(at)):
                pull = _pull(odds @ columns[:, own], self.noise, mine[own])
                np.matmul(pull.T, m.group, out=back[own])
                total += pull @ h[own]
            grads["group"], grads["group_bias"] = np.ascontiguousarray(total[:, :-1]), total[:, -1].copy()
            odds = _with_bias(-m.word, self.log_inside - m.bias)
            for g in np.flatnonzero(np.diff(edges)):
                for own in _slices(edges[g], edges[g + 1]):
                    pull = _pull(odds[g] @ columns[:, own], self.inside[g], place[own])
                    back[own] += pull.T @ m.word[g]
                    total = pull @ h[own]
                    grads["word"][g] += total[:, :-1]
                    grads["bias"][g] += total[:, -1]
        moves = [(k, slice(None), grad) for k, grad in grads.items()]
        moves.append(("position", slice(None), np.stack([np.einsum("nd,nd->d", back, b) for b in before])))
        ids = np.concatenate([flat[at - 1 - p] for p in range(CONTEXT)])
        order = _order(ids, len(m.context))
        found, begin = np.unique(ids[order], return_index=True)
        pulled = np.concatenate([back * x for x in m.position])
        moves.append(("context", found, np.add.reduceat(pulled[order], begin, axis=0)))
        for name, where, grad in moves:
            self._move(name, where, grad)


def _flatten(texts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Texts' outputs in a row, each after ``CONTEXT`` ends and closed by one, and the places of their tokens."""
    pad, end = np.full(CONTEXT, END, np.int32), np.full(1, END, np.int32)
    flat = np.concatenate([part for ids in texts for part in (pad, ids, end)])
    sizes = np.array([len(ids) + 1 for ids in texts])
    return flat, np.arange(sizes.sum()) + np.repeat(np.arange(1, len(sizes) + 1) * CONTEXT, sizes)


def _learn_batches(shared) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_memory()
        words, rest, model = shared.value
        index = Outputs(words, rest)
        learner, held, size, weight = Learner(model), [], 0, 0

        def learn() -> None:
            flat, at = _flatten(held)
            for begin in range(0, len(at), STEP):
                learner.step(flat, at[begin : begin + STEP])

        for batch in batches:
            for text in batch.column(0):
                held.append(np.fromiter(map(index.__getitem__, tokens(text.as_py())), np.int32))
                size += len(held[-1]) + 1
                if size >= 4 * STEP:
                    learn()
                    held, weight, size = [], weight + size, 0
        if held:
            learn()
            weight += size
        if weight:
            values = learner.m.flat_params()
            blocks = [values[i : i + BLOCK] for i in range(0, len(values), BLOCK)]
            yield pa.RecordBatch.from_arrays([pa.array(range(len(blocks)), pa.int32()), pa.array([float(weight)] * len(blocks)), pa.array([b.tobytes() for b in blocks], pa.binary())], names=["block", "weight", "content"])

    return run


def _average_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    sums: dict[int, tuple[np.ndarray, float]] = {}
    for batch in batches:
        for block, weight, content in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
            total, mass = sums.get(block, (0.0, 0.0))
            sums[block] = total + weight * np.frombuffer(content.as_py(), np.float32).astype(np.float64), mass + weight
    if sums:
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([(t / m).astype(np.float32).tobytes() for t, m in sums.values()], pa.binary())], names=["block", "content"])


def trained(texts: DataFrame, words: list[bytes], rest: int, start: LogBilinear, n_tokens: int) -> LogBilinear:
    """The average of the models that learners make of all ``texts``; without any, ``start``."""
    shared = texts.sparkSession.sparkContext.broadcast((words, rest, start))
    learned = texts.select("text").coalesce(max(1, -(-n_tokens // LEARNER_TOKENS))).mapInArrow(_learn_batches(shared), "block int, weight double, content binary")
    blocks = learned.repartition("block").mapInArrow(_average_batches, "block int, content binary").collect()
    if not blocks:
        return start
    return start.with_params(np.concatenate([np.frombuffer(r.content, np.float32) for r in sorted(blocks, key=lambda r: r.block)]))


def _score_batches(shared) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_memory()
        words, n_vocab, rest, counts, model, base_all, rest_all, end_count = shared.value
        index = {w: i for i, w in enumerate(words)}
        unknown = len(words)
        place = np.array([i + 1 + rest if i < n_vocab else rest_class(w, rest) for i, w in enumerate(words)] + [0], np.int32)
        use = np.append(np.log10(counts + 1), 0.0)  # that of unknown words is added in the join
        log_all, log_rest = float(np.log10(base_all)), np.log10(rest_all)
        inner = np.where(place > rest, 0.0, use - log_rest[np.minimum(place, rest)])
        inner[unknown] = 0.0
        known = np.append(counts > 0, False)
        end_base = float(np.log10(end_count + 1))
        get, digest = index.get, xxhash.xxh64_intdigest

        def out(rows: list) -> pa.RecordBatch:
            flat, at = _flatten([r[2] for r in rows])
            ends = np.cumsum([len(r[2]) + 1 for r in rows])
            sums = np.add.reduceat(model.log_probs(flat, at), np.append(0, ends[:-1]))
            cols = list(zip(*rows, strict=True))
            return pa.RecordBatch.from_arrays(
                [pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.bool_()), pa.array([len(x) + 1 for x in cols[2]], pa.int64()), pa.array(cols[3], pa.int64()), pa.array(cols[4], pa.float64()), pa.array(sums + np.array(cols[5]), pa.float64()), pa.array(cols[6], pa.list_(pa.int64())), pa.array(cols[7], pa.list_(pa.int32()))],
                names=["doc_id", "held_out", "n_tokens", "n_known", "base_score", "score", "rare", "times"],
            )

        held, size = [], 0
        for batch in batches:
            for doc, text, away in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist(), strict=True):
                found = tokens(text.as_py())
                ids = np.fromiter(map(get, found, repeat(unknown)), np.int64, len(found))
                to, own = place[ids], float(inner[ids].sum())
                missing = np.flatnonzero(ids == unknown)
                others = [found[i] for i in missing.tolist()]
                rare = Counter(others)
                of = {w: rest_class(w, rest) for w in rare}
                to[missing] = np.fromiter(map(of.__getitem__, others), np.int32, len(others))
                own -= float(log_rest[to[missing]].sum())
                hashes = np.array([digest(w, 42) for w in rare], np.uint64).view(np.int64)
                base = float(use[ids].sum()) + end_base - (len(found) + 1) * log_all
                held.append((doc, away, to, int(known[ids].sum()) + (end_count > 0), base, own, hashes, list(rare.values())))
                size += len(to) + 1
                if size >= 4 * BATCH:
                    yield out(held)
                    held, size = [], 0
        if held:
            yield out(held)

    return run


def language_model_scores(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", folds: int = 7, held_fold: int = 2, vocab: int = VOCAB, rest: int = REST, common: int = COMMON) -> DataFrame:
    """``doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score``, one row per input row.

    Rows whose id's fold is ``held_fold`` are scored only; the others, null ids
    among them, are learned from as well.  Null and empty texts are an end alone.
    Repeated rows count and stay.  Without training rows every count is zero and
    the model is the smoothed unigram distribution.  Words of equal frequency are
    all in the vocabulary or none is.  Other columns are not read.
    """
    spark = docs.sparkSession
    held = F.coalesce(fold(F.col(doc_id), folds) == held_fold, F.lit(False))
    rows = docs.select(F.col(doc_id).cast("bigint").alias("doc_id"), F.col(text).cast("string").alias("text"), held.alias("held"))
    counts = materialise(word_counts(rows), "word-counts")
    by_rest = {r.r: (r.c, r.k) for r in counts.where("c > 0").groupBy(_rest_column(F.col("word"), rest).alias("r")).agg(F.sum("c").alias("c"), F.count("*").alias("k")).collect()}
    n_words, kinds = (sum(x[i] for x in by_rest.values()) for i in (0, 1))
    n_ends = rows.where(~F.col("held")).count()
    train_tokens, kinds = n_words + n_ends, kinds + (n_ends > 0)
    top = sorted(((bytes(r.word), r.c) for r in most_frequent(counts, "c", vocab).collect()), key=lambda x: (-x[1], x[0]))
    words = [w for w, _ in top]
    seen = set(words)
    more = [(bytes(r.word), r.c) for r in most_frequent(counts, "total", common).collect() if bytes(r.word) not in seen]
    rest_tokens, rest_kinds = (np.array([0] + [by_rest.get(r + 1, (0, 0))[i] for r in range(rest)]) for i in (0, 1))
    for w, c in top:
        rest_tokens[rest_class(w, rest)] -= c
        rest_kinds[rest_class(w, rest)] -= 1
    rest_all = (rest_tokens + rest_kinds + 1).astype(np.float64)
    uses = np.concatenate([[n_ends], rest_tokens[1:], [c for _, c in top]]).astype(np.float64)
    model = trained(rows.where(~F.col("held")), words, rest, LogBilinear.start(uses), train_tokens)
    table_counts = np.array([c for _, c in top + more], np.float64)
    base_all = train_tokens + kinds + 1
    shared = spark.sparkContext.broadcast((words + [w for w, _ in more], len(words), rest, table_counts, model, base_all, rest_all, n_ends))
    scored = rows.mapInArrow(_score_batches(shared), "doc_id bigint, held_out boolean, n_tokens bigint, n_known bigint, base_score double, score double, rare array<bigint>, times array<int>")
    first = materialise(scored.withColumn("rid", F.monotonically_increasing_id()), "scores")
    uses_of = first.select("rid", F.inline(F.arrays_zip("rare", "times"))).toDF("rid", "h", "n")
    met = uses_of.join(counts.where("c > 0").select(F.xxhash64("word").alias("h"), "c"), "h")
    sums = met.groupBy("rid").agg(F.sum(F.col("n") * F.log10(F.col("c") + 1)).alias("b"), F.sum("n").alias("k"))
    added = F.coalesce("b", F.lit(0.0))
    return first.join(sums, "rid", "left").select(
        "doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce("k", F.lit(0))).cast("bigint").alias("n_known"), F.lit(train_tokens).cast("bigint").alias("train_tokens"),
        (F.col("base_score") + added).alias("base_score"), (F.col("score") + added).alias("score"),
    )
