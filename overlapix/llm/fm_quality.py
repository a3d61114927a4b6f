"""Text quality by a factorisation machine.

Features of a text are hashed words, statistics of its structure cut into
ranges, and the length that the table states.  Beside a weight each feature has
a short factor vector; the sum over all pairs of features of their factors'
products is scored in linear time as half of (square of the sum minus sum of
the squares).  The model is fitted in numpy on a bounded sample of labelled
rows and sent to the executors; its size depends on its parameters alone.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Hashed words share this many weights.
WORD_SLOTS = 1 << 15
#: Ranges of one structure statistic.
RANGES = 24
FACTORS = 6
#: Labelled rows that the model is fitted on at most, by order of a hash of their id.
TRAIN_ROWS = 12_000
EPOCHS = 6
STATISTICS = ("chars", "words", "lines", "mean_word", "upper", "digit", "symbol", "space", "distinct", "top_word", "repeat_bigram", "repeat_line", "stop_end", "pipe", "mark_run", "exclaim", "no_letter", "stated")
SLOTS = WORD_SLOTS + len(STATISTICS) * RANGES
WORD = re.compile(r"[^\W\d_]+")
#: Statistics that are shares of a text, cut evenly on a square-root scale.
_SHARES = frozenset("upper digit symbol space distinct top_word repeat_bigram repeat_line stop_end pipe mark_run exclaim no_letter".split())
_ALPHA = re.compile(r"[^\W\d_]")
_MARKS = re.compile(r"[!?$%&*#=+@^~<>{}\[\]|\\/_]{2,}")


def statistics(text: str, stated: int | None, found: list[str]) -> dict[str, float]:
    """``found`` are the text's words of letters."""
    chars = len(text)
    words = text.split()
    n = max(1, len(words))
    lines = [x for x in text.split("\n") if x.strip()]
    counts = Counter(words)
    letters = sum(map(len, found))
    size = max(1, chars)
    spaces = text.count(" ")
    return {
        "chars": chars, "words": len(words), "lines": len(lines), "mean_word": chars / n,
        "upper": sum(map(str.isupper, words)) / n, "digit": sum(map(text.count, "0123456789")) / size,
        "symbol": (chars - letters - spaces - text.count("\n")) / size, "space": spaces / size,
        "distinct": len(counts) / n, "top_word": max(counts.values(), default=0) / n,
        "repeat_bigram": 1 - len(set(zip(words, words[1:], strict=False))) / max(1, len(words) - 1) if len(words) > 1 else 0.0,
        "repeat_line": 1 - len(set(lines)) / max(1, len(lines)),
        "stop_end": sum(x.rstrip()[-1:] in (".", "!", "?", "…", "。") for x in lines) / max(1, len(lines)),
        "pipe": min(1.0, text.count("|") / n), "mark_run": min(1.0, len(_MARKS.findall(text)) / n),
        "exclaim": min(1.0, text.count("!") / n), "no_letter": sum(not w.isalpha() and not _ALPHA.search(w) for w in counts) / max(1, len(counts)),
        "stated": abs((chars if stated is None else stated) - chars),
    }


def _slot(word: str, known: dict[str, int]) -> int:
    if len(known) > 100_000:
        known.clear()
    slot = known[word] = zlib.crc32(word.encode("utf-8", "surrogatepass")) % WORD_SLOTS
    return slot


def features(text: str | None, stated: int | None, known: dict[str, int]) -> tuple[np.ndarray, np.ndarray]:
    """Slots and values of one text.  ``known`` keeps the slots of words seen."""
    text = text or ""
    found = WORD.findall(text.lower())
    slots: list[int] = []
    for i, (name, x) in enumerate(statistics(text, stated, found).items()):
        r = int(math.sqrt(min(1.0, max(0.0, x))) * (RANGES - 1)) if name in _SHARES else min(RANGES - 1, int(2 * math.log1p(x)))
        slots.append(WORD_SLOTS + i * RANGES + r)
    values = np.ones(len(slots), np.float32)
    counts = Counter(found)
    if counts:
        weight = np.log1p(np.fromiter(counts.values(), np.float32, len(counts)))
        values = np.concatenate([values, weight / np.sqrt((weight * weight).sum())])
        get = known.get
        slots += [s if (s := get(w)) is not None else _slot(w, known) for w in counts]
    return np.array(slots, np.int32), values


@dataclass
class Model:
    bias: float
    weight: np.ndarray
    factor: np.ndarray

    def raw(self, slots: np.ndarray, values: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Scores before the sigmoid, of texts whose features follow one another."""
        linear = np.add.reduceat(self.weight[slots] * values, starts)
        part = self.factor[slots] * values[:, None]
        total = np.add.reduceat(part, starts, axis=0)
        squares = np.add.reduceat(part * part, starts, axis=0)
        return self.bias + linear + 0.5 * (total * total - squares).sum(1)

    def score(self, slots: np.ndarray, values: np.ndarray, starts: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw(slots, values, starts), -30, 30)))


def fit(rows: list[tuple[np.ndarray, np.ndarray, int]], seed: int = 7) -> Model:
    """Adaptive gradient steps over mini-batches; rows are (slots, values, label).
    Without rows every text scores the neutral half."""
    rng = np.random.default_rng(seed)
    model = Model(0.0, np.zeros(SLOTS, np.float32), rng.normal(0, 0.02, (SLOTS, FACTORS)).astype(np.float32))
    if not rows:
        model.factor[:] = 0
        return model
    share = np.clip(np.mean([y for *_, y in rows]), 0.02, 0.98)
    model.bias = float(np.log(share / (1 - share)))
    seen_w, seen_f, seen_b = np.full(SLOTS, 1e-3, np.float32), np.full((SLOTS, FACTORS), 1e-3, np.float32), 1e-3
    for epoch in range(EPOCHS):
        order = rng.permutation(len(rows))
        for i in range(0, len(rows), 64):
            part = [rows[j] for j in order[i : i + 64]]
            slots, values = (np.concatenate([r[c] for r in part]) for c in (0, 1))
            sizes = np.array([len(r[0]) for r in part])
            starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
            error = model.score(slots, values, starts) - np.array([r[2] for r in part])
            each = np.repeat(error, sizes).astype(np.float32) / len(part) * 8
            scaled = model.factor[slots] * values[:, None]
            total = np.repeat(np.add.reduceat(scaled, starts, axis=0), sizes, axis=0)
            unique, back = np.unique(slots, return_inverse=True)
            grad_w = np.bincount(back, each * values, len(unique)) + 2e-4 * model.weight[unique]
            local = each[:, None] * values[:, None] * (total - scaled)
            grad_f = np.stack([np.bincount(back, local[:, c], len(unique)) for c in range(FACTORS)], 1) + 2e-4 * model.factor[unique]
            seen_w[unique] += grad_w**2
            seen_f[unique] += grad_f**2
            rate = 0.15 / (1 + epoch)
            model.weight[unique] -= (rate * grad_w / np.sqrt(seen_w[unique])).astype(np.float32)
            model.factor[unique] -= (0.3 * rate * grad_f / np.sqrt(seen_f[unique])).astype(np.float32)
            grad_b = float(error.mean())
            seen_b += grad_b**2
            model.bias -= rate * grad_b / np.sqrt(seen_b)
    return model


def _feature_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    known: dict[str, int] = {}
    for batch in batches:
        rows = [features(t, n, known) for t, n in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True)]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([s.tobytes() for s, _ in rows], pa.binary()), pa.array([v.tobytes() for _, v in rows], pa.binary())], names=["doc_id", "slots", "values"])


def _score_batches(model: Model, name: str) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, int] = {}
        for batch in batches:
            out = []
            for a in range(0, batch.num_rows, 256):
                part = batch.slice(a, 256)
                rows = [features(t, n, known) for t, n in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True)]
                starts = np.concatenate([[0], np.cumsum([len(s) for s, _ in rows])[:-1]]).astype(int)
                out.append(model.score(np.concatenate([s for s, _ in rows]), np.concatenate([v for _, v in rows]), starts))
            score = np.concatenate(out) if out else np.zeros(0)
            yield pa.RecordBatch.from_arrays([*batch.columns[2:], pa.array(score, pa.float64())], names=[*batch.schema.names[2:], name])

    return run


def fold(doc_id: Column, folds: int) -> Column:
    """crc32 of the id as text, modulo ``folds``; a null id has a null fold."""
    return F.crc32(doc_id.cast("string").cast("binary")) % folds


def _texts(docs: DataFrame, text: str) -> tuple[Column, Column]:
    stated = F.col("n_chars").cast("bigint") if "n_chars" in docs.columns else F.lit(None).cast("bigint")
    return F.col(text).cast("string").alias("__text"), stated.alias("__stated")


def train(docs: DataFrame, labels: DataFrame, text: str = "text", doc_id: str = "doc_id", label: str = "quality", rows: int = TRAIN_ROWS) -> Model:
    """Fit on at most ``rows`` labelled documents outside fold 0 of 5, taken by
    the order of a hash of their ids.  Null ids and labels are left out; an id
    with several labels counts once, by its largest; repeated documents count
    as they are, within the same bound."""
    given = labels.select(F.col("doc_id").cast("bigint").alias("__id"), F.col(label).cast("int").alias("__y")).where("__id is not null and __y is not null")
    given = given.where(fold(F.col("__id"), 5) != 0).groupBy("__id").agg(F.max("__y").alias("__y"))
    sample = given.orderBy(F.xxhash64("__id"), "__id").limit(rows)
    picked = docs.join(F.broadcast(sample), docs[doc_id].cast("bigint") == F.col("__id")).select(F.col("__id").alias("doc_id"), *_texts(docs, text))
    made = picked.mapInArrow(_feature_batches, "doc_id bigint, slots binary, values binary").limit(rows).collect()
    y = {r["__id"]: r["__y"] for r in sample.collect()}
    made.sort(key=lambda r: (r.doc_id, bytes(r.slots)))
    return fit([(np.frombuffer(bytes(r["slots"]), np.int32), np.frombuffer(bytes(r["values"]), np.float32), int(y[r.doc_id] == 1)) for r in made])


def scored(docs: DataFrame, model: Model, keep: tuple[str, ...] = ("doc_id",), text: str = "text", name: str = "score") -> DataFrame:
    """``keep`` columns and the score (0 to 1) as ``name``, one row per input row,
    nulls and empty texts included."""
    kept = docs.select(*keep)
    ddl = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields), f"`{name}` double"])
    return docs.select(*_texts(docs, text), *keep).mapInArrow(_score_batches(model, name), ddl)
