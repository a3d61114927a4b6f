"""Token counts under a unigram vocabulary, without building the tokens.

Aho-Corasick enumerates the vocabulary's matches in a word; dynamic programming
over end positions carries the best score and the number of pieces.  Ties go to
the match that starts first, and a later one must score strictly higher, which
is what a left-to-right search over start positions does.  A character that no
single-character piece covers scores ``UNKNOWN_PENALTY`` below the lowest score;
with byte pieces in the vocabulary it counts one piece a byte.

Words are what stands between spaces, each with a leading mark, so a text's
count is the sum of its words' counts and each distinct word is searched once
per worker.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import lru_cache

import ahocorasick
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Fixed value: the character that stands for a space.
SPACE = "▁"
#: Fixed value: how far below the lowest score an unknown character is.
UNKNOWN_PENALTY = 10.0
CACHE_WORDS = 800_000


def read_pieces(path: str) -> list[tuple[str, float]]:
    """Pieces and scores of a sentencepiece file, in id order."""
    model = sentencepiece.SentencePieceProcessor(model_file=path)
    return [(model.id_to_piece(i), model.get_score(i)) for i in range(model.get_piece_size())]


class UnigramCounter:
    def __init__(self, pieces: list[tuple[str, float]], byte_fallback: bool = True) -> None:
        self.machine = ahocorasick.Automaton()
        for piece, score in dict(pieces).items():
            if piece:
                self.machine.add_word(piece, (len(piece), score))
        self.machine.make_automaton()
        names = dict(pieces)
        self.single = {p for p in names if len(p) == 1}
        self.unknown = min(s for _, s in pieces) - UNKNOWN_PENALTY
        self.bytes = byte_fallback and all(f"<0x{b:02X}>" in names for b in range(256))
        self.known: dict[str, int] = {}

    def word(self, word: str) -> int:
        """Pieces of one word, mark included."""
        n = len(word)
        best = [float("-inf")] * (n + 1)
        count = [0] * (n + 1)
        best[0] = 0.0
        if self.single.issuperset(word):
            for end, (size, score) in self.machine.iter(word):
                to, at = end + 1, end + 1 - size
                value = best[at] + score
                if value > best[to]:
                    best[to] = value
                    count[to] = count[at] + 1
            return count[n]
        matches: list[list[tuple[int, float]]] = [[] for _ in range(n)]
        for end, match in self.machine.iter(word):
            matches[end].append(match)
        open_run = [False] * (n + 1)  # the best path ends in unknown characters, which are one piece together
        for end in range(n):
            to = end + 1
            for size, score in matches[end]:
                value = best[to - size] + score
                if value > best[to]:
                    best[to], count[to], open_run[to] = value, count[to - size] + 1, False
            if word[end] not in self.single:
                value = best[end] + self.unknown
                if value > best[to]:
                    more = len(word[end].encode("utf-8", "surrogatepass")) if self.bytes else not open_run[end]
                    best[to], count[to], open_run[to] = value, count[end] + more, True
        return count[n]

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        marked = text.replace(" ", SPACE)
        words = (marked if marked[0] == SPACE else SPACE + marked).split(SPACE)[1:]
        known = self.known
        total = 0
        for w in words:
            n = known.get(w)
            if n is None:
                if len(known) >= CACHE_WORDS:
                    known.clear()
                n = known[w] = self.word(SPACE + w)
            total += n
        return total


@lru_cache(maxsize=2)
def counter(path: str) -> UnigramCounter:
    return UnigramCounter(read_pieces(path))


def _batches(path: str) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tool = counter(path)
        for batch in batches:
            counts = [tool.count(x.as_py()) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64())], names=["doc_id", "n_tokens"])

    return run


def token_counts(docs: DataFrame, path: str, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``(doc_id, n_tokens)``, one row per input row.  Null and empty texts have no
    tokens; repeated rows and null ids stay; other columns are not read."""
    return docs.select(F.col(doc_id).cast("bigint").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(_batches(path), "doc_id bigint, n_tokens bigint")
