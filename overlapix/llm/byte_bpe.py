"""Byte-level BPE encoding and decoding with the tokenizers library over Arrow batches.

Byte-level models see a byte as a printable character; the table between the
two is built here by its public rule.  A rank file becomes a merge list: every
split of a token into two tokens is a merge of that token's rank.

Texts are cut at single spaces first.  A piece between two spaces that neither
starts nor ends in white space is encoded the same wherever it stands, since
the pre-tokeniser's pattern looks back at nothing and ahead only past white
space; so each distinct piece is encoded once per worker and looked up after
that.  Texts with other white space at a cut are encoded whole.
"""

from __future__ import annotations

import base64
import os
import re
from array import array
from collections.abc import Callable, Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
import tokenizers
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from tokenizers import Regex, Tokenizer, models, pre_tokenizers

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

#: Pieces kept per worker; a full table starts anew, results never depend on it.
CACHE_PIECES = 600_000
#: The same beside the tables of a decoder.
ROUND_TRIP_PIECES = 200_000
#: Below this character the classes of letters and digits are the same in every Unicode version.
LATIN_END = "\u0250"
#: Fixed value: the public pattern of byte-level BPE that cuts a text into words.
WORDS = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+")


@lru_cache(maxsize=1)
def byte_to_char() -> dict[int, str]:
    """Printable Latin-1 bytes stand for themselves, the others for code points from 256 on, in byte order."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    spare = (b for b in range(256) if b not in set(plain))
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(spare)}


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}


def tokenizer_from_ranks(path: str, pattern: str) -> Tokenizer:
    """A tokenizer that merges as the rank file says: lowest rank first, leftmost first."""
    ranks, chars = read_ranks(path), byte_to_char()
    name = {token: "".join(chars[b] for b in token) for token in ranks}
    merges = [(name[token[:i]], name[token[i:]]) for token, _ in sorted(ranks.items(), key=lambda x: x[1]) for i in range(1, len(token)) if token[:i] in ranks and token[i:] in ranks]
    tok = Tokenizer(models.BPE(vocab={name[t]: r for t, r in ranks.items()}, merges=merges, ignore_merges=True))
    tok.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.Split(Regex(pattern), "isolated"), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
    return tok


@lru_cache(maxsize=4)
def load_tokenizer(path: str, pattern: str | None = None) -> Tokenizer:
    """``pattern`` is given for rank files; a ``.json`` file carries its own."""
    return tokenizer_from_ranks(path, pattern) if pattern else Tokenizer.from_file(path)


class PieceEncoder:
    """text -> ids as little-endian unsigned 32-bit bytes."""

    def __init__(self, tok: Tokenizer, pieces: int = CACHE_PIECES) -> None:
        self.tok, self.pieces = tok, pieces
        self.inner: dict[str, bytes] = {}

        self.words: dict[str, bytes] = {}
        self.latin = {b: c for b, c in byte_to_char().items()}
        self.special = [t.content for t in tok.get_added_tokens_decoder().values()]

    def _run(self, texts: list[str]) -> list[bytes]:
        """Whole texts, all of it by the library."""
        return [np.array(x.ids, "<u4").tobytes() for x in self.tok.encode_batch(texts, add_special_tokens=False)]

    def _word(self, word: str) -> bytes:
        """One match of the pattern, merged by the library's model."""
        if word.isascii() and word.isprintable():
            mapped = word.replace(" ", self.latin[0x20])
        else:
            mapped = word.encode("utf-8", "surrogatepass").decode("latin-1").translate(self.latin)
        ids = self.words[word] = array("I", [t.id for t in self.tok.model.tokenize(mapped)]).tobytes()
        return ids

    def _run_pieces(self, pieces: list[str]) -> list[bytes]:
        """The pieces with a space before each."""
        out, known, new = [], self.words, self._word
        if len(known) > self.pieces:
            known.clear()
        body = "\n".join(pieces)  # a special token is looked for in all pieces at once
        special = [s for s in self.special if s in body]
        for p in pieces:
            if not p.isascii() and max(p) >= LATIN_END or (special and any(s in p for s in special)):
                out += self._run([f" {p}"])  # the library's own tables of character classes
            elif p.isalpha():
                w = f" {p}"
                out.append(known.get(w) or new(w))
            elif p[-1] in ".," and p[:-1].isalpha():
                w, e = f" {p[:-1]}", p[-1]
                out.append((known.get(w) or new(w)) + (known.get(e) or new(e)))
            else:
                out.append(b"".join([known.get(w) or new(w) for w in WORDS.findall(f" {p}")]))
        return out

    def encode(self, texts: Iterable[str]) -> list[bytes]:
        cut = [_pieces(t) for t in texts]
        wanted: set[str] = set()
        for c in cut:
            if type(c) is list:
                wanted.update(c[1:])
        if len(self.inner) + len(wanted) > self.pieces:
            self.inner.clear()
        new = list(wanted - self.inner.keys())
        for i in range(0, len(new), 50_000):
            part = new[i : i + 50_000]
            self.inner.update(zip(part, self._run_pieces(part), strict=True))
        whole = self._run([c[0] if type(c) is list else c for c in cut])  # the first piece has no space before it
        look = self.inner.__getitem__
        return [w + b"".join(map(look, c[1:])) if type(c) is list else w for c, w in zip(cut, whole, strict=True)]


#: A space beside white space.
_UNSAFE = re.compile(r" (?:\s|(?<=\s ))").search


def _pieces(text: str) -> list[str] | str:
    """The pieces between single spaces, or the text itself if a cut is not safe."""
    if not text or text[0].isspace() or text[-1].isspace() or _UNSAFE(text):
        return text
    return text.split(" ")


_ENCODERS: dict[tuple, PieceEncoder] = {}


def encoder(path: str, pattern: str | None = None, pieces: int = CACHE_PIECES) -> PieceEncoder:
    if (path, pattern) not in _ENCODERS:
        _ENCODERS[path, pattern] = PieceEncoder(load_tokenizer(path, pattern), pieces)
    return _ENCODERS[path, pattern]


class ByteTable:
    """id -> bytes, read back from the vocabulary's characters."""

    def __init__(self, tok: Tokenizer) -> None:
        back = {c: b for b, c in byte_to_char().items()}
        special = {i for i, t in tok.get_added_tokens_decoder().items() if t.special}
        self.of = {i: t.encode() if i in special or any(c not in back for c in t) else bytes(back[c] for c in t) for t, i in tok.get_vocab().items()}

    def decode(self, ids: np.ndarray) -> bytes:
        return b"".join(map(self.of.__getitem__, ids.tolist()))

    def offsets(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Start and end code point of each token; a token inside a character spans that character."""
        sizes = np.fromiter((len(self.of[i]) for i in ids.tolist()), np.int64, len(ids))
        raw = np.frombuffer(self.decode(ids), np.uint8)
        lead = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])
        ends = np.cumsum(sizes)
        starts = ends - sizes
        begins = np.where(starts < len(raw), lead[np.minimum(starts + 1, len(raw))] - 1, lead[-1])
        return begins, lead[ends]


_TABLES: dict[tuple, ByteTable] = {}


def byte_table(path: str, pattern: str | None = None) -> ByteTable:
    if (path, pattern) not in _TABLES:
        _TABLES[path, pattern] = ByteTable(load_tokenizer(path, pattern))
    return _TABLES[path, pattern]


def small_parts(batch: pa.RecordBatch, column: int, chars: int = 1 << 22) -> Iterator[pa.RecordBatch]:
    """Slices of a batch whose texts hold about ``chars`` bytes each."""
    size = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    group = np.cumsum(size) // chars
    cuts = [0, *(np.flatnonzero(np.diff(group)) + 1).tolist(), batch.num_rows]
    for a, b in zip(cuts, cuts[1:], strict=False):
        if b > a:
            yield batch.slice(a, b - a)


def _encode_batches(path: str, pattern: str | None) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tool = encoder(path, pattern)
        for batch in batches:
            for part in small_parts(batch, 0):
                ids = tool.encode(x or "" for x in part.column(0).to_pylist())
                yield pa.RecordBatch.from_arrays([*part.columns[1:], pa.array(ids, pa.binary())], names=[*part.schema.names[1:], "ids"])

    return run


def _round_batches(path: str, pattern: str | None) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tool, table = encoder(path, pattern, ROUND_TRIP_PIECES), byte_table(path, pattern)
        for batch in batches:
            for part in small_parts(batch, 0):
                texts = [x or "" for x in part.column(0).to_pylist()]
                ids = tool.encode(texts)
                back = [table.decode(np.frombuffer(x, "<u4")) for x in ids]
                same = [b == t.encode("utf-8", "surrogatepass") for b, t in zip(back, texts, strict=True)]
                yield pa.RecordBatch.from_arrays([*part.columns[1:], pa.array(ids, pa.binary()), pa.array(back, pa.binary()), pa.array(same, pa.bool_())], names=[*part.schema.names[1:], "ids", "decoded", "round_trip"])
        tool.inner.clear()  # workers outlive their tasks
        tool.words.clear()

    return run


def _decode_batches(path: str, pattern: str | None) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = byte_table(path, pattern)
        for batch in batches:
            for part in small_parts(batch, 0):
                out = [table.decode(np.frombuffer(x, "<u4")) for x in part.column(0).to_pylist()]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(out, pa.binary())], names=[*part.schema.names, "decoded"])

    return run


def _offset_batches(path: str, pattern: str | None) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = byte_table(path, pattern)
        for batch in batches:
            for part in small_parts(batch, 0):
                spans = [table.offsets(np.frombuffer(x, "<u4")) for x in part.column(0).to_pylist()]
                cols = [pa.array([s[i].tolist() for s in spans], pa.list_(pa.int64())) for i in (0, 1)]
                yield pa.RecordBatch.from_arrays([*part.columns, *cols], names=[*part.schema.names, "starts", "ends"])

    return run


def _ddl(df: DataFrame, more: str) -> str:
    return ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields), more])


def encode_texts(docs: DataFrame, path: str, pattern: str | None = None, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns plus ``ids`` BINARY: the token ids of each whole text as
    little-endian unsigned 32-bit integers, in order.  Null texts count as empty
    and give empty ids.  Repeated rows stay; other columns are not read."""
    kept = docs.select(*keep)
    return docs.select(F.col(text).cast("string").alias("__text"), *keep).mapInArrow(_encode_batches(path, pattern), _ddl(kept, "ids binary"))


def encode_and_decode(docs: DataFrame, path: str, pattern: str | None = None, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns, ``ids``, ``decoded`` and ``round_trip`` in one pass, so that one
    worker a task holds the tables; otherwise as :func:`encode_texts` and :func:`decode_ids`."""
    kept = docs.select(*keep)
    return docs.select(F.col(text).cast("string").alias("__text"), *keep).mapInArrow(_round_batches(path, pattern), _ddl(kept, "ids binary, decoded binary, round_trip boolean"))


def decode_ids(encoded: DataFrame, path: str, pattern: str | None = None) -> DataFrame:
    """Adds ``decoded`` BINARY: the bytes that ``ids`` stand for, joined before any
    reading as characters, so characters split over tokens come back whole."""
    rest = [c for c in encoded.columns if c != "ids"]
    df = encoded.select("ids", *rest)
    return df.mapInArrow(_decode_batches(path, pattern), _ddl(df, "decoded binary"))


def with_offsets(encoded: DataFrame, path: str, pattern: str | None = None) -> DataFrame:
    """Adds ``starts`` and ``ends``: the code points each token covers."""
    rest = [c for c in encoded.columns if c != "ids"]
    df = encoded.select("ids", *rest)
    return df.mapInArrow(_offset_batches(path, pattern), _ddl(df, "starts array<bigint>, ends array<bigint>"))


__all__ = ["byte_to_char", "decode_ids", "encode_texts", "encoder", "read_ranks", "tokenizer_from_ranks", "tokenizers", "with_offsets"]
