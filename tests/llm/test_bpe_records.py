import hashlib
import random
import zlib

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from tokenizers import Tokenizer

from overlapix.llm import byte_bpe, records
from tests.llm.helpers import EDGES, docs_frame

RANKS, JSON = P.path("byte_bpe_multi_50k.tiktoken"), P.path("byte_bpe_50k.json")


@pytest.fixture(scope="module")
def reference():
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=byte_bpe.read_ranks(RANKS), special_tokens={})


def fuzz(n=3000):
    rng, pool = random.Random(11), "  \n\t  　'abéß中١²Ⅷ́א.,!​\U0001f600"
    return ["".join(rng.choice(pool) if rng.random() < 0.85 else chr(rng.randrange(0x21, 0xD7FF)) for _ in range(rng.randrange(25))) for _ in range(n)]


def test_same_ids_as_reference(reference):
    texts = fuzz() + ["it's we'll  two  spaces", " lead", "trail ", "\r\n x\r y"]
    for text, raw in zip(texts, byte_bpe.encoder(RANKS, P.PATTERN).encode(texts), strict=True):
        assert np.frombuffer(raw, "<u4").tolist() == reference.encode_ordinary(text), ascii(text)


def test_json_tokenizer_with_special_string():
    texts = [*fuzz(), "a <|endoftext|> b<|endoftext|>"]
    want = [x.ids for x in Tokenizer.from_file(JSON).encode_batch(texts, add_special_tokens=False)]
    assert [np.frombuffer(x, "<u4").tolist() for x in byte_bpe.encoder(JSON).encode(texts)] == want


def test_round_trip_and_offsets(spark, reference):
    df = byte_bpe.encode_texts(docs_frame(spark, EDGES), RANKS, P.PATTERN, keep=("doc_id", "text"))
    done = byte_bpe.with_offsets(byte_bpe.decode_ids(df, RANKS, P.PATTERN), RANKS, P.PATTERN).collect()
    assert len(done) == len(EDGES)
    for r in done:
        text = r.text or ""
        assert bytes(r.decoded) == text.encode()
        ids = np.frombuffer(bytes(r.ids), "<u4").tolist()
        assert ids == reference.encode_ordinary(text)
        for i, s, e in zip(ids, r.starts, r.ends, strict=True):
            piece = reference.decode_single_token_bytes(i)
            assert piece in text[s:e].encode() and (len(piece) == len(text[s:e].encode()) or e - s <= len(piece) + 1)


def test_one_pass_is_the_same(spark):
    df = docs_frame(spark, EDGES)
    two = byte_bpe.decode_ids(byte_bpe.encode_texts(df, RANKS, P.PATTERN), RANKS, P.PATTERN)
    one = byte_bpe.encode_and_decode(df, RANKS, P.PATTERN)
    rows = lambda x: sorted(((r.doc_id, bytes(r.ids), bytes(r.decoded)) for r in x.collect()), key=repr)
    assert rows(one) == rows(two) and one.where("round_trip").count() == len(EDGES)


def test_records_round_trip(spark):
    rows = EDGES + [(100 - i, f"text {i} " * (i % 7)) for i in range(60)]
    manifest = records.write_records(docs_frame(spark, rows), JSON)
    got = sorted(((r.start, r.doc_id, r.n_tokens, r.ids_crc32) for r in records.read_digests(manifest).collect()))
    tok, at, want = Tokenizer.from_file(JSON), 0, []
    for i, t in sorted(rows, key=lambda x: (x[0] is not None, x[0] or 0, x[1] is not None, x[1] or "")):
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
        want.append((at, i, len(ids), zlib.crc32(ids.tobytes())))
        at += len(ids)
    assert got == want
    file = manifest.orderBy("part", "seq").first()
    first, _ = records.read_record(spark, file.data, file.offsets, 0)
    assert first is None
    assert records.read_record(spark, file.data, file.offsets, file.n_docs - 1) is not None


def test_damage_is_found(tmp_path):
    raw = records.frame(5, np.array([1, 2, 70_000], "<u4"))
    (tmp_path / "x").write_bytes(raw[:-6] + b"\0" + raw[-5:])
    with (tmp_path / "x").open("rb") as f, pytest.raises(ValueError):
        records.unframe(f)
    (tmp_path / "y").write_bytes(raw)
    with (tmp_path / "y").open("rb") as f:
        assert records.unframe(f)[1].tolist() == [1, 2, 70_000] and records.unframe(f) is None


def test_empty_table(spark):
    assert records.read_digests(records.write_records(docs_frame(spark, []), JSON)).count() == 0
    assert byte_bpe.encode_texts(docs_frame(spark, []), JSON).count() == 0


def test_digest_is_of_little_endian_ids(spark, reference):
    r = byte_bpe.encode_texts(docs_frame(spark, [(1, "Hello there")]), RANKS, P.PATTERN).first()
    assert hashlib.sha256(bytes(r.ids)).hexdigest() == hashlib.sha256(np.array(reference.encode_ordinary("Hello there"), "<u4").tobytes()).hexdigest()


def test_cuts_without_a_call_a_piece():
    """Each piece cost two calls to look for white space at its ends."""
    import sys

    def plain(text):
        parts = text.split(" ")
        return text if any(not p or p[0].isspace() or p[-1].isspace() for p in parts) else parts

    spaces = [chr(c) for c in range(0x110000) if chr(c).isspace()]
    for t in ["", *(f.replace("_", s) for s in spaces for f in ("_", "a_b", "a _b", "a_ b", "a_", "_a", "a b_c d", "a__b c"))]:
        assert byte_bpe._pieces(t) == plain(t), ascii(t)
    calls = []
    sys.setprofile(lambda frame, event, arg: calls.append(event))
    byte_bpe._pieces("word " * 999 + "end")
    sys.setprofile(None)
    assert len(calls) < 50
