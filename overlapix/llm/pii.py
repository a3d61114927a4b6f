"""Personal data by weak supervision.

Wide patterns propose spans: whole matches of the base patterns, the sound parts
of matches that fail their check because they run on into the next number,
written-out addresses, numbers without a country code, and keys and tokens.
Five labelers vote for, against or not at all on each span, none of which sees
what another tests: its shape, an arithmetic check of its content, a gazetteer,
the words before it, and what touches it.  Votes are counted by pattern of votes
over all documents; expectation-maximisation on those counts estimates how
reliable each labeler is, and a span classifier, a logistic model over votes and
their pairs, is trained on the resulting probabilities.  It alone decides which
proposed spans are kept; spans of the base patterns always are.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from math import log2

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from overlapix.llm.storage import materialise

#: Kinds of the base patterns, and those that the method alone finds.
KINDS = ("email", "ip", "card", "phone", "secret")
BASE_KINDS = KINDS[:4]
LABELERS = ("shape", "check", "gazetteer", "context", "edges")
#: A proposed span is kept at this probability.
ACCEPT = 0.9
CONTEXT = 32
#: Votes of -1, 0, 1 that each labeler is believed to have cast on spans that are personal
#: data, before any is counted; the reverse on others.  They count for a thousand spans,
#: and in proportion where there are more, so that no accident of the mixture of forms
#: in a corpus turns a labeler's meaning round.
BELIEF = {"shape": (4.0, 8.0, 8.0), "check": (0.5, 6.0, 25.0), "gazetteer": (2.0, 8.0, 8.0), "context": (2.0, 10.0, 8.0), "edges": (4.0, 8.0, 8.0)}

_LOCAL = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-"
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]+(?:\.[0-9]+){3}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGIT = re.compile("[0-9]")
#: Wider forms: written-out addresses, numbers without a country code, keys and tokens.
_SPELT = re.compile(r"[A-Za-z0-9._%+-]{1,64} ?[\[({] ?(?:at|AT) ?[\])}] ?[A-Za-z0-9-]{1,63}(?:(?: ?[\[({] ?(?:dot|DOT) ?[\])}] ?|\.)[A-Za-z0-9-]{1,63}){1,4}")
_NATIONAL = re.compile(r"(?<![0-9+])(?:\([0-9]{3}\) ?|[0-9]{3}[-.])[0-9]{3}[-. ][0-9]{4}(?![0-9])")
_KEY = re.compile(r"(?<![A-Za-z0-9_+/-])[A-Za-z0-9_+/-]{16,}+={0,2}")
#: Usual ways of writing.
_KEY_SHAPE = re.compile(r"(?:AKIA|ASIA)[0-9A-Z]{16}|gh[pous]_[A-Za-z0-9]{36}|eyJ[A-Za-z0-9_-]+|(?:sk|pk)_(?:live|test)_[A-Za-z0-9]+|xox[bp]-[0-9A-Za-z-]+|[0-9a-f]+|[0-9A-F]+")
_PHONE_SHAPE = re.compile(r"\+[0-9]{1,3}[ .-]?(?:\([0-9]{1,4}\)|[0-9]{1,4})(?:[ .-][0-9]{2,4}){1,4}|\+[0-9]{10,15}")
_GROUPS = ((16,), (15,), (14,), (4, 4, 4, 4), (4, 6, 5), (4, 6, 4))

#: Gazetteers: endings of mail hosts, first digits of card issuers, calling codes, lengths of
#: keys and digests in hexadecimal digits, and first letters of issued keys.
HOST_ENDS = frozenset("com org net edu gov int io de fr es uk eu us info biz ch at it nl be pl pt ca au jp cn in br mx ru se no dk fi co".split())
ISSUERS = ("4", "51", "52", "53", "54", "55", "34", "37", "6011", "65", "35", "36", "38", "62")
CALLING = ("1", "7", "20", "27", "30", "31", "32", "33", "34", "36", "39", "40", "41", "43", "44", "45", "46", "47", "48", "49", "51", "52", "54", "55", "60", "61", "62", "63", "64", "65", "66", "81", "82", "84", "86", "90", "91", "92", "351", "352", "353", "358", "380", "420", "421", "966", "971", "972")
KEY_SIZES = (32, 40, 48, 56, 64, 96, 128)
KEY_STARTS = ("AKIA", "ASIA", "AIza", "ghp_", "gho_", "ghs_", "github_pat_", "glpat-", "sk-", "sk_live_", "sk_test_", "pk_live_", "xoxb-", "xoxp-", "eyJ", "SG.")
NEAR = {
    "email": re.compile(r"\b(?:e-?mail|mail|contact|write to|kontakt|correo|courriel)\b", re.I),
    "ip": re.compile(r"\b(?:ip|addr(?:ess)?|host|server|client|from)\b", re.I),
    "card": re.compile(r"\b(?:card|visa|mastercard|amex|credit|debit|karte|tarjeta|carte)\b", re.I),
    "phone": re.compile(r"\b(?:phone|tel|call|mobile|cell|fax|whatsapp|telefon|tel[eé]fono|t[eé]l[eé]phone)\b", re.I),
    "secret": re.compile(r"(?:token|secret|passw(?:or)?d|passwd|pwd|api[ _-]?key|access[ _-]?key|private[ _-]?key|auth(?:orization)?|bearer|credentials?|clave|passwort|mot de passe)[\w-]*[\"']?\s*(?:[:=]|is\b|\s)\s*[\"']?$", re.I),
}
AGAINST = {
    "email": re.compile(r"(?:://|git|ssh)[^ ]*$", re.I),
    "ip": re.compile(r"\b(?:version|v|release|section|chapter|build)\.? ?$", re.I),
    "card": re.compile(r"\b(?:isbn|ean|order|invoice|serial|tracking|token|id)\b[ #:=]*$", re.I),
    "phone": re.compile(r"\b(?:isbn|order|invoice|serial|id|page|pages)\b[ #:=]*$", re.I),
    "secret": re.compile(r"(?:://[^ ]*|\b(?:sha-?\d*|md5|crc|commit|checksum|digest|hash|uuid|etag|revision|doi|href|src|file|path)\b[\"']?\s*[:=#]?\s*[\"']?)$", re.I),
}


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        n = ord(c) - 48
        if i % 2:
            n = 2 * n - 9 * (n > 4)
        total += n
    return total % 10 == 0


def _emails(text: str) -> Iterator[tuple[int, int]]:
    done = at = 0
    while (at := text.find("@", at)) >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            yield start, m.end()
            done = at = m.end()
        else:
            at += 1


def matches(text: str) -> Iterator[tuple[str, int, int, bool]]:
    """``(kind, start, end, sound)`` of the base patterns, leftmost and not
    overlapping within a kind; unsound ones fail their kind's check."""
    if "@" in text:
        for s, e in _emails(text):
            yield "email", s, e, True
    if not _DIGIT.search(text):
        return
    for m in _IP.finditer(text):
        yield "ip", *m.span(), _octets(m[0])
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 12:
            digits = m[0].replace(" ", "").replace("-", "")
            yield "card", *m.span(), 14 <= len(digits) <= 19 and luhn(digits)
    if "+" in text:
        for m in _PHONE.finditer(text):
            yield "phone", *m.span(), 10 <= sum(map(str.isdigit, m[0])) <= 15


def _entropy(span: str) -> float:
    return -sum(n / len(span) * log2(n / len(span)) for n in Counter(span).values())


def _vote(good: bool, bad: bool = True) -> int:
    return 1 if good else -1 if bad else 0


def votes(kind: str, text: str, start: int, end: int) -> tuple[int, ...]:
    """One vote of -1, 0 or 1 from each labeler."""
    span = text[start:end]
    digits = "".join(c for c in span if "0" <= c <= "9")
    if kind == "email":
        tail = re.split(r"[.\s\])}]+", span.rstrip("])} "))[-1].lower()
        shape = _vote(".." not in span and not span.startswith(".") and not span.endswith("-"))
        check = _vote(bool(re.fullmatch(r"[a-z]{2,12}", tail)))
        gazetteer = _vote(tail in HOST_ENDS, False)
    elif kind == "ip":
        parts = span.split(".")
        shape = _vote(not any(len(p) > 1 and p[0] == "0" for p in parts))
        check = _vote(_octets(span))
        gazetteer = _vote(0 < int(parts[0][:4] or 0) < 240)
    elif kind == "card":
        groups = tuple(map(len, re.split(r"[ -]", span)))
        shape = _vote(groups in _GROUPS, len(groups) > 4)
        check = _vote(14 <= len(digits) <= 19 and luhn(digits))
        gazetteer = _vote(digits.startswith(ISSUERS), False)
    elif kind == "phone":
        shape = _vote(bool(_PHONE_SHAPE.fullmatch(span)), span[0] == "+")
        check = _vote(10 <= len(digits) <= 15)
        gazetteer = _vote(span[0] == "+" and digits.startswith(CALLING), False)
    else:
        body = span.rstrip("=")
        hexadecimal = bool(re.fullmatch(r"[0-9a-f]+|[0-9A-F]+", body))
        shape = _vote(bool(_KEY_SHAPE.fullmatch(body)), "/" in body or body.count("-") + body.count("_") > 3)
        turns = sum(a.isdigit() != b.isdigit() for a, b in zip(body, body[1:], strict=False))
        check = _vote(_entropy(body) >= 0.65 * log2(min(len(body), 16 if hexadecimal else 62)) and 10 * turns >= len(body))
        gazetteer = _vote(span.startswith(KEY_STARTS) or (hexadecimal and len(body) in KEY_SIZES), False)
    before = text[max(0, start - CONTEXT) : start]
    context = -1 if AGAINST[kind].search(before) else _vote(bool(NEAR[kind].search(before)), False)
    left, right = text[start - 1 : start] if start else "", text[end : end + 1]
    if kind == "secret":
        edges = _vote(not left.strip(" \t\r\n\"'`=:(") and not right.strip(" \t\r\n\"'`,;.)"), left.isalnum() or right.isalnum() or left in ("@", "/", "."))
    else:
        edges = _vote(not any(c.isalnum() or c in "_=\"'#" for c in left + right))
    return shape, check, gazetteer, context, edges


def _octets(span: str) -> bool:
    return all(len(p) <= 3 and int(p or 0) <= 255 for p in (q.lstrip("0") for q in span.split(".")))


def _part_of_phone(text: str, start: int, end: int) -> int | None:
    """Where a number that runs on would end: the last blank before which it has ten digits or more, and at most fifteen."""
    count, last = 0, None
    for at in range(start, end):
        c = text[at]
        if c == " " and count >= 10 and "0" <= text[at - 1] <= "9":
            last = at
        count += "0" <= c <= "9"
        if count > 15:
            break
    return last


def _parts_of_card(text: str, start: int, end: int) -> Iterator[tuple[int, int]]:
    """Runs of whole groups of digits, grouped as cards are, that pass the check."""
    groups = [(start + m.start(), start + m.end()) for m in re.finditer("[0-9]+", text[start:end])]
    if len(groups) < 2:
        return
    done = start
    for i, (s, _) in enumerate(groups):
        if s < done:
            continue
        for want in _GROUPS:
            run = groups[i : i + len(want)]
            if tuple(e - b for b, e in run) == want:
                stop = run[-1][1]
                if luhn("".join(text[b:e] for b, e in run)):
                    yield s, stop
                    done = stop
                    break


def proposals(text: str) -> Iterator[tuple[str, int, int, bool, tuple[int, ...]]]:
    """``(kind, start, end, base, votes)`` of every proposed span; ``base`` marks sound matches of the base patterns."""
    for kind, s, e, sound in matches(text):
        if sound or kind != "card" or sum("0" <= c <= "9" for c in text[s:e]) >= 13:
            yield kind, s, e, sound, votes(kind, text, s, e)
        if not sound and kind == "phone" and (cut := _part_of_phone(text, s, e)):
            yield kind, s, cut, False, votes(kind, text, s, cut)
        if not sound and kind == "card":
            for b, f in _parts_of_card(text, s, e):
                yield kind, b, f, False, votes(kind, text, b, f)
    if "at" in text or "AT" in text:
        if "[" in text or "(" in text or "{" in text:
            for m in _SPELT.finditer(text):
                yield "email", *m.span(), False, votes("email", text, *m.span())
    if _DIGIT.search(text):
        for m in _NATIONAL.finditer(text):
            if not re.search(r"\+[\x20().0-9-]{0,8}$", text[max(0, m.start() - 9) : m.start()]):
                yield "phone", *m.span(), False, votes("phone", text, *m.span())
        for m in _KEY.finditer(text):
            if _DIGIT.search(m[0]) and not m[0].isdigit() and re.search("[A-Za-z]", m[0]) and text[m.end() : m.end() + 1] != "@":
                yield "secret", *m.span(), False, votes("secret", text, *m.span())


def code_of(kind: str, cast: tuple[int, ...]) -> int:
    """Kind and votes as one small integer: the pattern that is counted."""
    code = KINDS.index(kind)
    for v in cast:
        code = code * 3 + v + 1
    return code


def votes_of(code: int) -> tuple[int, tuple[int, ...]]:
    cast = []
    for _ in LABELERS:
        code, v = divmod(code, 3)
        cast.append(v - 1)
    return code, tuple(reversed(cast))


N_CODES = len(KINDS) * 3 ** len(LABELERS)


@dataclass
class SpanModel:
    """``accepted`` pattern codes, and what was estimated on the way."""

    accepted: frozenset[int] = frozenset()
    reliability: dict[str, float] = field(default_factory=dict)
    probability: dict[int, float] = field(default_factory=dict)


def expectation_maximisation(codes: np.ndarray, counts: np.ndarray, rounds: int = 60) -> tuple[np.ndarray, dict[str, float]]:
    """Probability that a pattern marks personal data, and each labeler's share
    of right votes; votes are taken as independent given the truth."""
    cast = np.array([votes_of(c)[1] for c in codes]).reshape(len(codes), len(LABELERS)) + 1
    p = np.clip(0.5 + 0.15 * (cast - 1).sum(1), 0.05, 0.95)
    chance = np.full((2, len(LABELERS), 3), 1 / 3)
    belief = np.array([[BELIEF[name][::-1], BELIEF[name]] for name in LABELERS]) * max(1.0, counts.sum() / 1000)
    share = belief[0].sum(1)
    for _ in range(rounds):
        w = np.stack([counts * (1 - p), counts * p])
        prior = (w.sum(1) + share) / (counts.sum() + share.sum())
        for j in range(len(LABELERS)):
            for v in range(3):
                chance[:, j, v] = (w[:, cast[:, j] == v].sum(1) + belief[j, :, v]) / (w.sum(1) + belief[j].sum(1))
        log = np.log(prior)[:, None] + sum(np.log(chance[:, j, cast[:, j]]) for j in range(len(LABELERS)))
        p = 1 / (1 + np.exp(np.clip(log[0] - log[1], -50, 50)))
    right = {}
    for j, name in enumerate(LABELERS):
        told = cast[:, j] != 1
        agree = np.where(cast[:, j] == 2, p, 1 - p)
        right[name] = float((counts * agree)[told].sum() / max(1e-9, counts[told].sum()))
    return p, right


def _design(codes: np.ndarray) -> np.ndarray:
    rows = []
    for c in codes:
        kind, cast = votes_of(c)
        pairs = [cast[i] * cast[j] for i in range(len(cast)) for j in range(i)]
        rows.append([1.0, *(float(kind == k) for k in range(len(KINDS))), *cast, *pairs])
    return np.array(rows).reshape(len(codes), -1)


def fit(codes: np.ndarray, counts: np.ndarray, steps: int = 400) -> SpanModel:
    """The span classifier on counted vote patterns; nothing counted, nothing accepted."""
    if not len(codes):
        return SpanModel()
    order = np.argsort(codes)
    codes, counts = codes[order], counts[order].astype(float)
    soft, right = expectation_maximisation(codes, counts)
    x, weight = _design(codes), counts / counts.sum()
    theta, moment, square = (np.zeros(x.shape[1]) for _ in range(3))
    for t in range(1, steps + 1):
        p = 1 / (1 + np.exp(-np.clip(x @ theta, -30, 30)))
        g = x.T @ (weight * (p - soft)) + 1e-4 * theta
        moment, square = 0.9 * moment + 0.1 * g, 0.99 * square + 0.01 * g * g
        theta -= 0.1 * (moment / (1 - 0.9**t)) / (np.sqrt(square / (1 - 0.99**t)) + 1e-8)
    p = 1 / (1 + np.exp(-np.clip(x @ theta, -30, 30)))
    return SpanModel(frozenset(int(c) for c, q in zip(codes, p, strict=True) if q >= ACCEPT), right, dict(zip(codes.tolist(), p.tolist(), strict=True)))


_PROPOSED = "doc_id bigint, base array<bigint>, starts array<int>, ends array<int>, kinds array<int>, codes array<int>"


def _propose_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        cols: list[list[list[int]]] = [[] for _ in range(5)]
        for text in batch.column(1):
            found = list(proposals(text.as_py() or ""))
            for c, x in zip(cols, zip(*((int(b), s, e, KINDS.index(k), code_of(k, v)) for k, s, e, b, v in found), strict=True) if found else [[]] * 5, strict=True):
                c.append(list(x))
        kinds = [pa.int64(), *[pa.int32()] * 4]
        yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, pa.list_(t)) for c, t in zip(cols, kinds, strict=True))], names=["doc_id", "base", "starts", "ends", "kinds", "codes"])


def propose(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``doc_id, found``: one row per input row, its proposed spans as structs
    ``(start, kind, end, base, code)`` in code points, end exclusive."""
    rows = docs.select(F.col(doc_id).cast("bigint").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(_propose_batches, _PROPOSED)
    zipped = F.arrays_zip(F.col("starts").alias("start"), F.col("kinds").alias("kind"), F.col("ends").alias("end"), F.col("base"), F.col("codes").alias("code"))
    return rows.select("doc_id", F.transform(zipped, lambda x: F.struct(x["start"].alias("start"), x["kind"].alias("kind"), x["end"].alias("end"), (x["base"] == 1).alias("base"), x["code"].alias("code"))).alias("found"))


def train(proposed: DataFrame) -> SpanModel:
    """Fit on the vote patterns of all proposed spans; at most ``N_CODES`` counts reach the driver."""
    counted = proposed.select(F.explode("found.code").alias("code")).groupBy("code").count().limit(N_CODES).collect()
    return fit(np.array([r.code for r in counted], int), np.array([r["count"] for r in counted], int))


def _kept(found: Column, model: SpanModel) -> Column:
    accepted = F.array(*[F.lit(c).cast("int") for c in sorted(model.accepted)]) if model.accepted else F.array().cast("array<int>")
    kept = F.filter(found, lambda x: x["base"] | F.array_contains(accepted, x["code"]))
    return F.array_sort(F.array_distinct(F.transform(kept, lambda x: F.struct(x["start"], x["kind"], x["end"]))))


def _written(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(names, x["kind"]), x["start"].cast("string"), x["end"].cast("string"))), ",")


def _number(spans: str, kind: int) -> Column:
    return F.size(F.filter(spans, lambda x: x["kind"] == kind)).cast("bigint")


def personal_data(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans``, one row per input row.

    Counts and digest are of the base patterns' spans; ``spans`` adds what the
    classifier accepts, of their kinds and of kind ``secret``.  Null and empty texts have none; repeated rows and null
    ids stay; an empty table gives no rows.
    """
    proposed = materialise(propose(docs, text, doc_id), "proposed")
    model = train(proposed)
    base = F.array_sort(F.transform(F.filter("found", lambda x: x["base"]), lambda x: F.struct(x["start"], x["kind"], x["end"])))
    counts = [_number("base", k).alias(f"n_{name}") for k, name in enumerate(BASE_KINDS)]
    return proposed.select("doc_id", base.alias("base"), _written(_kept(F.col("found"), model)).alias("spans")).select("doc_id", *counts, F.sha2(_written(F.col("base")).cast("binary"), 256).alias("base_sha256"), "spans")


def redacted(text: str | None, model: SpanModel) -> str | None:
    """``text`` with a mark of its kind for each kept span; overlapping spans give one mark."""
    if not text:
        return text
    spans = sorted((s, -e, k) for k, s, e, base, cast in proposals(text) if base or code_of(k, cast) in model.accepted)
    out, done = [], 0
    for s, e, kind in spans:
        e = -e
        if s < done:
            done = max(done, e)
            continue
        out += [text[done:s], f"<{kind.upper()}>"]
        done = e
    return "".join([*out, text[done:]])


def _redact_batches(model: SpanModel, at: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = pa.array([redacted(x.as_py(), model) for x in batch.column(at)], pa.string())
            yield batch.set_column(at, batch.schema.names[at], texts)

    return run


def redact(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``docs`` with every kept span replaced by a mark of its kind; columns and rows as before."""
    model = train(propose(docs, text, doc_id))
    return docs.mapInArrow(_redact_batches(model, docs.columns.index(text)), docs.schema)
