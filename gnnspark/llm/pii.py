"""Personal data by weak supervision: labelers vote on candidate spans, expectation-maximisation estimates their reliabilities, and a
span classifier is trained on the estimated labels.

Strict patterns give spans that always stay (email, ip, card, phone). Loose patterns propose further candidates, doubtful ones among them: obfuscated addresses,
groups of digits that may be national numbers, cards, dates or order numbers, dotted and colon-separated numbers that may be addresses or versions, and long keys
that may be secrets. Regex, format, gazetteer and context labelers vote on every candidate of the corpus; votes and binary shape features are one small
number, so the corpus is reduced to counts of at most a few thousand different numbers before anything reaches the driver. Strict and loose candidates of each kind have
priors of their own, so that many sure spans do not vouch for the doubtful ones. The classifier then decides on the loose candidates.

Patterns are written so that a text is scanned in linear time. Defined results: null text is empty; repeated rows each get a
result; a corpus without candidates gets an untrained classifier that adds nothing; an empty table gives no rows. Only the named columns are read.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BASE_KINDS = ("email", "ip", "card", "phone")
KINDS = (*BASE_KINDS, "secret")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]+\.[0-9]+\.[0-9]+")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_OBFUSCATED = re.compile(r"\b[A-Za-z0-9._%-]{1,64} ?[\[(](?:at|AT|@)[\])] ?[A-Za-z0-9-]{1,63}(?: ?(?:\.|[\[(](?:dot|DOT)[\])]) ?[A-Za-z0-9-]{1,63}){1,4}")
_DIGIT_GROUPS = re.compile(r"(?<![\w+.-])\(?[0-9](?:[().\x20-]{0,2}[0-9]){5,24}(?![\w-])")
_COLONS = re.compile(r"(?<![\w:])[0-9A-Fa-f]{1,4}(?::[0-9A-Fa-f]{1,4}){2,7}(?![\w:])")
_KEY = re.compile(r"(?<![A-Za-z0-9_+/=-])[A-Za-z0-9_+/-]{20,200}(?![A-Za-z0-9_+/-])")
# Gazetteers and context words of the labelers.
TOP_DOMAINS = frozenset("com org net edu gov int info biz de fr es uk it nl eu us ca au ch at be pl pt se no dk fi io co".split())
CARD_STARTS = ("4", "51", "52", "53", "54", "55", "34", "37", "6011", "65", "35", "30", "36")
CUES = {
    "email": re.compile(r"mail|contact|write to|kontakt|correo|courriel", re.I),
    "ip": re.compile(r"\bip\b|address|host|server|login|adresse", re.I),
    "card": re.compile(r"card|visa|credit|payment|karte|carte|tarjeta", re.I),
    "phone": re.compile(r"phone|tel\b|tel\.|call|fax|mobile|telefon|teléfono|téléphone", re.I),
    "secret": re.compile(r"token|secret|passw|pwd|key|auth|bearer|credential", re.I),
}
AGAINST = re.compile(r"version|isbn|doi|section|release|invoice|order no|part no", re.I)
CONTEXT = 40
LABELERS = ("regex", "format", "gazetteer", "context", "against")


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = int(d) * (1 + i % 2)
        total += n - 9 if n > 9 else n
    return total % 10 == 0


def _digits(text: str) -> str:
    return "".join(c for c in text if "0" <= c <= "9")


def emails(text: str):
    """Spans of the strict email pattern: each @ has one possible match, from the start of the run on its left."""
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            yield start, m.end()
            done = m.end()
        at = text.find("@", max(at + 1, done))


def strict_spans(text: str | None) -> list[tuple[str, int, int]]:
    """(kind, start, end) in code points: leftmost, non-overlapping matches of each kind that pass its test."""
    if not text:
        return []
    out = [("email", s, e) for s, e in emails(text)] if "@" in text else []
    out += [("ip", *m.span()) for m in _IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p[-4:]) <= 255 for p in m.group().split("."))]
    out += [("card", *m.span()) for m in _CARD.finditer(text) if m.end() - m.start() >= 16 and 16 <= len(d := _digits(m.group())) <= 19 and luhn(d)]
    if "+" in text:
        out += [("phone", *m.span()) for m in _PHONE.finditer(text) if 8 <= len(_digits(m.group())) <= 15]
    return out


def loose_spans(text: str, strict: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
    """Further candidates that overlap no strict span and no candidate before them."""
    found, taken = [], bytearray(len(text))
    for _, a, b in strict:
        taken[a:b] = b"\1" * (b - a)

    def add(kind: str | None, s: int, e: int) -> None:
        if kind and taken.find(1, s, e) < 0:
            found.append((kind, s, e))
            taken[s:e] = b"\1" * (e - s)

    if "(" in text or "[" in text:
        for m in _OBFUSCATED.finditer(text):
            add("email", *m.span())
    for m in _DIGIT_GROUPS.finditer(text):
        add(kind_of_digits(m.group()), *m.span())
    if text.count(":") > 1:
        for m in _COLONS.finditer(text):
            add("ip", *m.span())
    for m in _KEY.finditer(text):
        if is_mixed(m.group()):
            add("secret", *m.span())
    return found


def kind_of_digits(span: str) -> str | None:
    """What a group of digits could be by its marks and length; None: nothing personal."""
    n = len(_digits(span))
    if "." in span and not any(c in span for c in " ()-"):
        return "ip" if span.count(".") >= 3 else None
    if n >= 13:
        return "card" if n <= 19 else None
    return "phone" if n >= 7 and n < len(span) else None


def is_mixed(key: str) -> bool:
    """Letters and digits in turn, as in keys and unlike in words with a number behind them."""
    turns = sum(a.isdigit() != b.isdigit() for a, b in zip(key, key[1:]))
    return turns >= 4


def octets(span: str) -> bool:
    parts = span.split(".")
    return len(parts) == 4 and all(p.isdigit() and len(p) <= 3 and int(p) <= 255 for p in parts)


def votes(text: str, kind: str, start: int, end: int, strict: bool) -> tuple[int, ...]:
    """One vote a labeler: 2 for personal data, 0 against, 1 no opinion."""
    span, digits = text[start:end], _digits(text[start:end])
    around = text[max(0, start - CONTEXT) : start] + " " + text[end : end + CONTEXT]
    checked = 2 if strict else 1
    if kind == "email":
        shape, known = 2 if span.count("@") == 1 or "at" in span.lower() else 0, 2 if span.rpartition(".")[2].lower() in TOP_DOMAINS else 1
    elif kind == "ip" and ":" in span:
        groups = span.split(":")
        checked, shape, known = 2 if len(groups) == 8 else 0, 2 if any(len(g) > 2 for g in groups) else 0, 2 if groups[0][:1] in "2fF" else 1
    elif kind == "ip":
        checked = checked if octets(span) else 0
        shape, known = 2 if all(len(p) == 1 or p[:1] != "0" for p in span.split(".")) else 0, 0 if span.startswith(("0.", "127.", "255.")) else 2
    elif kind == "card":
        checked = 2 if luhn(digits) else 0
        shape, known = 2 if len(digits) in (15, 16, 19) else 0, 2 if digits.startswith(CARD_STARTS) else 1
    elif kind == "phone":
        dated = bool(re.fullmatch(r"(?:19|20)[0-9]{2}[-. ][0-9]{1,2}[-. ][0-9]{1,2}|[0-9]{1,2}[-. ][0-9]{1,2}[-. ](?:19|20)[0-9]{2}", span))
        shape = 0 if dated else 2 if 10 <= len(digits) <= 13 else 1
        known = 1 if len(digits) < 10 else 2 if digits[-10] not in "01" else 0
        checked = checked if not dated else 0
    else:
        checked = 2 if re.fullmatch("[0-9a-fA-F]{32,}", span) else 1
        assigned = re.search(r"[:=]\s*[\"']?$", text[max(0, start - 4) : start]) is not None
        shape, known = 2 if assigned else 0, 0 if span.count("/") > 2 or span.count("-") > 4 else 1
    return (checked, shape, known, 2 if CUES[kind].search(around) else 1, 0 if AGAINST.search(around) else 1)


def pattern_of(text: str, kind: str, start: int, end: int, strict: bool) -> int:
    """Kind and strictness (the group), votes and shape features as one number."""
    code = 2 * KINDS.index(kind) + strict
    for v in votes(text, kind, start, end, strict):
        code = code * 3 + v
    span = text[start:end]
    before, after = text[start - 1 : start], text[end : end + 1]
    shape = (before.isalnum(), after.isalnum(), " " in span, "-" in span, before in ("(", "[", "<", '"'), before == "" or before.isspace())
    for bit in shape:
        code = code * 2 + bool(bit)
    return code


def unpacked(code: int) -> tuple[int, list[int], list[int]]:
    """(group, votes, shape bits); the group is twice the kind, and one more for strict spans."""
    bits = []
    for _ in range(6):
        code, b = divmod(code, 2)
        bits.append(b)
    vote = []
    for _ in LABELERS:
        code, v = divmod(code, 3)
        vote.append(v)
    return code, vote[::-1], bits[::-1]


@dataclass
class PiiModel:
    """Priors of the groups, reliabilities of the labelers, and the weights of the span classifier over kind, votes and shape."""

    priors: np.ndarray
    tables: np.ndarray
    weights: np.ndarray | None = None

    @staticmethod
    def features(code: int) -> np.ndarray:
        group, vote, bits = unpacked(code)
        x = np.zeros(len(KINDS) + 3 * len(vote) + len(bits) + 1)
        x[group // 2] = 1
        for i, v in enumerate(vote):
            x[len(KINDS) + 3 * i + v] = 1
        x[len(KINDS) + 3 * len(vote) : -1] = bits
        x[-1] = 1
        return x

    def probability(self, code: int) -> float:
        if self.weights is None:
            return 0.0
        return float(1 / (1 + np.exp(-np.clip(self.features(code) @ self.weights, -30, 30))))


# Pseudo-counts of the votes (against, none, for) of a labeler that is better than chance, for no personal data and for personal data.
BELIEF = np.array([[6.0, 3.0, 1.0], [1.0, 3.0, 6.0]])


def estimate(groups: np.ndarray, vote: np.ndarray, n: np.ndarray, n_groups: int, rounds: int = 200) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Expectation-maximisation over vote patterns: (priors by group, tables [class, labeler, vote], expected labels).

    Votes are independent given the class; the pseudo-counts of :data:`BELIEF` name the classes, and each group's prior has one of two candidates of either class.
    """
    k = vote.shape[1]
    one = np.eye(3)[vote]
    tables = np.repeat((BELIEF / BELIEF.sum(1, keepdims=True))[:, None, :], k, axis=1)
    priors = np.full(n_groups, 0.5)
    for _ in range(rounds):
        logs = np.einsum("ikv,ykv->iy", one, np.log(tables)) + np.stack([np.log(1 - priors[groups]), np.log(priors[groups])], 1)
        soft = 1 / (1 + np.exp(np.clip(logs[:, 0] - logs[:, 1], -30, 30)))
        yes, every = np.bincount(groups, n * soft, n_groups), np.bincount(groups, n, n_groups)
        priors = (yes + 1) / (every + 2)
        counts = np.stack([np.einsum("i,ikv->kv", n * w, one) for w in (1 - soft, soft)]) + BELIEF[:, None, :]
        tables = counts / counts.sum(2, keepdims=True)
    return priors, tables, soft


def fit_counts(counts: dict[int, int], steps: int = 400) -> PiiModel:
    """Expectation-maximisation over vote patterns, then logistic regression on the expected labels; each group weighs the same in it."""
    k, n_groups = len(LABELERS), 2 * len(KINDS)
    if not counts:
        return PiiModel(np.full(n_groups, 0.5), np.full((2, k, 3), 1 / 3))
    codes = sorted(counts)
    n = np.array([counts[c] for c in codes], float)
    told = [unpacked(c) for c in codes]
    groups, vote = np.array([t[0] for t in told]), np.array([t[1] for t in told])
    priors, tables, soft = estimate(groups, vote, n, n_groups)
    model = PiiModel(priors, tables)
    x = np.stack([PiiModel.features(c) for c in codes])
    share = n / np.bincount(groups, n, n_groups)[groups]
    w, share = np.zeros(x.shape[1]), share / share.sum()
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        w -= 1.0 * (x.T @ (share * (p - soft)) + 1e-4 * w)
    model.weights = w
    return model


def train(docs: DataFrame, text: str = "text") -> PiiModel:
    """Fit to all candidates of all texts. The driver receives counts of vote patterns: at most 10 * 3**5 * 2**6 numbers."""

    def count(batches):
        for batch in batches:
            seen: Counter[int] = Counter()
            for t in batch.column(0).to_pylist():
                strict = strict_spans(t)
                seen.update(pattern_of(t, *s, True) for s in strict)
                seen.update(pattern_of(t, *s, False) for s in (loose_spans(t, strict) if t else ()))
            yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.int64()), pa.array(list(seen.values()), pa.int64())], names=["code", "n"])

    rows = docs.select(F.col(text)).mapInArrow(count, "code long, n long").groupBy("code").agg(F.sum("n").alias("n")).collect()
    return fit_counts({r["code"]: r["n"] for r in rows})


def all_spans(text: str | None, model: PiiModel, threshold: float = 0.5) -> tuple[list, list]:
    """(strict spans, all spans), each by kind as listed, then start."""
    strict = strict_spans(text)
    more = [s for s in (loose_spans(text, strict) if text else ()) if model.probability(pattern_of(text, *s, False)) >= threshold]
    order = lambda s: (KINDS.index(s[0]), s[1])
    return strict, sorted(strict + more, key=order) if more else strict


def redacted(text: str, spans: list[tuple[str, int, int]]) -> str:
    """The text with each span replaced by its kind in brackets; of overlapping spans the first in text order names the place."""
    out, at = [], 0
    for kind, s, e in sorted(spans, key=lambda x: (x[1], -x[2])):
        if s >= at:
            out += [text[at:s], f"[{kind.upper()}]"]
        at = max(at, e)
    return "".join([*out, text[at:]])


def told(spans) -> str:
    return ",".join(f"{k}:{s}:{e}" for k, s, e in spans)


def find(docs: DataFrame, model: PiiModel, id_col: str = "doc_id", text: str = "text", threshold: float = 0.5) -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans): counts and digest of strict spans, and all spans as text."""
    kept = docs.select(F.col(id_col).alias("doc_id"), F.col(text).alias("text"))
    schema = kept.select("doc_id").withColumns({f"n_{k}": F.lit(0).cast("long") for k in BASE_KINDS} | {"base_sha256": F.lit(""), "spans": F.lit("")}).schema

    def apply(batches):
        for batch in batches:
            counts, digest, spans = [[] for _ in BASE_KINDS], [], []
            for t in batch.column(1).to_pylist():
                strict, every = all_spans(t, model, threshold)
                for i, k in enumerate(BASE_KINDS):
                    counts[i].append(sum(s[0] == k for s in strict))
                digest.append(hashlib.sha256(told(strict).encode()).hexdigest())
                spans.append(told(every))
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(c, pa.int64()) for c in counts], pa.array(digest, pa.string()), pa.array(spans, pa.string())], names=schema.names)

    return kept.mapInArrow(apply, schema)


def redact(docs: DataFrame, model: PiiModel, text: str = "text", threshold: float = 0.5) -> DataFrame:
    """The table with every span of every text replaced; null stays null, other columns pass."""
    at, schema = docs.columns.index(text), docs.schema

    def apply(batches):
        for batch in batches:
            new = [None if t is None else redacted(t, all_spans(t, model, threshold)[1]) for t in batch.column(at).to_pylist()]
            arrays = [pa.array(new, pa.string()) if i == at else batch.column(i) for i in range(batch.num_columns)]
            yield pa.RecordBatch.from_arrays(arrays, names=schema.names)

    return docs.mapInArrow(apply, schema)
