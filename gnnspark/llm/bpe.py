"""Byte-level BPE encoding and decoding over contiguous rank arrays.

A word's parts and the ranks of its adjacent pairs lie side by side in arrays. The least rank is found by a scan, its
right boundary is deleted, and only the two neighbouring ranks are looked up again. The arrays of all
unseen short words of one width are stacked, so each step of the loop serves them together; words longer than ``SHORT`` bytes
use a heap over the same pairs, which keeps their cost n log n.

The vocabulary file (a fixed size, read on the driver from a path that is a parameter) is broadcast. Each Python worker keeps a bounded memory of
encoded words. Texts are handled in pieces of a bounded number of words, so a very long text needs no more memory than its own ids.

Defined results: null text is empty (no ids); control strings of the vocabulary become their own ids, as the
tokenizers library does; repeated rows each get a result; an empty table gives no rows. Only the named columns are read.
A vocabulary file that asks for steps not built here (a normaliser, another pre-tokeniser, dropout, added tokens that take spaces or whole
words) is refused. Letters and numbers are those of the regex package's Unicode tables; the tokenizers library may have others, which
can only matter for code points that one of the two versions leaves unassigned.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import struct
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SHORT, REMEMBERED, WORDS_AT_ONCE, CHARS_AT_ONCE = 48, 500_000, 200_000, 1_000_000
NONE = np.int32(2**31 - 1)
# Fixed value: how byte-level vocabularies cut a text into words.
WORD_PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


def byte_letters() -> dict[str, int]:
    """The printable letter of each byte: printable Latin-1 stands for itself, the rest for code points from 256 on, in order."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(rest)}


def refused(told: dict) -> list[str]:
    """What a vocabulary file asks for that this encoder does not do; empty if it can follow the file."""
    model, cut = told["model"], told.get("pre_tokenizer") or {}
    wrong = [k for k in ("normalizer", "post_processor") if told.get(k)]
    wrong += [f"model {k}" for k in ("dropout", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback", "ignore_merges") if model.get(k)]
    if model.get("type", "BPE") != "BPE":
        wrong.append("model type")
    if cut.get("type") != "ByteLevel" or cut.get("add_prefix_space") or not cut.get("use_regex", True):
        wrong.append("pre_tokenizer")
    if (told.get("decoder") or {}).get("type") != "ByteLevel":
        wrong.append("decoder")
    if any(a.get(k) for a in told.get("added_tokens", []) for k in ("single_word", "lstrip", "rstrip", "normalized")):
        wrong.append("added_tokens")
    if any(i >= 2**20 for i in model["vocab"].values()):
        wrong.append("ids of 2**20 or more")
    return wrong


class Bpe:
    """A vocabulary with its merges as sorted pair codes."""

    def __init__(self, spec: str):
        told = json.loads(spec)
        if wrong := refused(told):
            raise ValueError(f"vocabulary file not supported: {', '.join(wrong)}")
        vocab, merges = told["model"]["vocab"], told["model"]["merges"]
        letters = byte_letters()
        self.special = {a["content"]: a["id"] for a in told.get("added_tokens", [])}
        size = max([*vocab.values(), *self.special.values()]) + 1
        self.pieces: list[bytes] = [b""] * size
        for token, i in vocab.items():
            self.pieces[i] = bytes(letters[c] for c in token)
        for token, i in self.special.items():
            self.pieces[i] = token.encode()
        self.byte_id = np.array([vocab[c] for c, _ in sorted(letters.items(), key=lambda x: x[1])], np.int32)
        pairs = [m if isinstance(m, list) else m.split(" ") for m in merges]
        code = np.array([vocab[a] * 2**20 + vocab[b] for a, b in pairs], np.int64)
        made = np.array([vocab[a + b] for a, b in pairs], np.int32)
        order = np.argsort(code, kind="stable")
        self.codes, self.code_rank, self.made = np.append(code[order], 2**62), np.append(order, 0).astype(np.int32), made
        self.words = regex.compile(WORD_PATTERN)
        self.cut = regex.compile("|".join(map(regex.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None
        self.known: dict[str, bytes] = {}

    def ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Merge ranks of pairs, NONE where no merge joins them."""
        code = left.astype(np.int64) * 2**20 + right
        at = np.searchsorted(self.codes, code)
        return np.where(self.codes[at] == code, self.code_rank[at], NONE)

    def merge_stack(self, parts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, number of ids) for a matrix with a row of byte ids per word, filled up with -1."""
        n, width = parts.shape
        out, count = parts.copy(), np.zeros(n, np.int64)
        live = np.arange(n)
        rank = np.full((n, width), NONE, np.int32)
        if width > 1:
            rank[:, :-1] = np.where(parts[:, 1:] >= 0, self.ranks(parts[:, :-1], np.maximum(parts[:, 1:], 0)), NONE)
        cols = np.arange(width)
        while len(live):
            at = rank.argmin(1)
            row = np.arange(len(live))
            best = rank[row, at]
            on = best < NONE
            if not on.all():
                out[live[~on]], count[live[~on]] = parts[~on], (parts[~on] >= 0).sum(1)
                parts, rank, live, at, best = parts[on], rank[on], live[on], at[on], best[on]
                row = np.arange(len(live))
                if not len(live):
                    break
            source = np.minimum(cols + (cols > at[:, None]), width - 1)
            parts, rank = np.take_along_axis(parts, source, 1), np.take_along_axis(rank, source, 1)
            parts[:, -1], rank[:, -1] = -1, NONE
            parts[row, at] = self.made[best]
            after = np.minimum(at + 1, width - 1)
            right = parts[row, after]
            rank[row, at] = np.where((right >= 0) & (after > at), self.ranks(parts[row, at], np.maximum(right, 0)), NONE)
            inner = np.flatnonzero(at > 0)
            rank[inner, at[inner] - 1] = self.ranks(parts[inner, at[inner] - 1], parts[inner, at[inner]])
        return out, count

    def merge_long(self, data: bytes) -> np.ndarray:
        """One long word, by a heap of (rank, place) with stale entries skipped."""
        ids = self.byte_id[np.frombuffer(data, np.uint8)].tolist()
        n = len(ids)
        nxt, prv = list(range(1, n + 1)), list(range(-1, n - 1))
        first = self.ranks(np.array(ids[:-1], np.int32), np.array(ids[1:], np.int32)).tolist()
        heap = [(r, i, ids[i], ids[i + 1]) for i, r in enumerate(first) if r < NONE]
        heapq.heapify(heap)

        def push(i: int) -> None:
            if i >= 0 and nxt[i] < n:
                r = int(self.ranks(np.array([ids[i]]), np.array([ids[nxt[i]]]))[0])
                if r < NONE:
                    heapq.heappush(heap, (r, i, ids[i], ids[nxt[i]]))

        while heap:
            r, i, a, b = heapq.heappop(heap)
            j = nxt[i]
            if ids[i] != a or j >= n or ids[j] != b:
                continue
            ids[i], ids[j] = int(self.made[r]), -1
            nxt[i] = nxt[j]
            if nxt[i] < n:
                prv[nxt[i]] = i
            push(prv[i])
            push(i)
        return np.array([x for x in ids if x >= 0], np.uint32)

    def learn(self, words: set[str]) -> None:
        """Encode unseen words into the memory, as little-endian unsigned 32-bit ids."""
        by_width: dict[int, list[tuple[str, bytes]]] = {}
        for w in words:
            data = w.encode("utf-8", "replace")
            if len(data) > SHORT:
                self.known[w] = self.merge_long(data).astype("<u4").tobytes()
            else:
                by_width.setdefault(-(-len(data) // 4) * 4, []).append((w, data))
        for width, same in by_width.items():
            for i in range(0, len(same), 20_000):
                part = same[i : i + 20_000]
                raw = np.frombuffer(b"".join(d.ljust(width, b"\0") for _, d in part), np.uint8).reshape(len(part), width)
                lengths = np.array([len(d) for _, d in part])
                stack = np.where(np.arange(width) < lengths[:, None], self.byte_id[raw], np.int32(-1))
                ids, count = self.merge_stack(stack)
                flat = ids.astype("<u4").tobytes()
                for k, ((w, _), c) in enumerate(zip(part, count.tolist())):
                    self.known[w] = flat[4 * width * k : 4 * (width * k + c)]

    def remember(self, words: set[str]) -> None:
        """Make sure that the memory holds these words; it is emptied when it would grow past its bound."""
        fresh = words.difference(self.known)
        if fresh:
            if len(self.known) + len(fresh) > REMEMBERED:
                self.known.clear()
                fresh = words
            self.learn(fresh)

    def segments(self, text: str) -> list[str | int]:
        """The text cut at control strings, each given as its id."""
        out, at = [], 0
        if self.cut and any(s in text for s in self.special):
            for m in self.cut.finditer(text):
                out += [text[at : m.start()], self.special[m.group()]]
                at = m.end()
        return [*out, text[at:]]

    def encode_long(self, text: str) -> Iterator[bytes]:
        """The packed ids of a long text, in pieces of a bounded number of words."""
        for part in self.segments(text):
            if isinstance(part, int):
                yield struct.pack("<I", part)
                continue
            found = (m.group() for m in self.words.finditer(part))
            while some := list(islice(found, WORDS_AT_ONCE)):
                self.remember(set(some))
                yield b"".join(map(self.known.__getitem__, some))

    def encode_all(self, texts: list[str | None]) -> Iterator[Iterator[bytes] | list[bytes]]:
        """The packed ids of each text, in order. Unseen words of many texts are merged together."""
        i = 0
        while i < len(texts):
            if len(texts[i] or "") > CHARS_AT_ONCE:
                yield self.encode_long(texts[i])
                i += 1
                continue
            group, chars = [], 0
            while i < len(texts) and chars + len(texts[i] or "") <= 2 * CHARS_AT_ONCE and len(texts[i] or "") <= CHARS_AT_ONCE:
                chars += len(texts[i] or "")
                group.append([p if isinstance(p, int) else self.words.findall(p) for p in self.segments(texts[i] or "")])
                i += 1
            self.remember({w for parts in group for p in parts if not isinstance(p, int) for w in p})
            for parts in group:
                yield [struct.pack("<I", p) if isinstance(p, int) else b"".join(map(self.known.__getitem__, p)) for p in parts]

    def encode(self, text: str | None) -> np.ndarray:
        return self.encode_many([text])[0]

    def encode_many(self, texts: list[str | None]) -> list[np.ndarray]:
        return [np.frombuffer(b"".join(pieces), "<u4") for pieces in self.encode_all(texts)]

    def decode_bytes(self, ids: np.ndarray) -> bytes:
        return b"".join(map(self.pieces.__getitem__, ids.tolist()))

    def decode(self, ids) -> str:
        """The text of ids; bytes that are no UTF-8 become replacement characters."""
        return self.decode_bytes(np.asarray(ids, np.int64)).decode("utf-8", "replace")

    def digests(self, texts: list[str | None]) -> Iterator[tuple[int, str, str]]:
        """(number of ids, digest of the ids, digest of the decoded text) of each text, piece by piece."""
        for pieces in self.encode_all(texts):
            n, ids_hash, raw = 0, hashlib.sha256(), []
            for piece in pieces:
                n += len(piece) // 4
                ids_hash.update(piece)
                raw.append(self.decode_bytes(np.frombuffer(piece, "<u4")))
            whole = b"".join(raw).decode("utf-8", "replace").encode("utf-8")
            yield n, ids_hash.hexdigest(), hashlib.sha256(whole).hexdigest()


_loaded: dict[int, Bpe] = {}


def loaded(spec: str) -> Bpe:
    """One vocabulary per Python worker."""
    key = hash(spec)
    if key not in _loaded:
        _loaded.clear()
        _loaded[key] = Bpe(spec)
    return _loaded[key]


def _mapped(docs: DataFrame, path: str, text: str, keep: tuple[str, ...], schema, rows) -> DataFrame:
    with open(path, encoding="utf-8") as f:
        spec = docs.sparkSession.sparkContext.broadcast(f.read())
    k = len(keep)

    def apply(batches):
        bpe = loaded(spec.value)
        for batch in batches:
            arrays = rows(bpe, batch.column(k).to_pylist())
            yield pa.RecordBatch.from_arrays([*[batch.column(i) for i in range(k)], *arrays], names=[f.name for f in schema])

    return docs.select(*[F.col(f"`{c}`") for c in keep], F.col(text).alias("__text")).mapInArrow(apply, schema)


def encode(docs: DataFrame, path: str, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The kept columns and ``ids`` (array of int), in one pass without a shuffle."""
    schema = docs.select(*keep).withColumn("ids", F.array(F.lit(0))).schema
    return _mapped(docs, path, text, keep, schema, lambda bpe, texts: [pa.array([x.astype(np.int32) for x in bpe.encode_many(texts)], pa.list_(pa.int32()))])


def decode(coded: DataFrame, path: str, ids: str = "ids", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The kept columns and ``decoded`` (text); null ids decode to the empty text."""
    schema = coded.select(*keep).withColumn("decoded", F.lit("")).schema
    return _mapped(coded, path, ids, keep, schema, lambda bpe, rows: [pa.array([bpe.decode(r or []) for r in rows], pa.string())])


def digests(docs: DataFrame, path: str, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The kept columns, n_tokens, ids_sha256 and decoded_sha256: encode, then decode what was encoded."""
    schema = docs.select(*keep).withColumns({"n_tokens": F.lit(0).cast("long"), "ids_sha256": F.lit(""), "decoded_sha256": F.lit("")}).schema

    def rows(bpe: Bpe, texts: list[str | None]):
        told = list(bpe.digests(texts))
        return [pa.array([t[0] for t in told], pa.int64()), *[pa.array([t[i] for t in told], pa.string()) for i in (1, 2)]]

    return _mapped(docs, path, text, keep, schema, rows)
