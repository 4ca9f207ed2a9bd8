"""The 32 bits behind the md5 form of a uniform, in numpy: for all pairs of a head and a tail of the hashed text."""

from __future__ import annotations

import hashlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np

_SHIFTS = np.repeat(np.array([7, 12, 17, 22, 5, 9, 14, 20, 4, 11, 16, 23, 6, 10, 15, 21], np.uint32).reshape(4, 1, 4), 4, axis=1).ravel()
_ADDS = np.floor(np.abs(np.sin(np.arange(1, 65, dtype=float))) * 2**32).astype(np.uint32)
_START = np.array([0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476], np.uint32)
_WORDS = [*range(16), *[(5 * i + 1) % 16 for i in range(16, 32)], *[(3 * i + 5) % 16 for i in range(32, 48)], *[7 * i % 16 for i in range(48, 64)]]
#: Pairs of one call, so that its arrays stay in a core's cache; and the longest text of a single md5 block.
PAIRS, LONGEST = 16384, 55


def _digest_starts(words: list[np.ndarray], shape: tuple[int, int]) -> np.ndarray:
    """The first 32 bits of the md5 of single blocks, read as hex digits are. ``words``: 16 arrays that broadcast to ``shape``."""
    a, b, c, d = (np.full(shape, x, np.uint32) for x in _START)
    f, t = np.empty(shape, np.uint32), np.empty(shape, np.uint32)
    for i in range(64):
        if i < 16:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
        elif i < 32:
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
        elif i < 48:
            np.bitwise_xor(b, c, out=f)
            f ^= d
        else:
            np.invert(d, out=f)
            f |= b
            f ^= c
        f += a
        f += words[_WORDS[i]] + _ADDS[i : i + 1]
        np.right_shift(f, np.uint32(32) - _SHIFTS[i], out=t)
        f <<= _SHIFTS[i]
        f |= t
        f += b
        a, b, c, d, f = d, f, b, c, a
    return (a + _START[0]).byteswap()


def _block(texts: list[bytes], at: int, end: bool) -> np.ndarray:
    """(16, n) words of blocks that hold only ``texts``, all of one length, from byte ``at``, and the padding if the text ends there."""
    n, k = len(texts), len(texts[0])
    raw = np.zeros((n, 64), np.uint8)
    raw[:, at : at + k] = np.frombuffer(b"".join(texts), np.uint8).reshape(n, k)
    if end:
        raw[:, at + k] = 0x80
        raw[:, 56:58] = np.frombuffer((8 * (at + k)).to_bytes(2, "little"), np.uint8)
    return np.ascontiguousarray(raw.view("<u4").T)


def _by_length(texts: list[bytes]) -> list[np.ndarray]:
    out = defaultdict(list)
    for i, x in enumerate(texts):
        out[len(x)].append(i)
    return [np.array(x) for x in out.values()]


def pair_bits(heads: list[bytes], tails: list[bytes]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(places of heads, places of tails, bits): the bits of all their concatenations, in pieces of bounded size."""
    for hs in _by_length(heads):
        for ts in _by_length(tails):
            k = len(heads[hs[0]])
            for j in range(0, len(ts), PAIRS):
                tj = ts[j : j + PAIRS]
                step = max(1, PAIRS // len(tj))
                fits = k + len(tails[tj[0]]) <= LONGEST
                tail = _block([tails[x] for x in tj], k, True)[:, None, :] if fits else None
                for i in range(0, len(hs), step):
                    hi = hs[i : i + step]
                    if not fits:
                        yield hi, tj, np.array([[int(hashlib.md5(heads[x] + tails[y]).hexdigest()[:8], 16) for y in tj] for x in hi], np.uint32)
                        continue
                    head = _block([heads[x] for x in hi], 0, False)[:, :, None]
                    words = [tail[w] if 4 * w >= k else head[w] if 4 * w + 4 <= k else head[w] | tail[w] for w in range(16)]
                    yield hi, tj, _digest_starts(words, (len(hi), len(tj)))


class Tails:
    """Ids in decimal as tails of hashed texts, for calls that pair them freely. The words of one alignment are held, as heads of a task hardly change in length."""

    def __init__(self, ids: np.ndarray):
        text = np.asarray(ids).astype("S20")
        self.size = np.char.str_len(text).astype(np.uint32)
        self.most, self.same = int(self.size.max(initial=0)), len(np.unique(self.size)) < 2
        self.raw = text.view(np.uint8).reshape(len(text), 20)[:, : self.most]
        self.shift, self.words = -1, np.zeros((0, 0), np.uint32)

    def shifted(self, by: int) -> np.ndarray:
        """(words, n): the tails from byte ``by`` of a block's word on, each with its end mark."""
        if by != self.shift:
            raw = np.zeros((len(self.raw), -(-(by + self.most + 1) // 4) * 4), np.uint8)
            raw[:, by : by + self.most] = self.raw
            raw[np.arange(len(raw)), by + self.size] = 0x80
            self.shift, self.words = by, np.ascontiguousarray(raw.view("<u4").T)
        return self.words

    def bits(self, heads: list[bytes], which: np.ndarray | None, at: np.ndarray) -> np.ndarray:
        """The bits of head ``which[i]`` before tail ``at[i]``, for all i; of the only head if ``which`` is none."""
        out = np.empty(len(at), np.uint32)
        for hs in _by_length(heads):
            k, own = len(heads[hs[0]]), np.full(len(heads), -1)
            own[hs] = np.arange(len(hs))
            if len(hs) == len(heads):
                mine = None
            else:
                mine = np.flatnonzero(own[which] >= 0)
            if k + self.most > LONGEST:
                for i in range(len(at)) if mine is None else mine.tolist():
                    text = heads[0 if which is None else which[i]] + self.raw[at[i]].tobytes().rstrip(b"\0")
                    out[i] = int(hashlib.md5(text).hexdigest()[:8], 16)
                continue
            head, tail, first = _block([heads[x] for x in hs], 0, False), self.shifted(k % 4), k // 4
            for i in range(0, len(at) if mine is None else len(mine), PAIRS):
                some = slice(i, i + PAIRS) if mine is None else mine[i : i + PAIRS]
                t = at[some]
                h = np.zeros(1, np.int64) if len(hs) == 1 else own[which[some]]
                words = [head[w][h] for w in range(first)] + [x[t] for x in tail]
                if k % 4:
                    words[first] |= head[first][h]
                words += [np.zeros(1, np.uint32)] * (16 - len(words))
                words[14] = np.uint32(8) * (np.uint32(k) + (self.size[t[:1]] if self.same else self.size[t]))
                out[some] = _digest_starts(words, (len(t),))
        return out
