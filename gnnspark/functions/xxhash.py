"""The ``xxhash64`` form of a uniform in numpy: the numbers of :func:`hashing.uniform` without a row for each of them."""

from __future__ import annotations

import numpy as np

_U = np.uint64
_P1, _P2, _P3, _P4, _P5 = map(_U, (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
START = np.array([42], _U)
#: Hashes of one pass.
PIECE = 16384


def _turned(x: np.ndarray, by: int) -> np.ndarray:
    return (x << _U(by)) | (x >> _U(64 - by))


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> _U(33))) * _P2
    h = (h ^ (h >> _U(29))) * _P3
    return h ^ (h >> _U(32))


def long_part(x: np.ndarray) -> np.ndarray:
    """What a long adds to a hash, apart from the hash so far."""
    return _turned(np.asarray(x, np.int64).view(_U) * _P2, 31) * _P1


def _pieces(part: np.ndarray, so_far: np.ndarray):
    """(first place, hashes) of :func:`with_part`, in pieces that stay in a core's cache; a piece is overwritten by the next one."""
    head, n = so_far + (_P5 + _U(8)), max(len(part), len(so_far))
    h, t = np.empty(min(n, PIECE), _U), np.empty(min(n, PIECE), _U)
    for i in range(0, n, PIECE):
        a, b = (x[i : i + PIECE] if len(x) > 1 else x for x in (part, head))
        x, y = h[: min(PIECE, n - i)], t[: min(PIECE, n - i)]
        np.bitwise_xor(a, b, out=x)
        np.left_shift(x, _U(27), out=y)
        x >>= _U(37)
        x |= y
        x *= _P1
        x += _P4
        for by, times in ((33, _P2), (29, _P3), (32, None)):
            np.right_shift(x, _U(by), out=y)
            x ^= y
            if times is not None:
                x *= times
        yield i, x


def with_part(part: np.ndarray, so_far: np.ndarray) -> np.ndarray:
    out = np.empty(max(len(part), len(so_far)), _U)
    for i, h in _pieces(part, so_far):
        out[i : i + len(h)] = h
    return out


def least_hash(u: np.ndarray) -> np.ndarray:
    """Hashes that no uniform of ``u`` or more lies below; rounding is on the safe side."""
    return np.maximum(np.floor(u * 4294967296.0) - 2, 0).astype(_U) << _U(32)


def most_hash(u: np.ndarray) -> np.ndarray:
    """Hashes that no uniform of ``u`` or less lies above."""
    return (np.minimum(np.floor(u * 4294967296.0) + 2, 4294967295.0).astype(_U) << _U(32)) | _U(0xFFFFFFFF)


def reaching(part: np.ndarray, so_far: np.ndarray, least: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(places, hashes) of those of :func:`with_part` that are ``least`` (of each place) or more."""
    found = [(i + at, h[at]) for i, h in _pieces(part, so_far) for at in (np.flatnonzero(h >= least[i : i + len(h)]),)]
    return tuple(map(np.concatenate, zip(*found))) if found else (np.zeros(0, np.int64), np.zeros(0, _U))


def with_long(x, so_far: np.ndarray) -> np.ndarray:
    return with_part(long_part(np.atleast_1d(np.asarray(x, np.int64))), so_far)


def with_int(x: int, so_far: np.ndarray) -> np.ndarray:
    return _mixed(_turned((so_far + _P5 + _U(4)) ^ (np.array([x & 0xFFFFFFFF], _U) * _P1), 23) * _P2 + _P3)


def uniforms(h: np.ndarray) -> np.ndarray:
    u = (h >> _U(11)).astype(np.float64)
    u += 0.5
    u /= float(2**53)
    return u
