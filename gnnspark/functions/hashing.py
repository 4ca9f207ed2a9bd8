"""Keyed uniforms: every random choice is a function of its keys, so any engine and any retry makes the same choice."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _col(key) -> Column:
    return key if isinstance(key, Column) else F.lit(key)


def uniform(seed, *keys, impl: str = "md5") -> Column:
    """A number in (0, 1) from the keys. ``md5`` is portable (the oracles use it); ``xxhash64`` is the fast form for production."""
    if impl == "xxhash64":
        bits = F.shiftrightunsigned(F.xxhash64(_col(seed), *map(_col, keys)), 11)
        return (bits + F.lit(0.5)) / F.lit(float(2**53))
    text = F.concat_ws(":", *[_col(k).cast("string") for k in (seed, *keys)])
    return (F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long") + F.lit(0.5)) / F.lit(4294967296.0)


def text_id(text: Column) -> Column:
    """A negative 60-bit id for a node that is only known by its text; needs no global ranking."""
    return -F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long") - 1


def race_key(u: Column, p: Column) -> Column:
    """Exponential race: ascending keys list nodes in the order of sequential weighted draws without replacement."""
    return -F.log(u) / p


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))
