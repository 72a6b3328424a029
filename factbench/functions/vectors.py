"""Vectors as arrays: cosine and random-hyperplane signatures, in doubles."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F


def _c(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def dot(a: Column | str, b: Column | str) -> Column:
    products = F.zip_with(_c(a), _c(b), lambda x, y: x.cast("double") * y.cast("double"))
    return F.aggregate(products, F.lit(0.0), lambda s, x: s + x)


def norm(a: Column | str) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column | str, b: Column | str) -> Column:
    """Null where a vector is zero."""
    return dot(a, b) / F.nullif(norm(a) * norm(b), F.lit(0.0))


def plane(table: int, bit: int, dims: int) -> list[float]:
    """Signs that depend on nothing but their place, so that every run has the same planes."""
    out: list[float] = []
    block = 0
    while len(out) < dims:
        digest = hashlib.md5(f"{table}:{bit}:{block}".encode()).digest()
        out += [1.0 if byte >> k & 1 else -1.0 for byte in digest for k in range(8)]
        block += 1
    return out[:dims]


def signature(vector: Column | str, table: int, bits: int, dims: int) -> Column:
    """``bits`` signs of a vector of ``dims`` components against random planes, as one integer: for a few bits, without Python."""
    out = F.lit(0)
    for bit in range(bits):
        weights = F.array(*[F.lit(w) for w in plane(table, bit, dims)])
        out = out + F.when(dot(vector, weights) > 0, F.lit(1 << bit)).otherwise(0)
    return out
