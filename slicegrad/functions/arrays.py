"""Vector arithmetic on array columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda p, q: p * q), F.lit(0.0), lambda acc, v: acc + v)


def plus(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda p, q: p + q)


def scaled(a: Column, by: Column | float) -> Column:
    return F.transform(a, lambda v: v * by)


def norm(a: Column) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda acc, v: acc + v * v))


def softmax(a: Column) -> Column:
    """Shifted by the maximum, so that nothing overflows."""
    e = F.transform(a, lambda v: F.exp(v - F.array_max(a)))
    return F.transform(e, lambda v: v / F.aggregate(e, F.lit(0.0), lambda acc, z: acc + z))


def argmax(a: Column) -> Column:
    """0-based, the first of equals."""
    return (F.array_position(a, F.array_max(a)) - 1).cast("long")


def sums(a: Column, k: int) -> Column:
    """Element-wise sum as an aggregate of k sums: partial sums before the shuffle."""
    return F.array(*[F.sum(F.get(a, j)) for j in range(k)])


def folded(arrays: Column) -> Column:
    """Element-wise sum of an array of equally long arrays."""
    return F.aggregate(F.slice(arrays, 2, F.greatest(F.size(arrays) - 1, F.lit(0))), F.get(arrays, 0), lambda acc, v: F.zip_with(acc, v, lambda p, q: p + q))


def literal(values) -> Column:
    return F.array(*[F.lit(float(v)) for v in values]) if len(values) else F.expr("cast(array() as array<double>)")


def bucket_of(id_: Column, buckets: int, seed: int) -> Column:
    """Mini-batch bucket of an integer id."""
    return F.pmod(id_ * 7919 + seed * 104729, F.lit(buckets))


def text_bucket(word: Column, buckets: int) -> Column:
    """Hashing trick that other engines can repeat: the first 8 hex digits of the MD5."""
    return F.pmod(F.conv(F.substring(F.md5(word.cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(buckets))
