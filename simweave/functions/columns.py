"""Similarity measures and codes as Column expressions."""

from __future__ import annotations

from math import pi

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The Mersenne prime of the parity hash family, and gaussian codes' scale and offset.
PRIME = (1 << 31) - 1
CODES_PER_UNIT, LIMIT = 4096, 8


def r2c(r: Column) -> Column:
    """Cosine of a pair whose sign bits agree with probability r."""
    return F.cos(F.lit(pi) * (F.lit(1.0) - F.least(F.greatest(r, F.lit(0.0)), F.lit(1.0))))


def c2r(c: Column) -> Column:
    return F.lit(1.0) - F.acos(F.least(F.greatest(c, F.lit(-1.0)), F.lit(1.0))) / F.lit(pi)


def feature_id(feature: Column) -> Column:
    """31-bit id of a string feature, the same in other engines: leading md5 digits modulo the prime."""
    return F.conv(F.substring(F.md5(feature), 1, 15), 16, 10).cast("long") % F.lit(PRIME)


def jaccard(a: Column, b: Column) -> Column:
    """Jaccard similarity of two arrays of distinct elements; 0 for two empty ones."""
    inter = F.size(F.array_intersect(a, b))
    union = F.size(a) + F.size(b) - inter
    return F.when(union > 0, inter / union).otherwise(0.0)


def binary_cosine(a: Column, b: Column) -> Column:
    product = F.size(a).cast("double") * F.size(b)
    return F.when(product > 0, F.size(F.array_intersect(a, b)) / F.sqrt(product)).otherwise(0.0)


def dot(a: Column, b: Column) -> Column:
    """Dot product of two dense arrays of one length."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def quantise_gaussian(x: Column) -> Column:
    """2-byte code of a gaussian in (-8, 8)."""
    code = F.floor((x + LIMIT) * CODES_PER_UNIT)
    return F.least(F.greatest(code, F.lit(0)), F.lit(2 * LIMIT * CODES_PER_UNIT - 1)).cast("int")


def dequantise_gaussian(code: Column) -> Column:
    """The mid-point of a code's step."""
    return (code + 0.5) / CODES_PER_UNIT - LIMIT


def matches(a: Column, b: Column) -> Column:
    """Equal bits of two packed words; 32 bits sit in a non-negative long."""
    return F.lit(32) - F.bit_count(a.bitwiseXOR(b))


def matches_int(a: Column, b: Column, lo: int, hi: int) -> Column:
    """Equal hashes among positions lo (included) to hi (not included) of two signatures."""
    pairs = F.zip_with(F.slice(a, lo + 1, hi - lo), F.slice(b, lo + 1, hi - lo), lambda x, y: (x == y).cast("int"))
    return F.aggregate(pairs, F.lit(0), lambda s, x: s + x)
