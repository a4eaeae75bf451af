"""Column functions over vectors, sparse maps and hashes; native expressions only."""

from __future__ import annotations

from math import pi

from pyspark.sql import Column
from pyspark.sql import functions as F


def vec_dot(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def vec_norm(a: Column | str) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda s, x: s + x * x))


def vec_scale(a: Column | str, factor: Column) -> Column:
    return F.transform(a, lambda x: x * factor)


def vec_add(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def sq_distance(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def map_dot(a: Column | str, b: Column | str) -> Column:
    """Dot product of two attribute -> value maps; a missing attribute is 0."""
    both = F.map_zip_with(a, b, lambda k, x, y: F.coalesce(x, F.lit(0.0)) * F.coalesce(y, F.lit(0.0)))
    return F.aggregate(F.map_values(both), F.lit(0.0), lambda s, x: s + x)


def hash_uniform(*parts: Column) -> Column:
    """A number in (0, 1) that depends on the parts alone, so a retry gives it again."""
    return (F.pmod(F.xxhash64(*parts), F.lit(1 << 52)) + 0.5) / float(1 << 52)


def gaussian_hash(*parts: Column) -> Column:
    """A standard normal number that depends on the parts alone (Box and Muller)."""
    u, v = hash_uniform(*parts, F.lit(1)), hash_uniform(*parts, F.lit(2))
    return F.sqrt(-2.0 * F.log(u)) * F.cos(2.0 * pi * v)


def text_hash(value: Column | str, buckets: int) -> Column:
    """Bucket of a string by its MD5: the same in every engine that has MD5."""
    return F.conv(F.substring(F.md5(value), 1, 6), 16, 10).cast("long") % buckets
