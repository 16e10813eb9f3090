"""Column functions shared by the operators. All hashes are prefixes of MD5, so that any engine can repeat them."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: 32-bit modulus of the MinHash maps: the Mersenne prime 2**31 - 1.
PRIME = 2147483647


def h32(value: Column) -> Column:
    """First 32 bits of MD5 as a non-negative long."""
    return F.conv(F.substring(F.md5(value.cast("string")), 1, 8), 16, 10).cast("long")


def h60(value: Column) -> Column:
    """First 60 bits of MD5 as a non-negative long."""
    return F.conv(F.substring(F.md5(value.cast("string")), 1, 15), 16, 10).cast("long")


def unit(value: Column, seed: str) -> Column:
    """Uniform number in (0, 1) drawn from a key."""
    return (h32(F.concat(value.cast("string"), F.lit(f":{seed}"))) + 0.5) / 4294967296.0


def words(text: Column) -> Column:
    """Parts between whitespace."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), r"\s+"), lambda w: w != "")


def tokens(text: Column) -> Column:
    """Lower-cased runs of letters, digits and underscores."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(r"([\p{L}\p{N}_]+)"), F.lit(1))


def lines(text: Column) -> Column:
    """Lines that hold something."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: F.trim(x) != "")


def shingles(parts: Column, n: int) -> Column:
    """Distinct n-grams of an array of words as 32-bit hashes; fewer than n words: none."""
    grams = F.transform(
        F.sequence(F.lit(1), F.size(parts) - (n - 1)), lambda i: h32(F.array_join(F.slice(parts, i, n), " "))
    )
    return F.when(F.size(parts) >= n, F.array_distinct(grams)).otherwise(F.array().cast("array<bigint>"))


def jaccard(a: Column, b: Column) -> Column:
    """Of two arrays of distinct values; two empty ones: 0."""
    both = F.size(F.array_intersect(a, b))
    return F.coalesce(both / F.nullif(F.size(a) + F.size(b) - both, F.lit(0)), F.lit(0.0))


def ratio(a: Column, b: Column) -> Column:
    """a / b as double; 0 where b is 0."""
    return F.coalesce(a.cast("double") / F.nullif(b.cast("double"), F.lit(0.0)), F.lit(0.0))


def sigmoid(x: Column) -> Column:
    """Stable for large arguments of either sign."""
    return F.when(x >= 0, 1 / (1 + F.exp(-x))).otherwise(F.exp(x) / (1 + F.exp(x)))


def harmonic(*parts: Column) -> Column:
    """Harmonic mean; 0 if any part is 0."""
    return F.when(F.least(*parts) <= 0, F.lit(0.0)).otherwise(len(parts) / sum(1.0 / p for p in parts))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def distance(a: Column, b: Column) -> Column:
    """Euclidean."""
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, x: s + x))
