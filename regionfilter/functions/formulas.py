"""Segments, divergence terms and size formulas as column expressions."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

LOG2E = math.log2(math.e)


def seg_of(score: Column, n: int) -> Column:
    """Segment 0..n-1 of a score. Null and NaN fall in the lowest, whose filter is strictest; scores are rounded
    to nine places first, so that building and probing agree whatever computed them."""
    safe = F.coalesce(F.nanvl(F.round(score.cast("double"), 9), F.lit(0.0)), F.lit(0.0))
    return F.least(F.lit(n - 1), F.greatest(F.lit(0), F.floor(F.least(F.greatest(safe, F.lit(0.0)), F.lit(1.0)) * n).cast("int")))


def kl_term(a: Column, b: Column) -> Column:
    """a * log2(a / b); 0 without keys, null where it is unbounded."""
    return F.when(a <= 0, F.lit(0.0)).when(b > 0, a * F.log2(a / F.when(b > 0, b)))


def plain_bits(n: Column, rate: Column, c: float = 1.0) -> Column:
    """Bits of one filter of n keys: c * n * log2(1 / rate)."""
    return F.when((rate >= 1) | (n == 0), F.lit(0.0)).otherwise(F.lit(c) * n * F.log2(1 / rate))


def standard_rate(m: Column, h: Column, n: Column) -> Column:
    """Asymptotic false-positive rate of an array of m bits with h hashes of n keys each."""
    return F.pow(1 - F.pow(1 - 1 / m, h * n), h)


def shingles(text: Column, n: int) -> Column:
    """array<string> of the word n-grams of a text; empty if it has fewer words."""
    words = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"\s+"), lambda w: w != "")
    # the words are bound once as a variable, or they would be split anew for each n-gram
    grams = F.transform(F.array(words), lambda w: F.when(F.size(w) >= n, F.transform(F.sequence(F.lit(1), F.size(w) - n + 1), lambda i: F.concat_ws(" ", F.slice(w, i, n)))))
    return F.coalesce(F.get(grams, F.lit(0)), F.array().cast("array<string>"))


def shingle_hashes(text: Column, n: int) -> Column:
    """array<bigint> of the hashes of a text's word n-grams: each word is hashed once, a gram is the hash of n of them."""
    words = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"\s+"), lambda w: w != "")
    hashed = F.transform(words, lambda w: F.xxhash64(w))
    grams = F.transform(F.array(hashed), lambda w: F.when(F.size(w) >= n, F.transform(F.sequence(F.lit(1), F.size(w) - n + 1), lambda i: F.xxhash64(F.slice(w, i, n)))))
    return F.coalesce(F.get(grams, F.lit(0)), F.array().cast("array<bigint>"))
