"""Hash positions of elements, as built-in expressions.

Two families: ``md5`` (60 bits of an MD5, the same in any SQL engine) and ``xx`` (seeded xxhash64, for production).
Position i is (h1 + i * h2) mod m with h2 odd, both reduced mod m first so that no product overflows.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def u60(x: Column) -> Column:
    """The first 15 hex digits of md5(x) as bigint."""
    return F.conv(F.substring(F.md5(x), 1, 15), 16, 10).cast("bigint")


def u60_sql(x: str) -> str:
    """The same in DuckDB's SQL."""
    return f"('0x' || substr(md5({x}), 1, 15))::BIGINT"


def bucket(x: Column, salt: str, size: int = 100) -> Column:
    """A repeatable number below size for an element: a sample is a range of buckets."""
    return F.pmod(u60(F.concat(x, F.lit(f"#{salt}"))), F.lit(size)).cast("int")


def bases(elem: Column, family: str = "md5") -> tuple[Column, Column]:
    """Two hashes of an element, not negative."""
    if family == "md5":
        return u60(elem), u60(F.concat(elem, F.lit("#2")))
    if family == "xx":
        mask = F.lit((1 << 60) - 1)
        return F.xxhash64(elem).bitwiseAND(mask), F.xxhash64(elem, F.lit(2)).bitwiseAND(mask)
    raise ValueError(family)


def positions(elem: Column, hashes: Column | int, m: Column | int, family: str = "md5") -> Column:
    """array<bigint> of the bits of an element in an array of m bits."""
    h1, h2 = bases(elem, family)
    m = m if isinstance(m, Column) else F.lit(m)
    m = m.cast("bigint")
    n = hashes if isinstance(hashes, Column) else F.lit(hashes)
    first, step = F.pmod(h1, m), F.pmod(h2.bitwiseOR(F.lit(1).cast("bigint")), m)
    return F.transform(F.sequence(F.lit(0), n.cast("int") - 1), lambda i: F.pmod(first + i * step, m))
