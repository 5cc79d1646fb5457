"""Vector arithmetic as columns, for small inputs, plans in SQL and tests. Bulk work runs in kernels.py.

Sums are left folds over doubles, so their value doesn't depend on how rows are partitioned.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def total(xs: Column) -> Column:
    return F.aggregate(xs, F.lit(0.0), lambda a, x: a + x)


def dot(a: Column, b: Column) -> Column:
    return total(F.zip_with(a, b, lambda x, y: x * y))


def d2(a: Column, b: Column) -> Column:
    return total(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)))


def chunk(vec: Column, j: int, width: int) -> Column:
    return F.slice(vec, j * width + 1, width)


def adc(lut: Column, code: Column) -> Column:
    """Sum of table entries: lut[j][code[j]] over chunks j."""
    return total(F.zip_with(lut, code, lambda row, k: F.get(row, k)))


def let(value: Column, f) -> Column:
    """f of a value that is computed once, however often f names it."""
    return F.get(F.transform(F.array(value), f), F.lit(0))


def softmax(xs: Column) -> Column:
    shifted = lambda v: let(F.array_max(v), lambda top: F.transform(v, lambda x: F.exp(x - top)))
    return let(let(xs, shifted), lambda e: let(total(e), lambda t: F.transform(e, lambda x: x / t)))


def unit_uniform(*parts: Column) -> Column:
    """A number in (0, 1) from an md5 of the parts: the same wherever and whenever it is drawn."""
    h = F.md5(F.concat_ws(":", *[p.cast("string") for p in parts]))
    return (F.conv(F.substring(h, 1, 8), 16, 10).cast("double") + 0.5) / 4294967296.0


def draw_key(*parts: Column) -> Column:
    """A pseudo-random order key: the smallest of a group is a uniform draw."""
    return F.md5(F.concat_ws(":", *[p.cast("string") for p in parts]))


def hash_share(c: str | Column) -> Column:
    """A number in [0, 1) of each value, for samples that don't depend on where rows lie."""
    return F.pmod(F.xxhash64(c, F.lit(3)), F.lit(1 << 31)) / F.lit(float(1 << 31))
