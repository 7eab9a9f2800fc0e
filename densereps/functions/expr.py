"""Column expressions: sampling keys, grid cells, distances, pair counts."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def md5_key(id_col: Column | str, seed: int) -> Column:
    """Key of the permutation: md5 of "seed:id"."""
    column = F.col(id_col) if isinstance(id_col, str) else id_col
    return F.md5(F.concat(F.lit(f"{seed}:"), column.cast("string")).cast("binary"))


def cell(column: Column | str, side: float | int) -> Column:
    column = F.col(column) if isinstance(column, str) else column
    return F.floor(column / F.lit(side)).cast("long")


def squared_2d(ax, ay, bx, by) -> Column:
    return (ax - bx) * (ax - bx) + (ay - by) * (ay - by)


def l2_squared(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def l1(a, b) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.abs(x - y)), F.lit(0.0), lambda s, x: s + x)


def l_infinity(a, b) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.abs(x - y)), F.lit(0.0), lambda s, x: F.greatest(s, x))


def dot(a, b) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def cosine(a, b) -> Column:
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def choose2(n: Column | str) -> Column:
    n = F.col(n) if isinstance(n, str) else n
    return (n * (n - 1) / 2).cast("long")
