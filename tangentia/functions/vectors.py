"""Vector and small-matrix expressions on array columns; all stay on the JVM side."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

DOT = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def col(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def vec_dot(a, b) -> Column:
    return DOT(col(a), col(b))


def vec_add(a, b) -> Column:
    return F.zip_with(col(a), col(b), lambda x, y: x + y)


def vec_sub(a, b) -> Column:
    return F.zip_with(col(a), col(b), lambda x, y: x - y)


def vec_scale(a, s) -> Column:
    s = s if isinstance(s, Column) else F.lit(float(s))
    return F.transform(col(a), lambda x: x * s)


def vec_dist2(a, b) -> Column:
    return F.aggregate(F.zip_with(col(a), col(b), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def vec_dist(a, b) -> Column:
    return F.sqrt(vec_dist2(a, b))


def vec_norm(a) -> Column:
    return F.sqrt(F.aggregate(col(a), F.lit(0.0), lambda s, x: s + x * x))


def vec_cosine(a, b) -> Column:
    return vec_dot(a, b) / (vec_norm(a) * vec_norm(b))


def signed_round(x, digits: int = 6) -> Column:
    """Rounded; what becomes zero keeps its sign, as it does in SQL (Spark's own rounding goes through decimals, which have no negative zero).

    Decimals are slow: a number that is no half, and not so large that its product errs, is the nearest to a whole number of steps.
    """
    x, step = col(x), F.lit(10.0**digits)
    whole = F.floor(x * step + 0.5)
    r = F.when((F.abs(x) < 10.0 ** (11 - digits)) & (x * step + 0.5 - whole).between(1e-3, 1 - 1e-3), whole / step).otherwise(F.round(x, digits))
    return F.when(r == 0, x * F.lit(0.0)).otherwise(r)


def vec_round(a, digits: int = 6) -> Column:
    return F.transform(col(a), lambda x: signed_round(x, digits))


def mat_vec(m, v) -> Column:
    """Rows of an array of arrays, each times a vector."""
    v = col(v)
    return F.transform(col(m), lambda row: DOT(row, v))


def mat_mul_t(a, b) -> Column:
    """a times the transpose of b, both arrays of rows: the table of inner products of their rows."""
    b = col(b)
    return F.transform(col(a), lambda x: F.transform(b, lambda y: DOT(x, y)))


def det2(m) -> Column:
    g = lambda i, j: col(m)[i][j]
    return g(0, 0) * g(1, 1) - g(0, 1) * g(1, 0)


def det3(m) -> Column:
    g = lambda i, j: col(m)[i][j]
    minor = lambda a, b: g(1, a) * g(2, b) - g(1, b) * g(2, a)
    return g(0, 0) * minor(1, 2) - g(0, 1) * minor(0, 2) + g(0, 2) * minor(0, 1)


def is_valid(x, size: int | None = None) -> Column:
    """Not null, of the given length, and all components finite."""
    c = col(x)
    ok = c.isNotNull() & F.forall(c, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    return F.coalesce(ok & (F.size(c) == size) if size else ok & (F.size(c) > 0), F.lit(False))
