"""How alike two tangent planes are: arrays of orthonormal rows, strongest direction first."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from tangentia.functions.vectors import DOT, col, det2, det3, mat_mul_t

MODES = ("l1", "l2", "det", "vol", "projection")


def tangent_similarity(a, b, mode: str = "l1", dim: int = 2) -> Column:
    """A score in [0, 1].

    l1, l2: mean and root mean square of |cosine| of like-ranked directions (not invariant to a turn within the plane).
    det: |determinant| of the table of inner products, equal dimensions. vol: square root of the determinant of that
    table times its transpose, the smaller basis giving the rows. projection: the table's Frobenius norm over the root
    of the dimension (ours; invariant). det and vol are expressions up to three directions, a vectorised UDF beyond.
    """
    a, b = col(a), col(b)
    pairs = F.zip_with(a, b, lambda x, y: F.abs(DOT(x, y)))
    if mode == "l1":
        return F.least(F.aggregate(pairs, F.lit(0.0), lambda s, x: s + x) / F.size(pairs), F.lit(1.0))
    if mode == "l2":
        return F.least(F.sqrt(F.aggregate(pairs, F.lit(0.0), lambda s, x: s + x * x) / F.size(pairs)), F.lit(1.0))
    table = mat_mul_t(a, b)
    if mode == "projection":
        square = F.aggregate(F.flatten(table), F.lit(0.0), lambda s, x: s + x * x)
        return F.least(F.sqrt(square / F.least(F.size(a), F.size(b))), F.lit(1.0))
    if mode == "det":
        if dim == 1:
            return F.least(F.abs(table[0][0]), F.lit(1.0))
        return F.least(F.abs(det2(table)), F.lit(1.0)) if dim == 2 else F.least(F.abs(det3(table)), F.lit(1.0)) if dim == 3 else plane_angle(a, b)
    if mode == "vol":
        if dim > 3:
            return plane_angle(a, b)
        small = F.when(F.size(a) <= F.size(b), table).otherwise(mat_mul_t(b, a))
        gram = mat_mul_t(small, small)
        d = F.when(F.size(gram) == 1, gram[0][0]).when(F.size(gram) == 2, det2(gram)).otherwise(det3(gram))
        return F.least(F.sqrt(F.greatest(d, F.lit(0.0))), F.lit(1.0))
    raise ValueError(f"unknown mode {mode!r}; one of {MODES}")


@F.pandas_udf(DoubleType())
def plane_angle(a: pd.Series, b: pd.Series) -> pd.Series:
    def one(x, y):
        x, y = np.stack(x), np.stack(y)
        t = x @ y.T if len(x) <= len(y) else y @ x.T
        return float(min(1.0, np.sqrt(max(0.0, np.linalg.det(t @ t.T)))))

    return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)])


def score_arrays(a: np.ndarray, b: np.ndarray, mode: str = "l1") -> np.ndarray:
    """The same scores of stacks (n, dim, D), for tests and array paths."""
    if mode in ("l1", "l2"):
        c = np.abs(np.einsum("nkd,nkd->nk", a, b))
        return np.minimum(c.mean(1) if mode == "l1" else np.sqrt((c**2).mean(1)), 1)
    t = np.einsum("nkd,nld->nkl", a, b)
    if mode == "projection":
        return np.minimum(np.sqrt((t**2).sum((1, 2)) / min(a.shape[1], b.shape[1])), 1)
    if a.shape[1] > b.shape[1]:
        t = t.transpose(0, 2, 1)
    return np.minimum(np.sqrt(np.maximum(np.linalg.det(t @ t.transpose(0, 2, 1)), 0)), 1)
