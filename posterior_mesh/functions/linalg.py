"""Linear algebra on row-major arrays: products as column expressions, solves as Arrow batches."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType

VECTOR = ArrayType(DoubleType())


def element(m: Column, i: int, j: int, d: int) -> Column:
    return m[i * d + j]


def matvec(m: Column, x: Column, d: int) -> Column:
    """m x, unrolled: d stays small."""
    return F.array(*[sum((m[i * d + j] * x[j] for j in range(1, d)), m[i * d] * x[0]) for i in range(d)])


def outer(x: Column, d: int) -> Column:
    return F.array(*[x[i] * x[j] for i in range(d) for j in range(d)])


def vector_sum(x: Column, n: int) -> Column:
    """Element by element over the rows of a group; partial sums happen before the shuffle."""
    return F.array(*[F.sum(x[i]) for i in range(n)])


def covariance(n: Column, s1: Column, s2: Column, ridge: float, d: int) -> Column:
    """Ridge plus the population covariance from a count, a sum and a sum of outer products."""
    return F.array(*[s2[i * d + j] / n - s1[i] * s1[j] / (n * n) + (ridge if i == j else 0.0) for i in range(d) for j in range(d)])


def steady(solve, otherwise, *stacks: np.ndarray) -> np.ndarray:
    """All matrices of a stack at once; where one is singular to working precision, each of its own, by the pseudo-inverse if need be."""
    try:
        return solve(*stacks)
    except np.linalg.LinAlgError:
        out = []
        for one in zip(*stacks):
            try:
                out.append(solve(*one))
            except np.linalg.LinAlgError:
                out.append(otherwise(*one))
        return np.stack(out)


@F.pandas_udf(VECTOR)
def spd_inverse(m: pd.Series) -> pd.Series:
    """Inverse of a symmetric positive definite matrix; null stays null."""
    out = [None] * len(m)
    kept = [i for i, x in enumerate(m) if x is not None]
    if kept:
        flat = np.stack([np.asarray(m.iloc[i], float) for i in kept])
        d = round(flat.shape[1] ** 0.5)
        inverse = steady(np.linalg.inv, np.linalg.pinv, flat.reshape(-1, d, d))
        for i, x in zip(kept, (inverse + inverse.transpose(0, 2, 1)) / 2):
            out[i] = x.ravel()
    return pd.Series(out)


@F.pandas_udf(VECTOR)
def spd_solve(m: pd.Series, b: pd.Series) -> pd.Series:
    """m⁻¹ b of each row."""
    if not len(m):
        return pd.Series([], dtype=object)
    right = np.stack(b.to_numpy())
    d = right.shape[1]
    left = np.stack(m.to_numpy()).reshape(-1, d, d)
    return pd.Series(list(steady(np.linalg.solve, lambda a, b: np.linalg.pinv(a) @ b, left, right[:, :, None])[:, :, 0]))


@F.pandas_udf(VECTOR)
def cholesky(m: pd.Series) -> pd.Series:
    if not len(m):
        return pd.Series([], dtype=object)
    flat = np.stack(m.to_numpy())
    d = round(flat.shape[1] ** 0.5)
    return pd.Series(list(np.linalg.cholesky(flat.reshape(-1, d, d)).reshape(-1, d * d)))


def toeplitz_precision(rho: Column, d: int) -> Column:
    """Inverse of the matrix of powers of rho, which has three diagonals."""
    rows = []
    for i in range(d):
        for j in range(d):
            rows.append((F.lit(1.0) if i in (0, d - 1) else 1 + rho * rho) / (1 - rho * rho) if i == j else -rho / (1 - rho * rho) if abs(i - j) == 1 else F.lit(0.0))
    return F.array(*rows) if d > 1 else F.array(F.lit(1.0))
