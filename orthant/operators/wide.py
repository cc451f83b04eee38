"""Matrix algebra on factors as tables (key, f0 ... f{k-1}), in DataFrame operations alone.

A product with the data is one join and one wide sum, which stays in whole-stage code generation. A Gram
matrix is one row of k (k + 1) / 2 sums. Sweeps are chains of columns, each seeing those before it. Factors
up to ``BROADCAST_CELLS`` cells are broadcast to the data; larger ones are joined by a shuffle.
"""

from __future__ import annotations

from functools import reduce
from operator import add

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import hash_normal, hash_uniform
from .kernels import EPS

BROADCAST_CELLS = 4_000_000


def cols(k: int, p: str = "f") -> list[str]:
    return [f"{p}{j}" for j in range(k)]


def total(terms) -> Column:
    return reduce(add, terms)


def keys_of(x: DataFrame, side: str) -> DataFrame:
    return x.select(F.col(f"{side}_key").alias("key")).distinct()


def uniform_factor(keys: DataFrame, k: int, seed: int, scale: Column | float = 1.0) -> DataFrame:
    """Starting values: uniform hashes of the key, times ``scale``."""
    s = scale if isinstance(scale, Column) else F.lit(scale)
    return keys.select("key", *((hash_uniform(F.col("key"), j, seed) * s).alias(f"f{j}") for j in range(k)))


def normal_factor(keys: DataFrame, s: int, seed: int) -> DataFrame:
    """The Gaussian sampling matrix, never stored: a function of key, column and seed."""
    return keys.select("key", *(hash_normal(F.col("key"), j, seed).alias(f"f{j}") for j in range(s)))


def near(factor: DataFrame, k: int, rows: int | None) -> DataFrame:
    """``factor`` with a broadcast hint if its counted size allows that."""
    return F.broadcast(factor) if rows is not None and rows * (k + 1) <= BROADCAST_CELLS else factor


def times(x: DataFrame, b: DataFrame, k: int, rows: int | None = None) -> DataFrame:
    """X B: (key of the row, f0...)."""
    j = x.join(near(b.withColumnRenamed("key", "col_key"), k, rows), "col_key")
    return j.groupBy(F.col("row_key").alias("key")).agg(*(F.sum(F.col("value") * F.col(c)).alias(c) for c in cols(k)))


def times_t(x: DataFrame, a: DataFrame, k: int, rows: int | None = None) -> DataFrame:
    """X' A: (key of the column, f0...)."""
    j = x.join(near(a.withColumnRenamed("key", "row_key"), k, rows), "row_key")
    return j.groupBy(F.col("col_key").alias("key")).agg(*(F.sum(F.col("value") * F.col(c)).alias(c) for c in cols(k)))


def gram(f: DataFrame, k: int, p: str = "g") -> DataFrame:
    """F' F as one row g{i}_{j}, both triangles."""
    upper = f.agg(*(F.sum(F.col(f"f{i}") * F.col(f"f{j}")).alias(f"{p}{i}_{j}") for i in range(k) for j in range(i, k)))
    return upper.select(*(F.col(f"{p}{min(i, j)}_{max(i, j)}").alias(f"{p}{i}_{j}") for i in range(k) for j in range(k)))


def cross_gram(left: DataFrame, s: int, right: DataFrame, k: int, p: str = "c") -> DataFrame:
    """L' F as one row c{i}_{j} (s x k); both tables have the same keys."""
    r = right.select("key", *(F.col(f"f{j}").alias(f"r{j}") for j in range(k)))
    return left.join(r, "key").agg(*(F.sum(F.col(f"f{i}") * F.col(f"r{j}")).alias(f"{p}{i}_{j}") for i in range(s) for j in range(k)))


def small_product(f: DataFrame, s: int, c: DataFrame, k: int, p: str = "c") -> DataFrame:
    """F C row by row: F has s columns, C is one row of s x k values."""
    return f.crossJoin(F.broadcast(c)).select("key", *(total(F.col(f"f{i}") * F.col(f"{p}{i}_{j}") for i in range(s)).alias(f"f{j}") for j in range(k)))


def small_gram(c: DataFrame, s: int, k: int, p: str = "c", q: str = "g") -> DataFrame:
    """C' C of one row of s x k values."""
    return c.select(*(total(F.col(f"{p}{m}_{i}") * F.col(f"{p}{m}_{j}") for m in range(s)).alias(f"{q}{i}_{j}") for i in range(k) for j in range(k)))


def _with_target(f: DataFrame, h: DataFrame, g: DataFrame, k: int) -> DataFrame:
    t = h.select("key", *(F.col(f"f{j}").alias(f"h{j}") for j in range(k)))
    out = f.join(t, "key", "left").crossJoin(F.broadcast(g))  # g is one row
    return out.withColumns({f"h{j}": F.coalesce(f"h{j}", F.lit(0.0)) for j in range(k)})


def _fg(k: int, j: int) -> Column:
    return total(F.col(f"f{i}") * F.col(f"g{i}_{j}") for i in range(k))


def sweep(f: DataFrame, h: DataFrame, g: DataFrame, k: int, alpha: float = 0.0, beta: float = 0.0) -> DataFrame:
    """The Gram sweep, with sparsity and smoothness."""
    out = _with_target(f, h, g, k)
    for j in range(k):
        own = F.col(f"g{j}_{j}")
        new = F.greatest(F.col(f"h{j}") - _fg(k, j) + F.col(f"f{j}") * own - F.lit(alpha), F.lit(0.0)) / (own + F.lit(beta))
        out = out.withColumn(f"f{j}", F.when(own > EPS, new).otherwise(F.col(f"f{j}")))
    return out.select("key", *cols(k))


def multiplicative(f: DataFrame, h: DataFrame, g: DataFrame, k: int) -> DataFrame:
    out = _with_target(f, h, g, k)
    return out.select("key", *((F.col(f"f{j}") * F.greatest(F.col(f"h{j}"), F.lit(0.0)) / (_fg(k, j) + EPS)).alias(f"f{j}") for j in range(k)))


def signed_multiplicative(f: DataFrame, h: DataFrame, g: DataFrame, k: int) -> DataFrame:
    out = _with_target(f, h, g, k)
    zero = F.lit(0.0)
    up = [F.greatest(F.col(f"h{j}"), zero) + total(F.col(f"f{i}") * F.greatest(-F.col(f"g{i}_{j}"), zero) for i in range(k)) for j in range(k)]
    down = [F.greatest(-F.col(f"h{j}"), zero) + total(F.col(f"f{i}") * F.greatest(F.col(f"g{i}_{j}"), zero) for i in range(k)) for j in range(k)]
    return out.select("key", *((F.col(f"f{j}") * F.sqrt(up[j] / (down[j] + EPS))).alias(f"f{j}") for j in range(k)))


def clipped_least_squares(f: DataFrame, h: DataFrame, g: DataFrame, k: int) -> DataFrame:
    """clip(H G^-1). G is k x k: its inverse is made on the driver."""
    import numpy as np

    row = g.first()
    m = np.array([[row[f"g{i}_{j}"] for j in range(k)] for i in range(k)])
    inverse = np.linalg.inv(m + (1e-10 * np.trace(m) / k + EPS) * np.eye(k))
    out = _with_target(f, h, g, k)
    return out.select("key", *(F.greatest(total(F.col(f"h{i}") * F.lit(float(inverse[i, j])) for i in range(k)), F.lit(0.0)).alias(f"f{j}") for j in range(k)))


def projected_gradient(f: DataFrame, h: DataFrame, g: DataFrame, k: int, steps: int = 1) -> DataFrame:
    import numpy as np

    row = g.first()
    length = float(np.linalg.eigvalsh(np.array([[row[f"g{i}_{j}"] for j in range(k)] for i in range(k)]))[-1])
    out = _with_target(f, h, g, k)
    for _ in range(steps):
        out = out.withColumns({f"f{j}": F.greatest(F.col(f"f{j}") - (_fg(k, j) - F.col(f"h{j}")) / F.lit(length), F.lit(0.0)) for j in range(k)})
    return out.select("key", *cols(k))


def gradient(f: DataFrame, h: DataFrame, g: DataFrame, k: int) -> DataFrame:
    """F G - H, row by row."""
    out = _with_target(f, h, g, k)
    return out.select("key", *((_fg(k, j) - F.col(f"h{j}")).alias(f"f{j}") for j in range(k)))


def normalise(f: DataFrame, other: DataFrame, k: int) -> tuple[DataFrame, DataFrame]:
    """Unit columns of f; their norms go to ``other``, so that the product is unchanged."""
    size = f.agg(*(F.sqrt(F.sum(F.col(c) * F.col(c))).alias(f"n{c}") for c in cols(k)))
    size = F.broadcast(size.select(*(F.when(F.col(f"n{c}") > 0, F.col(f"n{c}")).otherwise(1.0).alias(f"n{c}") for c in cols(k))))
    return f.crossJoin(size).select("key", *((F.col(c) / F.col(f"n{c}")).alias(c) for c in cols(k))), other.crossJoin(size).select("key", *((F.col(c) * F.col(f"n{c}")).alias(c) for c in cols(k)))


def orthonormal(y: DataFrame, s: int) -> DataFrame:
    """The orthonormal factor of Y with positive diagonal, by its s x s Gram matrix: one aggregate to the driver,
    one row-local pass. Twice, so that orthonormality doesn't suffer from the squared condition."""
    import numpy as np

    for _ in range(2):
        row = gram(y, s).first()
        m = np.array([[row[f"g{i}_{j}"] for j in range(s)] for i in range(s)])
        inverse = np.linalg.inv(np.linalg.cholesky(m)).T
        y = y.select("key", *(total(F.col(f"f{i}") * F.lit(float(inverse[i, j])) for i in range(j + 1)).alias(f"f{j}") for j in range(s)))
    return y


def sample_range(x: DataFrame, columns: DataFrame, s: int, w: int, seed: int) -> DataFrame:
    """(X X')^w X Omega."""
    y = times(x, normal_factor(columns, s, seed), s)
    for _ in range(w):
        y = times(x, times_t(x, y, s), s)
    return y


def gaussian_sketch(x: DataFrame, columns: DataFrame, s: int, seed: int) -> DataFrame:
    """The unstructured, distance-preserving projection X Omega / sqrt(s)."""
    y = times(x, normal_factor(columns, s, seed), s)
    return y.select("key", *((F.col(c) / F.lit(s**0.5)).alias(c) for c in cols(s)))
