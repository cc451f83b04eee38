"""User-defined functions, aggregates and table functions, and their registration for SQL."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def gini_agg(v: pd.Series) -> float:
    """Gini coefficient of a group that fits a task (a component of B); null if it sums to zero."""
    x = np.sort(v.dropna().to_numpy())
    n, s = len(x), x.sum()
    return float(((2 * np.arange(1, n + 1) - n - 1) * x).sum() / (n * s)) if n and s > 0 else None


def gram_sweep_udf(g: np.ndarray):
    """A scalar function (h, a) -> a for a fixed Gram matrix."""
    from ..operators.kernels import gram_sweep

    @F.pandas_udf("array<double>")
    def run(h: pd.Series, a: pd.Series) -> pd.Series:
        return pd.Series(gram_sweep(np.stack(h.to_list()), g, np.stack(a.to_list())).tolist()) if len(h) else a

    return run


@F.udtf(returnType=T.StructType([T.StructField("col_key", T.LongType()), T.StructField("value", T.DoubleType())]))
class ExplodeCells:
    """The non-zero cells of an array."""

    def eval(self, vec) -> Iterator[tuple[int, float]]:
        for i, v in enumerate(vec or ()):
            if v:
                yield i, float(v)


@F.udtf(returnType=T.StructType([T.StructField("place", T.IntegerType()), T.StructField("value", T.DoubleType())]))
class Reconstruct:
    """The model's cells of one row: a (k) against B's rows laid end to end (n * k)."""

    def eval(self, a, b) -> Iterator[tuple[int, float]]:
        k = len(a or ())
        for i in range(len(b or ()) // k if k else 0):
            yield i, float(sum(x * y for x, y in zip(a, b[i * k : (i + 1) * k], strict=True)))


def register(spark: SparkSession) -> None:
    """SQL names: gini_agg, explode_cells, reconstruct, and the expressions vec_dot, vec_norm, vec_argmax."""
    spark.udf.register("gini_agg", gini_agg)
    spark.udtf.register("explode_cells", ExplodeCells)
    spark.udtf.register("reconstruct", Reconstruct)
    for name, args, body in (
        ("vec_dot", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v)"),
        ("vec_norm", "a ARRAY<DOUBLE>", "sqrt(aggregate(transform(a, x -> x * x), 0D, (s, v) -> s + v))"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS DOUBLE RETURN {body}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_argmax(a ARRAY<DOUBLE>) RETURNS INT RETURN cast(array_position(a, array_max(a)) - 1 AS INT)")
