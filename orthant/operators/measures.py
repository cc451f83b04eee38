"""Accuracy, sparsity and control measures."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .wide import cols, gram, near, total


def model_cells(x: DataFrame, a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    """Every cell of rows x columns, zeros included: (value, model). For small matrices and tests."""
    left = a.select(F.col("key").alias("row_key"), *(F.col(c).alias(f"a{c}") for c in cols(k)))
    right = b.select(F.col("key").alias("col_key"), *(F.col(c).alias(f"b{c}") for c in cols(k)))
    grid = left.crossJoin(F.broadcast(right)).select("row_key", "col_key", total(F.col(f"a{c}") * F.col(f"b{c}") for c in cols(k)).alias("model"))
    return grid.join(x, ["row_key", "col_key"], "left").select(F.coalesce("value", F.lit(0.0)).alias("value"), "model")


def objective_cells(x: DataFrame, a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    gap = F.col("value") - F.col("model")
    return model_cells(x, a, b, k).agg((F.sum(gap * gap) * 0.5).alias("objective"))


def objective_trace(x: DataFrame, a: DataFrame, b: DataFrame, k: int, a_rows: int | None = None, b_rows: int | None = None) -> DataFrame:
    """Half the squared error without any d x n product: one pass over the nonzeros and two Gram matrices."""
    left = a.select(F.col("key").alias("row_key"), *(F.col(c).alias(f"a{c}") for c in cols(k)))
    right = b.select(F.col("key").alias("col_key"), *(F.col(c).alias(f"b{c}") for c in cols(k)))
    hit = x.join(near(left, k, a_rows), "row_key").join(near(right, k, b_rows), "col_key")
    data = hit.agg(F.sum(F.col("value") * total(F.col(f"a{c}") * F.col(f"b{c}") for c in cols(k))).alias("xm"))
    norm = x.agg(F.sum(F.col("value") * F.col("value")).alias("xx"))
    ga, gb = gram(a, k, "p"), gram(b, k, "q")
    both = ga.crossJoin(gb).crossJoin(data).crossJoin(norm)  # rows of one
    mm = total(F.col(f"p{i}_{j}") * F.col(f"q{i}_{j}") for i in range(k) for j in range(k))
    return both.select(((F.col("xx") - 2 * F.col("xm") + mm) * 0.5).alias("objective"), F.col("xx"))


def relative_error(trace: DataFrame) -> DataFrame:
    return trace.select(F.sqrt(2 * F.greatest(F.col("objective"), F.lit(0.0)) / F.col("xx")).alias("relative_error"))


def gini(values: DataFrame, column: str, partitions: int | None = None) -> DataFrame:
    """Gini coefficient of all values of a column, null if they sum to zero. Ranks come from a range
    partitioning and the counts of the partitions before, so that no task holds more than its range."""
    v = values.select(F.col(column).cast("double").alias("v")).where("v is not null")
    v = v.repartitionByRange(partitions, "v") if partitions else v.repartitionByRange("v")
    # equal values may swap ranks without changing the sum, so parts need only be in order
    v = v.withColumn("part", F.spark_partition_id())
    inside = v.withColumn("i", F.row_number().over(Window.partitionBy("part").orderBy("v")))
    sums = inside.groupBy("part").agg(F.count("*").alias("n"), F.sum("v").alias("s"), F.sum(F.col("i") * F.col("v")).alias("w"), F.max("v").alias("top"))
    # one row per partition
    before = Window.orderBy("top", "part").rowsBetween(Window.unboundedPreceding, -1)
    ranked = sums.withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0)))
    out = ranked.agg(F.sum("n").alias("n"), F.sum("s").alias("s"), F.sum(F.col("w") + F.col("before") * F.col("s")).alias("w"))
    return out.select(F.when(F.col("s") > 0, (2 * F.col("w") - (F.col("n") + 1) * F.col("s")) / (F.col("n") * F.col("s"))).alias("gini"))


def gini_approximate(values: DataFrame, column: str, points: int = 1000) -> DataFrame:
    """From a grid of quantiles by trapezoids; the error is at most about 1 / points."""
    grid = F.percentile_approx(column, F.array(*(F.lit(i / points) for i in range(points + 1))), 20 * points)
    q = values.agg(grid.alias("q")).select("q", F.aggregate("q", F.lit(0.0), lambda s, v: s + v).alias("s"))
    weighted = F.aggregate(F.transform("q", lambda v, i: v * (2 * i - points)), F.lit(0.0), lambda s, v: s + v)
    return q.select(F.when(F.col("s") > 0, weighted / ((points + 1) * F.col("s"))).alias("gini"))


def long_factor(f: DataFrame, k: int) -> DataFrame:
    """(key, component, value)."""
    return f.select("key", F.posexplode(F.array(*cols(k))).alias("component", "value"))


def zero_share(f: DataFrame, k: int, tolerance: float = 0.0) -> DataFrame:
    v = long_factor(f, k)
    return v.agg(F.avg(F.when(F.abs("value") <= tolerance, 1.0).otherwise(0.0)).alias("zero_share"), F.sum(F.col("value") * F.col("value")).alias("smoothness"))


#: Rows that every row's distance is taken to.
ANCHORS = 8


def squared_distance(k: int, a: str = "a", b: str = "b") -> Column:
    return total((F.col(f"{a}f{j}") - F.col(f"{b}f{j}")) * (F.col(f"{a}f{j}") - F.col(f"{b}f{j}")) for j in range(k))


def distance_distortion(x: DataFrame, sketch: DataFrame, s: int, anchors: int = ANCHORS) -> DataFrame:
    """Ratios of the distances of every row to the ``anchors`` rows with the least keys, after and before projection. The
    anchors' cells are broadcast, so that rows meet them where they are."""
    keys = F.broadcast(x.select(F.col("row_key").alias("r0")).distinct().orderBy("r0").limit(anchors))
    norms = x.groupBy("row_key").agg(F.sum(F.col("value") * F.col("value")).alias("xx"))
    few = x.join(keys, F.col("row_key") == F.col("r0")).select("r0", "col_key", F.col("value").alias("v0"))
    dots = x.select(F.col("row_key").alias("r1"), "col_key", F.col("value").alias("v1")).join(F.broadcast(few), "col_key").where("r0 <> r1").groupBy("r0", "r1").agg(F.sum(F.col("v0") * F.col("v1")).alias("dot"))
    n0 = norms.join(keys, F.col("row_key") == F.col("r0")).select("r0", F.col("xx").alias("x0"))
    n1 = norms.select(F.col("row_key").alias("r1"), F.col("xx").alias("x1"))
    pairs = n1.join(F.broadcast(n0), F.col("r0") != F.col("r1")).join(dots, ["r0", "r1"], "left").withColumn("before", F.col("x0") + F.col("x1") - 2 * F.coalesce("dot", F.lit(0.0)))
    l, r = (sketch.select(F.col("key").alias(f"r{i}"), *(F.col(c).alias(f"{p}{c}") for c in cols(s))) for i, p in ((0, "a"), (1, "b")))
    return pairs.join(l, "r0").join(r, "r1").where("before > 0").select("r0", "r1", F.sqrt(squared_distance(s) / F.col("before")).alias("ratio"))


def spectrum_decay(sigma: np.ndarray) -> dict[str, float]:
    """Decay of singular values: exponential, sigma ~ exp(-p j), and power, sigma ~ j^-p, by least squares."""
    s = np.asarray(sigma, float)
    s = s[s > s[0] * 1e-12] if len(s) else s
    j = np.arange(1, len(s) + 1)
    fit = lambda t: float(-np.polyfit(t, np.log(s), 1)[0]) if len(s) > 1 else 0.0
    return {"exponential": fit(j), "power": fit(np.log(j))}


def sharpened(sigma: np.ndarray, w: int) -> np.ndarray:
    return np.asarray(sigma, float) ** (2 * w + 1)


#: Published pairs of a decay a component and the power with the least error.
ADVICE = ((0.0053, 3), (0.0012, 11))


def advised_power(p: float) -> int:
    """More power rounds for flatter spectra, linear in the reciprocal of the decay: 3 at a decay of 0.0053 a component
    and 11 at 0.0012; 1 to 15."""
    (p0, w0), (p1, w1) = ADVICE
    slope = (w1 - w0) / (1 / p1 - 1 / p0)
    return int(np.clip(round(w0 + slope * (1 / max(p, 1e-6) - 1 / p0)), 1, 15))
