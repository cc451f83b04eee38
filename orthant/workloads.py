"""The experiments: method comparisons, grids of k and w, penalty grids, costs, spectra; medians over starts.

Data are compressed once per (s, w, seed) and solved many times. The matrix of a workload, whose size is checked, is a
table of dense blocks; Spark deals a copy to every task that makes runs, so the driver never holds it.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .operators import dense
from .operators.costs import bytes_reduced, flops, memory_floats
from .operators.kernels import COMPRESSED, Penalty
from .operators.projection import block, chunks, packed_index
from .operators.solvers import held
from .sources.matrices import MATRICES

#: Cells of a dense matrix that a task may hold.
MOST_CELLS = 50_000_000
#: Cells of a block.
BLOCK_CELLS = 1 << 16
RUNS = "run_id string, method string, k int, s int, w int, alpha double, beta double, seed bigint, iter int, metric string, value double"
_RUN_TYPES = (pa.string(), pa.string(), pa.int32(), pa.int32(), pa.int32(), pa.float64(), pa.float64(), pa.int64(), pa.int32(), pa.string(), pa.float64())
SIX = ("mu", "cmu", "hals", "chals", "gram_hals", "cgram_hals")
PENALTIES = (0.0, 0.001, 0.01, 0.1, 1.0, 10.0)


@dataclass(frozen=True)
class Matrix:
    """Blocks of dense rows (first: the least row key, data), which follow each other by ``first``. ``unit``: tasks divide
    the matrix by its largest value."""

    blocks: DataFrame
    shape: tuple[int, int]
    unit: bool = False


def matrix_of(coo: DataFrame, unit: bool = False) -> Matrix:
    """The matrix of a bounded workload, rows and columns in the order of their keys; rows without cells have no place."""
    cells = held(coo)
    packed, keys = packed_index(cells)
    shape = cells.select("row_key").distinct().count(), len(keys)
    if shape[0] * shape[1] > MOST_CELLS:
        raise ValueError("the matrix is too large for repeated runs; use solvers.factorize")

    def lay_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in chunks(batches, shape[1], BLOCK_CELLS):
            first = batch.column("row_key").slice(0, 1)
            yield pa.RecordBatch.from_arrays([first, pa.array([block(batch, shape[1]).tobytes()], pa.binary())], ["first", "data"])

    return Matrix(held(packed.repartitionByRange("row_key").sortWithinPartitions("row_key").mapInArrow(lay_out, "first bigint, data binary")), shape, unit)


def _array_blocks(spark: SparkSession, x: np.ndarray) -> Matrix:
    step = max(1, BLOCK_CELLS // max(x.shape[1], 1))
    return Matrix(spark.createDataFrame([(at, x[at : at + step].astype(float).tobytes()) for at in range(0, len(x), step)], "first bigint, data binary"), x.shape)


def run_grid(spark: SparkSession, x: Matrix | np.ndarray, grid: list[dict], iterations: int, every: int) -> DataFrame:
    """One row per run, checked iteration and measure (objective, relative_error, gini, zero_share, seconds)."""
    matrix = x if isinstance(x, Matrix) else _array_blocks(spark, x)
    shape, unit, names = matrix.shape, matrix.unit, [c.split()[0] for c in RUNS.split(", ")]
    runs = [(str(i), g["method"], g["k"], g["s"], g["w"], float(g.get("alpha", 0)), float(g.get("beta", 0)), g["seed"]) for i, g in enumerate(grid)]
    tasks = max(1, min(len(runs), 2 * spark.sparkContext.defaultParallelism))
    problem_of = lambda g: (g[3], g[4], g[7]) if g[1] in COMPRESSED else ()
    # runs of one problem stand together, so that a task holds one projection at a time
    dealt = [sorted(runs[i::tasks], key=problem_of) for i in range(tasks)]

    def one(data: np.ndarray, problem: dense.Problem, g: tuple) -> list[tuple]:
        _, method, k, _, _, alpha, beta, seed = g
        a, b = dense.start(*data.shape, k, float(data.mean()), seed)
        out, norm, spent = [], np.linalg.norm(data), 0.0
        for i in range(1, iterations + 1):
            t = time.perf_counter()
            a, b = dense.iterate(problem, method, a, b, Penalty(alpha, beta))
            spent += time.perf_counter() - t
            if i % every == 0 or i == iterations:
                e = dense.objective(data, a, b)
                out += [(*g, i, "objective", e), (*g, i, "relative_error", float(np.sqrt(2 * e) / norm))]
        return [*out, (*g, iterations, "gini", dense.gini(b)), (*g, iterations, "zero_share", float((b == 0).mean())), (*g, iterations, "seconds", spent / iterations)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        data, at, task = np.empty(shape), 0, None
        for batch in batches:
            for i in range(batch.num_rows):
                part = np.frombuffer(batch.column("data")[i].as_buffer()).reshape(-1, shape[1])
                data[at : at + len(part)] = part
                at += len(part)
                task = batch.column("task")[i].as_py()
        if task is None:
            return
        if unit:
            data /= max(data.max(), 1e-300)
        key, problem = None, None
        for g in dealt[task]:
            if problem_of(g) != key:
                key, problem = problem_of(g), None
                problem = dense.compress(data, g[3], g[4], g[7]) if key else dense.Problem(data, data)
            columns = zip(*one(data, problem, g), strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, _RUN_TYPES, strict=True)], names)

    copies = matrix.blocks.crossJoin(F.broadcast(spark.range(tasks).select(F.col("id").cast("int").alias("task"))))
    return copies.repartitionById(tasks, F.col("task")).sortWithinPartitions("first").mapInArrow(run, RUNS)


def medians(runs: DataFrame) -> DataFrame:
    return runs.groupBy("method", "k", "s", "w", "alpha", "beta", "iter", "metric").agg(F.median("value").alias("value"), F.count("*").alias("starts"), (F.max("value") - F.min("value")).alias("spread"))


def data_of(spark: SparkSession, sf_dir: str, name: str, unit: bool = False) -> Matrix:
    return matrix_of(MATRICES[name](spark, sf_dir), unit)


def width_for(k: int, ratio: float, x: Matrix | np.ndarray) -> int:
    return int(min(np.ceil(ratio * k), *x.shape))


def compare_methods(spark: SparkSession, sf_dir: str, name: str, k: int, s: int, w: int, iterations: int, seeds: int = 3, methods: tuple[str, ...] = SIX) -> DataFrame:
    """Error curves and seconds per update of the methods, medians over starts."""
    x = data_of(spark, sf_dir, name)
    k, s = min(k, min(x.shape) - 2), min(s, min(x.shape))
    grid = [{"method": m, "k": k, "s": s, "w": w, "seed": seed} for m in methods for seed in range(seeds)]
    return medians(run_grid(spark, x, grid, iterations, max(1, iterations // 5)))


def kw_sweep(spark: SparkSession, sf_dir: str, name: str, ks: tuple[int, ...], ws: tuple[int, ...], ratio: float, iterations: int, seeds: int = 3) -> DataFrame:
    x = data_of(spark, sf_dir, name)
    ks = tuple(k for k in ks if k < min(x.shape) - 2)
    grid = [{"method": "cgram_hals", "k": k, "s": width_for(k, ratio, x), "w": w, "seed": seed} for k in ks for w in ws for seed in range(seeds)]
    grid += [{"method": "gram_hals", "k": k, "s": width_for(k, ratio, x), "w": 0, "seed": seed} for k in ks for seed in range(seeds)]
    return medians(run_grid(spark, x, grid, iterations, iterations)).where("metric in ('objective', 'relative_error')")


def penalty_grid(spark: SparkSession, sf_dir: str, name: str, which: str, k: int, s: int, w: int, iterations: int, unit: bool, seeds: int = 3) -> DataFrame:
    """Gini of B and the error beside it, by alpha or beta."""
    x = data_of(spark, sf_dir, name, unit)
    k, s = min(k, min(x.shape) - 2), min(s, min(x.shape))
    grid = [{"method": m, "k": k, "s": s, "w": w, "seed": seed, which: v} for m in ("gram_hals", "cgram_hals") for v in PENALTIES for seed in range(seeds)]
    return medians(run_grid(spark, x, grid, iterations, iterations)).where("metric in ('gini', 'zero_share', 'relative_error')")


def deviation_from_best(curves: DataFrame) -> DataFrame:
    """method, value, percent: each method's last median objective, and by how many percent it is above the best method's."""
    last = curves.where("metric = 'objective'").groupBy("method").agg(F.max_by("value", "iter").alias("value"))
    best = last.agg(F.min("value").alias("best"))  # one row
    return last.crossJoin(best).select("method", "value", ((F.col("value") / F.col("best") - 1) * 100).alias("percent"))


def cost_table(spark: SparkSession, sf_dir: str, name: str, k: int, s: int, w: int, iterations: int = 10, seeds: int = 3) -> DataFrame:
    """Model operations and memory beside measured seconds (medians over starts), a row per method."""
    x = data_of(spark, sf_dir, name)
    d, n = x.shape
    k, s = min(k, min(x.shape) - 2), min(s, min(x.shape))
    seconds = run_grid(spark, x, [{"method": m, "k": k, "s": s, "w": w, "seed": seed} for m in SIX for seed in range(seeds)], iterations, iterations).where("metric = 'seconds'")
    model = spark.createDataFrame([(m, flops(m, d, n, k, s), flops(m, d, n, k, s, "counted"), memory_floats(m, d, n, k, s), bytes_reduced(m, n, k, s, 8)) for m in SIX], "method string, flops double, counted double, floats double, bytes_reduced double")
    return model.join(seconds.groupBy("method").pivot("metric", ["seconds"]).agg(F.median("value")), "method")


def convergence(runs: DataFrame) -> DataFrame:
    """Per run: slope of the log error, last over best error, whether the curve ever rises."""
    w = Window.partitionBy("run_id").orderBy("iter")
    curve = runs.where("metric = 'objective'").withColumn("before", F.lag("value").over(w))
    return curve.groupBy("run_id", "method").agg(F.regr_slope(F.log("value"), F.col("iter")).alias("rate"), (F.max_by("value", "iter") / F.min("value")).alias("last_over_best"), F.bool_and(F.coalesce(F.col("value") <= F.col("before") * (1 + 1e-12), F.lit(True))).alias("monotone"))
