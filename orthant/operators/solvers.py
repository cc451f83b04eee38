"""Distributed factorization: row state in a table, small matrices on the driver.

Per iteration the compressed Gram solver makes one pass over the rows: each partition forms its targets
from the broadcast s x k block, sweeps its rows, and adds up L' A and the components' norms. s k + k
doubles per partition come back. The column side (n rows) is on the driver with the projections of the
columns, as is every block of its size; above a limit it is in tables (``grid``). The data rows are written once, in buckets of their keys; every pass writes
the factor's rows alone, in the same buckets, and their join needs no exchange. Lineage so stays bounded, and a lost
executor costs one pass at most.
"""

from __future__ import annotations

import contextlib
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import np_uniform
from ..plans.matrix_plan import choose_column_side, choose_placement
from . import dense
from .kernels import COMPRESSED, KERNELS, NONE, Penalty, residual_component
from .projection import Cells, ProjectedMatrix, cell_chunks, chunks, compress, packed_index, partial, sum_arrays


def shared_folder(spark) -> str:
    path = spark.conf.get("spark.checkpoint.dir", None)
    if not path:
        path = getattr(spark.sparkContext, "_factor_folder", None) or tempfile.mkdtemp(prefix="factors-")
        spark.sparkContext._factor_folder = path
    return path.rstrip("/")


def _place(spark, path: str):
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target, target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


CLEANUP_SETTING = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextlib.contextmanager
def freed_shuffles(spark) -> Iterator[None]:
    """Shuffle files of what runs inside go as soon as its result is there, not when the driver next collects its garbage."""
    before = spark.conf.get(CLEANUP_SETTING)
    spark.conf.set(CLEANUP_SETTING, "true")
    try:
        yield
    finally:
        spark.conf.set(CLEANUP_SETTING, before)


def held(frame: DataFrame) -> DataFrame:
    """Writes a state table into the shared folder and reads it back."""
    path = f"{shared_folder(frame.sparkSession)}/state-{uuid.uuid4().hex}"
    with freed_shuffles(frame.sparkSession):
        frame.write.parquet(path)
    target, files = _place(frame.sparkSession, path)
    files.deleteOnExit(target)
    out = frame.sparkSession.read.schema(frame.schema).parquet(path)
    out._state_path = path
    return out


def discard(table: DataFrame) -> None:
    """Deletes the files of a state table that nothing reads any more."""
    target, files = _place(table.sparkSession, table._state_path)
    files.delete(target, True)


#: Bytes of a factor's rows in a bucket, about: a pass holds a bucket's in memory.
BUCKET_BYTES = 64 << 20


def bucketed(frame: DataFrame, buckets: int, deal: bool = False) -> DataFrame:
    """Writes a table into the shared folder in buckets of ``key`` and reads it back. ``deal`` rows of anywhere first, so
    that a bucket is one file; rows of a pass already stand in their buckets."""
    spark, name = frame.sparkSession, f"state_{uuid.uuid4().hex}"
    path = f"{shared_folder(spark)}/{name.replace('_', '-')}"
    target, files = _place(spark, path)
    files.deleteOnExit(target)
    rows = frame.repartition(buckets, "key") if deal else frame
    with freed_shuffles(spark):
        rows.write.bucketBy(buckets, "key").option("path", path).saveAsTable(name)
    out = spark.table(name)
    spark.sql(f"DROP TABLE {name}")  # the entry alone: an external table's files stay
    out._state_path, out._buckets = path, buckets
    return out


def bucket_count(spark, rows: int, k: int) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")), -(-rows * k * 8 // BUCKET_BYTES))


class States:
    """Rows of one solve: the fixed ones, bucketed once, and the factor's (key, f) of the last two passes, as the last one is
    made from the one before."""

    def __init__(self, fixed: DataFrame, start: Callable[[DataFrame], DataFrame]) -> None:
        self.fixed, self.buckets = fixed, fixed._buckets
        self.start, self.paths, self.f = start, [], None

    def rows(self) -> DataFrame:
        """The fixed rows with their f; a bucket of f, whose size is bounded, is looked up."""
        return self.start(self.fixed) if self.f is None else self.fixed.join(self.f.hint("shuffle_hash"), "key")

    def advance(self, out: DataFrame, shape: tuple[int, ...]) -> np.ndarray:
        """Writes a pass's output (key, f, part), whose rows with a part are partial sums; returns their sum."""
        out = bucketed(out, self.buckets)
        self.paths.append(out._state_path)
        while len(self.paths) > 2:
            target, files = _place(out.sparkSession, self.paths.pop(0))
            files.delete(target, True)
        self.f = out.where("part is null").select("key", "f")
        return sum_arrays(out.where("part is not null").select("part"), shape)

    def divide(self, size: np.ndarray) -> None:
        self.f = _divided(self.f, size)


def _sums_row(key: int, sums: np.ndarray) -> pa.RecordBatch:
    """Partial sums, under a key of the task's own bucket."""
    return pa.RecordBatch.from_arrays([pa.array([key], pa.int64()), pa.nulls(1, pa.list_(pa.float64())), pa.array([sums.tobytes()], pa.binary())], ["key", "f", "part"])


def _divided(rows: DataFrame, size: np.ndarray) -> DataFrame:
    """The state with f's components divided by ``size``."""
    return rows.withColumn("f", F.zip_with("f", F.array(*(F.lit(float(v)) for v in size)), lambda x, y: x / y))


def _component_size(squares: float, k: int, j: int) -> np.ndarray:
    out = np.ones(k)
    out[j] = np.sqrt(squares) if squares > 0 else 1.0
    return out


def _matrix(column: pa.Array, width: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, width)


def _lists(x: np.ndarray) -> pa.Array:
    return pa.array(x.tolist(), pa.list_(pa.float64()))


def row_pass(states: States, s: int, k: int, update: Callable[[np.ndarray, np.ndarray], np.ndarray], width: int, measure: Callable[[np.ndarray, np.ndarray], list[float]] | None = None, measures: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Applies ``update(x, f) -> f`` to the rows (key, x, q, f): (L' F, sums of squares of F, sums of ``measure(x, f)``, which
    gives ``measures`` numbers). The new f and the sums come from one pass: partial sums ride as tagged rows of the same output."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        near, squares, more, key = np.zeros((s, k)), np.zeros(k), np.zeros(measures), None
        for batch in chunks(batches, width + s + k):
            x = _matrix(batch.column("x"), width)
            f = update(x, _matrix(batch.column("f"), k))
            near += _matrix(batch.column("q"), s).T @ f
            squares += (f * f).sum(0)
            if measure is not None:
                more += measure(x, f)
            key = batch.column("key")[0].as_py()
            yield pa.RecordBatch.from_arrays([batch.column("key"), _lists(f), pa.nulls(batch.num_rows, pa.binary())], ["key", "f", "part"])
        if key is not None:
            yield _sums_row(key, np.concatenate([near.ravel(), squares, more]))

    sums = states.advance(states.rows().select("key", "x", "q", "f").mapInArrow(run, FACTOR), (s * k + k + measures,))
    return sums[: s * k].reshape(s, k), sums[s * k : s * k + k], sums[s * k + k :]


FACTOR = "key bigint, f array<double>, part binary"
#: Numbers of a block of columns that the driver and each task of the uncompressed forms hold.
MOST_BLOCK = 50_000_000


def with_start(rows: DataFrame, k: int, seed: int, scale: float) -> DataFrame:
    """The rows with random f, functions of their keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            f = np_uniform(batch.column("key").to_numpy()[:, None], np.arange(k)[None, :], seed) * scale
            yield pa.RecordBatch.from_arrays([*batch.columns, _lists(f)], [*batch.schema.names, "f"])

    return rows.mapInArrow(run, ", ".join([*(f"{c} {t}" for c, t in rows.dtypes), "f array<double>"]))


def solve_projected(p: ProjectedMatrix, keys: np.ndarray, k: int, iterations: int, method: str = "cgram_hals", penalty: Penalty = NONE, seed: int = 7, normalize: str = "sweep", tolerance: float = 0.0, stop: str = "gain") -> tuple[DataFrame, np.ndarray, list[tuple[int, float]]]:
    """(A as rows (key, f), B (n x k), trace of half squared projected error of the column side). ``method``: any
    compressed kernel, or "chals" (component-major, 2 k passes an iteration)."""
    scale = 2 * np.sqrt(max(p.mean, 1e-12) / k)
    width = p.r.shape[0]
    fixed = p.rows if hasattr(p.rows, "_buckets") else bucketed(p.rows, bucket_count(p.rows.sparkSession, p.d, k), True)
    b = np_uniform(keys[:, None], np.arange(k)[None, :], seed + 1) * scale
    trace: list[tuple[int, float]] = []
    spark, states, rule = p.rows.sparkSession, States(fixed, lambda r: with_start(r, k, seed, scale)), Stop(tolerance, stop)

    def one_pass(update, component: int | None = None) -> np.ndarray:
        nonlocal b
        near, squares, _ = row_pass(states, p.s, k, update, width)
        if normalize != "none":
            size = np.where(squares > 0, np.sqrt(squares), 1.0) if component is None else _component_size(squares[component], k, component)
            states.divide(size)
            b, near = b * size, near / size
        return near

    for i in range(1, iterations + 1):
        if method == "chals":
            for j in range(k):
                near_b = spark.sparkContext.broadcast(p.r @ b)

                def update(x, f, j=j, nb=near_b):
                    f = f.copy()
                    f[:, j] = residual_component(x, f, nb.value, j)
                    return f

                near = one_pass(update, j)
                b[:, j] = residual_component(p.left.T, b, near, j, penalty)
        else:
            kernel, near_b = KERNELS[method], p.r @ b
            spread = spark.sparkContext.broadcast((near_b, near_b.T @ near_b))
            near = one_pass(lambda x, f, t=spread, kernel=kernel: kernel(x @ t.value[0], t.value[1], f))
            b = kernel(p.left.T @ near, near.T @ near, b, penalty)
        trace.append((i, 0.5 * float(((p.left - near @ b.T) ** 2).sum())))
        if rule.met(trace, lambda near=near, b=b: projected_gradient(b, near.T @ near, p.left.T @ near)):
            break
    return states.f if iterations else states.rows().select("key", "f"), b, trace


def _residual_by_rows(x: Cells, f: np.ndarray, other: np.ndarray, j: int) -> np.ndarray:
    """A residual has no empty cells: it is formed for a part of the rows at a time."""
    step = max(1, (1 << 20) // max(x.shape[1], 1))
    parts = (Cells(x.batch.slice(a, step), x.shape[1]).full() for a in range(0, x.shape[0], step))
    return np.concatenate([residual_component(part, f[i * step : (i + 1) * step], other, j) for i, part in enumerate(parts)])


def solve_raw(packed: DataFrame, keys: np.ndarray, k: int, iterations: int, method: str = "gram_hals", penalty: Penalty = NONE, seed: int = 7, normalize: str = "sweep", tolerance: float = 0.0, stop: str = "gain") -> tuple[DataFrame, np.ndarray, list[tuple[int, float]]]:
    """The uncompressed forms on packed rows. B (n x k) is on the driver, and its size is checked; every pass scans X and
    sends n x k doubles per partition. "hals" works through components: 2 k passes an iteration."""
    n = len(keys)
    if n * k > MOST_BLOCK:
        raise ValueError("the column factor is too large for one machine; use a compressed method")
    d, mass = partial(packed, lambda x, out: out.__iadd__([x.shape[0], x.val.sum()]), (2,), n)
    scale = 2 * np.sqrt(max(mass / max(d * n, 1), 1e-12) / k)
    spark = packed.sparkSession

    fixed = bucketed(packed.withColumnRenamed("row_key", "key"), bucket_count(spark, int(d), k), True)
    b = np_uniform(keys[:, None], np.arange(k)[None, :], seed + 1) * scale
    trace: list[tuple[int, float]] = []
    states, rule = States(fixed, lambda r: with_start(r, k, seed, scale)), Stop(tolerance, stop)

    def one_pass(update: Callable[[Cells, np.ndarray], np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums, key = np.zeros(n * k + k * k + 1), None
            h, g = sums[: n * k].reshape(n, k), sums[n * k : -1].reshape(k, k)
            for x in cell_chunks(batches, n):
                f = update(x, _matrix(x.batch.column("f"), k))
                x.add_turned(f, h)
                g += f.T @ f
                sums[-1] += (x.val * x.val).sum()
                key = x.batch.column("key")[0].as_py()
                yield pa.RecordBatch.from_arrays([x.batch.column("key"), _lists(f), pa.nulls(x.shape[0], pa.binary())], ["key", "f", "part"])
            if key is not None:
                yield _sums_row(key, sums)

        sums = states.advance(states.rows().select("key", "idx", "val", "f").mapInArrow(run, FACTOR), (n * k + k * k + 1,))
        return sums[: n * k].reshape(n, k), sums[n * k : -1].reshape(k, k), sums[-1]

    for i in range(1, iterations + 1):
        if method == "hals":
            for j in range(k):
                spread = spark.sparkContext.broadcast(b.copy())

                def update(x, f, j=j, t=spread):
                    f = f.copy()
                    f[:, j] = _residual_by_rows(x, f, t.value, j)
                    return f

                h, g, norm2 = one_pass(update)
                if normalize != "none":
                    size = _component_size(g[j, j], k, j)
                    states.divide(size)
                    b, h, g = b * size, h / size, g / np.outer(size, size)
                if g[j, j] > 0:
                    b[:, j] = np.maximum(h[:, j] - b @ g[:, j] + b[:, j] * g[j, j] - penalty.alpha, 0) / (g[j, j] + penalty.beta)
        else:
            kernel = KERNELS[method]
            spread = spark.sparkContext.broadcast((b.copy(), b.T @ b))
            h, g, norm2 = one_pass(lambda x, f, t=spread, kernel=kernel: kernel(x @ t.value[0], t.value[1], f))
            if normalize != "none":
                size = np.sqrt(np.where(np.diag(g) > 0, np.diag(g), 1.0))
                states.divide(size)
                b, h, g = b * size, h / size, g / np.outer(size, size)
            b = kernel(h, g, b, penalty)
        trace.append((i, 0.5 * float(norm2 - 2 * (h * b).sum() + (g * (b.T @ b)).sum())))
        if rule.met(trace, lambda b=b, g=g, h=h: projected_gradient(b, g, h)):
            break
    return states.f if iterations else states.rows().select("key", "f"), b, trace


def converged(trace: list[tuple[int, float]], tolerance: float) -> bool:
    """The last step's relative gain is at most ``tolerance``; 0 never stops."""
    return tolerance > 0 and len(trace) > 1 and abs(trace[-2][1] - trace[-1][1]) <= tolerance * max(abs(trace[-2][1]), 1e-300)


def projected_gradient(b: np.ndarray, g: np.ndarray, h: np.ndarray) -> float:
    """Norm of the gradient of half the squared error in B, without the parts that point out of the feasible set.
    ``g``: Gram matrix of the other side; ``h``: data times that side."""
    slope = b @ g - h
    return float(np.linalg.norm(np.where((b > 0) | (slope < 0), slope, 0.0)))


class Stop:
    """Stop rules: "gain", the last step's relative gain is at most ``tolerance``; "gradient", the projected gradient's
    norm is at most ``tolerance`` times that after the first iteration; "stagnation", the best objective of the last
    ``PATIENCE`` iterations is not below the best one before by more than ``tolerance`` of it. 0 never stops."""

    RULES = ("gain", "gradient", "stagnation")
    PATIENCE = 5

    def __init__(self, tolerance: float, rule: str = "gain") -> None:
        if rule not in self.RULES:
            raise ValueError(f"no such stop rule: {rule}")
        self.tolerance, self.rule, self.first = tolerance, rule, 0.0

    def met(self, trace: list[tuple[int, float]], gradient: Callable[[], float]) -> bool:
        if self.tolerance <= 0:
            return False
        if self.rule == "gain":
            return converged(trace, self.tolerance)
        if self.rule == "gradient":
            now = gradient()
            self.first = self.first or now
            return len(trace) > 1 and now <= self.tolerance * self.first
        values = [v for _, v in trace]
        return len(values) > self.PATIENCE and min(values[-self.PATIENCE :]) > (1 - self.tolerance) * min(values[: -self.PATIENCE])


def factorize(coo: DataFrame, k: int, s: int, w: int, iterations: int, method: str = "cgram_hals", penalty: Penalty = NONE, seed: int = 7, placement: str | None = None, normalize: str = "sweep", tolerance: float = 0.0, stop: str = "gain") -> tuple[DataFrame, DataFrame, list[tuple[int, float]]]:
    """(A: key, f; B: key, f; trace). ``placement``: "driver" brings the compressed state to one machine, whose size
    is checked, and iterates there; "distributed" never does; None lets the planner choose. ``normalize="component"``
    (unit length inside the sweep, k sums an iteration) is for the driver's placement. Compressed methods keep a column side
    above a counted size in tables (``grid``). ``tolerance``, ``stop``: see ``Stop``."""
    cells, spark = held(coo), coo.sparkSession
    if method in COMPRESSED and placement != "driver" and normalize != "component":
        n = cells.select("col_key").distinct().count()
        if choose_column_side(n, k, min(s, n)) == "tables":
            from . import grid

            return grid.factorize(cells, k, s, w, iterations, method, penalty, seed, normalize, tolerance, stop)
    packed, keys = packed_index(cells)
    packed = held(packed)
    discard(cells)
    if method in COMPRESSED:
        def hold(rows: DataFrame, count: int) -> DataFrame:
            if (placement or choose_placement(count, len(keys), k, min(s, len(keys)))) == "driver":
                return held(rows)
            return bucketed(rows, bucket_count(spark, count, k), True)

        p = compress(packed, keys, s, w, seed, hold=hold)
        placement = placement or choose_placement(p.d, p.n, k, p.s)
        if normalize == "component" and placement != "driver":
            raise ValueError("component normalisation needs the driver's placement")
        if placement == "driver":
            got = sorted((r["key"], r["x"], r["q"]) for r in p.rows.toLocalIterator())
            problem = dense.Problem(np.array([g[1] for g in got]), p.left, np.array([g[2] for g in got]), p.r)
            rk = np.array([g[0] for g in got], np.int64)
            scale = 2 * np.sqrt(max(p.mean, 1e-12) / k)
            a, b = np_uniform(rk[:, None], np.arange(k)[None, :], seed) * scale, np_uniform(keys[:, None], np.arange(k)[None, :], seed + 1) * scale
            trace, rule = [], Stop(tolerance, stop)
            for i in range(1, iterations + 1):
                a, b = dense.iterate(problem, method, a, b, penalty, normalize)
                near = problem.near_a(a)
                trace.append((i, 0.5 * float(((p.left - near @ b.T) ** 2).sum())))
                if rule.met(trace, lambda near=near, b=b: projected_gradient(b, near.T @ near, p.left.T @ near)):
                    break
            rows = spark.createDataFrame([(int(x), y) for x, y in zip(rk, a.tolist(), strict=True)], "key bigint, f array<double>")
        else:
            rows, b, trace = solve_projected(p, keys, k, iterations, method, penalty, seed, normalize, tolerance, stop)
    else:
        rows, b, trace = solve_raw(packed, keys, k, iterations, method, penalty, seed, normalize, tolerance, stop)
    return rows, spark.createDataFrame([(int(x), y) for x, y in zip(keys, b.tolist(), strict=True)], "key bigint, f array<double>"), trace


def fold_in(packed: DataFrame, b: np.ndarray, sweeps: int = 30, penalty: Penalty = NONE) -> DataFrame:
    """(key, f): coefficients of new rows (row_key, idx, val) for fixed B. idx are places of B's rows."""
    spread = packed.sparkSession.sparkContext.broadcast((b, b.T @ b))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fixed, g = spread.value
        for x in cell_chunks(batches, len(fixed)):
            h = x @ fixed
            f = np.zeros_like(h)
            for _ in range(sweeps):
                f = KERNELS["gram_hals"](h, g, f, penalty)
            yield pa.RecordBatch.from_arrays([x.batch.column("row_key"), _lists(f)], ["key", "f"])

    return packed.mapInArrow(run, "key bigint, f array<double>")
