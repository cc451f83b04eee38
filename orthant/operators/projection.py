"""Structured random projections of both sides, distributed.

Data are packed rows (row_key, idx, val). A power round reads the data once: each partition turns its rows
into t = x M and adds up x' t, so that the n x s block is the only thing that travels. All column-sized
blocks live on the driver and are broadcast; ``DRIVER_BYTES`` bounds them. If X' X itself fits that bound
(few columns), one scan makes it and the powers run on the driver.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import np_normal
from ..plans.matrix_plan import DRIVER_BYTES, choose_route



def block(batch: pa.RecordBatch, width: int) -> np.ndarray:
    """A batch of packed rows as a dense block (rows x width)."""
    idx, val = batch.column("idx"), batch.column("val")
    lengths = np.diff(idx.offsets.to_numpy())
    out = np.zeros((batch.num_rows, width))
    np.add.at(out, (np.repeat(np.arange(batch.num_rows), lengths), idx.flatten().to_numpy(zero_copy_only=False)), val.flatten().to_numpy(zero_copy_only=False))
    return out


def chunks(batches: Iterator[pa.RecordBatch], width: int, most: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """Slices whose dense block has at most ``most`` cells, or one row."""
    step = max(1, most // max(width, 1))
    for batch in batches:
        for at in range(0, batch.num_rows, step):
            yield batch.slice(at, step)


#: Bytes that one job may bring to the driver; numbers of a slice of larger arrays.
COLLECT_BYTES, SLICE_NUMBERS = 64 << 20, 1 << 17
#: Share of filled cells from which a dense product is less work than gathers.
DENSE_SHARE = 0.1


class Cells:
    """Packed rows as a matrix (rows x width). Rows filled to ``DENSE_SHARE`` are laid out dense; from others products
    gather the rows of their other side, so work and memory go with the stored cells."""

    def __init__(self, batch: pa.RecordBatch, width: int) -> None:
        idx, val = batch.column("idx"), batch.column("val")
        self.batch, self.shape = batch, (batch.num_rows, width)
        self.row = np.repeat(np.arange(batch.num_rows), np.diff(idx.offsets.to_numpy()))
        self.idx, self.val = idx.flatten().to_numpy(zero_copy_only=False), val.flatten().to_numpy(zero_copy_only=False)
        self.dense = block(batch, width) if len(self.val) >= DENSE_SHARE * batch.num_rows * width else None

    def full(self) -> np.ndarray:
        return block(self.batch, self.shape[1]) if self.dense is None else self.dense

    def __matmul__(self, m: np.ndarray) -> np.ndarray:
        if self.dense is not None:
            return self.dense @ m
        out = np.zeros((self.shape[0], m.shape[1]))
        _add_runs(out, self.row, m[self.idx] * self.val[:, None])
        return out

    def add_turned(self, g: np.ndarray, out: np.ndarray) -> None:
        """Adds x' g to ``out``."""
        if self.dense is not None:
            out += self.dense.T @ g
            return
        order = np.argsort(self.idx, kind="stable")
        _add_runs(out, self.idx[order], g[self.row[order]] * self.val[order, None])

    def add_gram(self, out: np.ndarray) -> None:
        """Adds x' x to ``out``, by the columns that have cells."""
        if self.dense is not None:
            out += self.dense.T @ self.dense
            return
        places, at = np.unique(self.idx, return_inverse=True)
        step = max(1, (1 << 20) // max(len(places), 1))
        for a in range(0, self.shape[0], step):
            lo, hi = np.searchsorted(self.row, (a, a + step))
            x = np.zeros((min(step, self.shape[0] - a), len(places)))
            np.add.at(x, (self.row[lo:hi] - a, at[lo:hi]), self.val[lo:hi])
            out[np.ix_(places, places)] += x.T @ x


def _add_runs(out: np.ndarray, place: np.ndarray, values: np.ndarray) -> None:
    """Adds rows of ``values`` to the rows ``place`` (ascending) of ``out``."""
    if len(place):
        first = np.flatnonzero(np.append(True, place[1:] != place[:-1]))
        out[place[first]] += np.add.reduceat(values, first, axis=0)


def cell_chunks(batches: Iterator[pa.RecordBatch], width: int, most: int = 1 << 16) -> Iterator[Cells]:
    """Slices of at most ``most`` stored cells and ``most`` / 16 rows, or one row."""
    for batch in batches:
        ends = batch.column("idx").offsets.to_numpy()
        at = 0
        while at < batch.num_rows:
            to = int(np.searchsorted(ends, ends[at] + most, side="right")) - 1
            to = min(max(to, at + 1), at + most // 16, batch.num_rows)
            yield Cells(batch.slice(at, to - at), width)
            at = to


def sum_arrays(parts: DataFrame, shape: tuple[int, ...], fan: int = 64) -> np.ndarray:
    """Sums binary double arrays of column ``part``, one per partition, in two levels; the result goes to the driver. Large
    arrays are cut into slices that tasks sum, as partitions that the driver reads in turn would also be made in turn."""
    size, each = int(np.prod(shape)), SLICE_NUMBERS

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = np.zeros(int(np.prod(shape)))
        for batch in batches:
            for raw in batch.column("part").to_pylist():
                out += np.frombuffer(raw)
        yield pa.RecordBatch.from_arrays([pa.array([out.tobytes()], pa.binary())], ["part"])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in add(batches):
            raw = batch.column("part")[0].as_buffer()
            for i, a in enumerate(range(0, size, each)):
                yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([raw.slice(8 * a, 8 * min(each, size - a)).to_pybytes()], pa.binary())], ["slice", "part"])

    def add_slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for j, i in enumerate(batch.column("slice").to_pylist()):
                sums[i] = sums.get(i, 0) + np.frombuffer(batch.column("part")[j].as_buffer())
        for i, x in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([x.tobytes()], pa.binary())], ["slice", "part"])

    n = parts.rdd.getNumPartitions()
    if n > 1 and 8 * n * size > COLLECT_BYTES:
        tasks = min(-(-size // each), parts.sparkSession.sparkContext.defaultParallelism)
        out = np.zeros(size)
        for row in parts.mapInArrow(cut, "slice int, part binary").repartition(tasks, "slice").mapInArrow(add_slices, "slice int, part binary").toLocalIterator():
            out[row["slice"] * each : (row["slice"] + 1) * each] = np.frombuffer(bytes(row["part"]))
        return out.reshape(shape)
    if n > fan:
        parts = parts.repartition(max(1, int(n**0.5))).mapInArrow(add, "part binary")
        n = int(n**0.5)
    total = np.zeros(int(np.prod(shape)))
    for row in parts.collect():
        total += np.frombuffer(bytes(row["part"]))
    return total.reshape(shape)


def partial(frame: DataFrame, add, shape: tuple[int, ...], width: int) -> np.ndarray:
    """The sum over all packed rows of what ``add(cells, out)`` adds to ``out``, an array of ``shape``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = np.zeros(shape)
        for x in cell_chunks(batches, width):
            add(x, out)
        yield pa.RecordBatch.from_arrays([pa.array([out.tobytes()], pa.binary())], ["part"])

    # large sums are one per task that runs at a time, not one per partition, as all of them travel
    tasks = frame.sparkSession.sparkContext.defaultParallelism
    if 8 * int(np.prod(shape)) * tasks > COLLECT_BYTES:
        frame = frame.coalesce(tasks)
    return sum_arrays(frame.mapInArrow(run, "part binary"), shape)


@dataclass
class ProjectedMatrix:
    """``rows``: (key, x: X R', q: L, f: A) per datapoint, a table; column side on the driver: ``left`` = L' X
    (s x n), ``r`` (s x n). X is not needed any more."""

    rows: DataFrame
    left: np.ndarray
    r: np.ndarray
    norm2: float
    mean: float
    d: int

    @property
    def n(self) -> int:
        return self.left.shape[1]

    @property
    def s(self) -> int:
        return self.left.shape[0]


def packed_index(coo: DataFrame) -> tuple[DataFrame, np.ndarray]:
    """(packed rows with column places in idx, the column keys in order). The column keys are held on the driver."""
    distinct = coo.select("col_key").distinct().persist()
    count = distinct.count()
    if count * 8 > DRIVER_BYTES:
        raise ValueError("too many columns for this route")
    keys = np.sort(np.fromiter((r["col_key"] for r in (distinct.collect() if count * 64 <= COLLECT_BYTES else distinct.toLocalIterator())), np.int64))
    distinct.unpersist()
    places = coo.sparkSession.createDataFrame([(int(k), i) for i, k in enumerate(keys)], "col_key bigint, place int")
    cells = coo.join(F.broadcast(places) if len(keys) <= 1_000_000 else places, "col_key")
    packed = cells.groupBy("row_key").agg(F.array_sort(F.collect_list(F.struct("place", "value"))).alias("c")).select("row_key", F.col("c.place").alias("idx"), F.col("c.value").alias("val"))
    return packed, keys


def orth(y: np.ndarray) -> np.ndarray:
    """Orthonormal factor with positive diagonal; directions below the rank are dropped."""
    q, r = np.linalg.qr(y)
    d = np.diag(r)
    keep = np.abs(d) > 1e-12 * max(np.abs(d).max(initial=0), 1e-300)
    return (q * np.where(d < 0, -1.0, 1.0))[:, keep]


def compress(packed: DataFrame, keys: np.ndarray, s: int, w: int, seed: int, route: str | None = None, hold=None) -> ProjectedMatrix:
    """Both projections. ``route``: "gram" (two scans, powers of X' X on the driver), "iterate" (w + 3 scans,
    orthonormalised between powers), or None to let the planner choose. ``hold(rows, count)`` makes a table of the state."""
    n = len(keys)
    s = min(s, n)
    route = route or choose_route(n, s, w)
    spark = packed.sparkSession
    omega = np_normal(keys[:, None], np.arange(s)[None, :], seed)

    def scan(m: np.ndarray) -> np.ndarray:
        spread = spark.sparkContext.broadcast(m)

        return partial(packed, lambda x, out: x.add_turned(x @ spread.value, out), m.shape, n)

    def first(x: Cells, out: np.ndarray) -> None:
        g = np_normal(x.batch.column("row_key").to_numpy()[:, None], np.arange(s)[None, :], seed + 1)
        x.add_turned(g, out[: n * s].reshape(n, s))
        out[n * s : n * s + 3] += [(x.val * x.val).sum(), x.val.sum(), x.shape[0]]
        if route == "gram":
            x.add_gram(out[n * s + 3 :].reshape(n, n))

    got = partial(packed, first, (n * s + 3 + (n * n if route == "gram" else 0),), n)
    z, (norm2, mass, d) = got[: n * s].reshape(n, s), got[n * s : n * s + 3]
    c = got[n * s + 3 :].reshape(n, n) if route == "gram" else None
    power = (lambda m: c @ m) if c is not None else scan
    m, v = omega, orth(z)
    for _ in range(w):
        m, v = power(orth(m)) if c is None else c @ orth(m), orth(power(v))
    m = orth(m)  # spans the same as before the last product; Y = X m
    r = v.T
    yy = m.T @ (c @ m if c is not None else scan(m))  # Y' Y
    values, vectors = np.linalg.eigh((yy + yy.T) / 2)
    keep = values > values[-1] * 1e-13
    turn = (vectors[:, keep] / np.sqrt(values[keep]))[:, ::-1]
    lift = m @ turn  # L = X lift has orthonormal columns
    left = (lift.T @ c) if c is not None else scan(lift).T
    spread = spark.sparkContext.broadcast((lift, r.T))

    def state(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, b = spread.value
        for x in cell_chunks(batches, n):
            arrays = [pa.array((x @ y).tolist(), pa.list_(pa.float64())) for y in (b, a)]
            yield pa.RecordBatch.from_arrays([x.batch.column("row_key"), *arrays], ["key", "x", "q"])

    rows = packed.mapInArrow(state, "key bigint, x array<double>, q array<double>")
    return ProjectedMatrix(hold(rows, int(d)) if hold else rows, left, r, float(norm2), float(mass / max(d * n, 1)), int(d))


def tall_qr(frame: DataFrame, column: str, s: int) -> tuple[DataFrame, np.ndarray]:
    """(rows with orthonormal arrays in ``column``, R) of a tall table: QR per partition, QR of the stacked
    triangles on the driver, one row-local pass. R has a positive diagonal."""

    def triangles(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        r = np.zeros((0, s))
        for batch in chunks(batches, s):
            y = batch.column(column).flatten().to_numpy(zero_copy_only=False).reshape(-1, s)
            r = np.linalg.qr(np.concatenate([r, y]), mode="r")
        if len(r):
            yield pa.RecordBatch.from_arrays([pa.array(r.tolist(), pa.list_(pa.float64()))], ["r"])

    stacked = np.array([row["r"] for row in frame.select(column).mapInArrow(triangles, "r array<double>").toLocalIterator()])
    r = np.linalg.qr(stacked, mode="r")
    r = r * np.where(np.diag(r) < 0, -1.0, 1.0)[:, None]
    inverse = np.linalg.inv(r)
    others = [c for c in frame.columns if c != column]
    solved = F.array(*(F.aggregate(F.zip_with(column, F.array(*(F.lit(float(v)) for v in inverse[:, j])), lambda x, y: x * y), F.lit(0.0), lambda p, q: p + q) for j in range(s)))
    return frame.select(*others, solved.alias(column)), r


#: Bytes of blocks of columns that the search for singular values keeps on the driver, about.
BASIS_BYTES = 256 << 20
#: Residual of a squared singular value, as a share of it, at which the search ends, and the passes it may take.
RESIDUAL, MOST_PASSES = 1e-3, 300


def singular_values(packed: DataFrame, n: int, m: int, seed: int = 3) -> np.ndarray:
    """The ``m`` largest singular values: from X' X if a partition's part of it is small enough to travel, else by block
    Krylov rounds, a pass over X for every block, until each square is within ``RESIDUAL`` of itself of a true one."""
    if 8 * n * n <= COLLECT_BYTES:
        c = partial(packed, lambda x, out: x.add_gram(out), (n, n), n)
        return np.sqrt(np.maximum(np.linalg.eigvalsh(c)[::-1][:m], 0))
    size = min(n, m + 10)
    most = int(np.clip(BASIS_BYTES // (16 * n * size), 2, 8))
    v, z = np.zeros((n, 0)), np.zeros((n, 0))
    fresh = orth(np_normal(np.arange(n)[:, None], np.arange(size)[None, :], seed))
    for _ in range(MOST_PASSES):
        spread = packed.sparkSession.sparkContext.broadcast(fresh)
        moved = partial(packed, lambda x, out, u=spread: x.add_turned(x @ u.value, out), fresh.shape, n)
        spread.destroy()
        v, z = np.concatenate([v, fresh], 1), np.concatenate([z, moved], 1)
        small = v.T @ z
        values, turn = np.linalg.eigh((small + small.T) / 2)
        values, turn = values[::-1][:size], turn[:, ::-1][:, :size]
        rest = z @ turn - (v @ turn) * values
        if (np.linalg.norm(rest[:, :m], axis=0) <= np.maximum(RESIDUAL * values[:m], 1e-12 * values[0])).all():
            break
        if v.shape[1] + size > most * size:
            v, z = v @ turn, z @ turn
        for _ in range(2):
            rest -= v @ (v.T @ rest)
        fresh = orth(rest)
        fresh -= v @ (v.T @ fresh)
        fresh = orth(fresh)
        if not fresh.shape[1]:
            break
    else:
        raise ValueError(f"singular values did not settle in {MOST_PASSES} passes")
    return np.sqrt(np.maximum(values[:m], 0))
