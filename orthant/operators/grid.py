"""Compressed solves of matrices with very many columns: the column side is in tables, as the row side is.

Rows and columns are numbered in blocks of neighbouring keys, and X is a table of blocks of cells. A product deals one side's
blocks, in order, to the tasks that hold the other side's sums, and only where cells meet them. Bases are never
orthonormalised in place: their triangles turn what is read next. The driver gets sizes of blocks and matrices of s x s.
"""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import np_normal
from .kernels import KERNELS, NONE, Penalty, residual_component
from .projection import _add_runs, sum_arrays
from .solvers import States, Stop, _component_size, _lists, bucket_count, bucketed, discard, held, row_pass, with_start

#: Bytes of a block of numbers, and of the sums that a task holds, about.
BLOCK_BYTES, SUM_BYTES = 2 << 20, 32 << 20
#: Cells of a block of cells, about, and of a step of a product; blocks of a batch.
MOST_CELLS, STEP_CELLS, BATCH_BLOCKS = 1 << 16, 1 << 14, 4
BATCH_SETTINGS = ("spark.sql.execution.arrow.maxRecordsPerBatch", "spark.sql.parquet.columnarReaderBatchSize")
SIDES = ("rb", "cb")


@contextlib.contextmanager
def few_blocks(spark) -> Iterator[None]:
    before = {name: spark.conf.get(name) for name in BATCH_SETTINGS}
    for name in BATCH_SETTINGS:
        spark.conf.set(name, str(BATCH_BLOCKS))
    try:
        yield
    finally:
        for name, value in before.items():
            spark.conf.set(name, value)


def _release() -> None:
    """Gives memory that a reused Python worker no longer needs back to the system."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # other C libraries have no such call
        ctypes.CDLL("libc.so.6").malloc_trim(0)


@dataclass(frozen=True)
class Grid:
    """``cells``: (rb, cb, row, col, val), the cells of a pair of blocks by places in them. ``keys``, ``sizes``: by side ("rb",
    "cb"), a block's keys in order (block, data) and the number of its keys."""

    cells: DataFrame
    pairs: DataFrame
    keys: dict[str, DataFrame]
    sizes: dict[str, np.ndarray]
    norm2: float
    mean: float


def _numbered(keys: DataFrame, each: int) -> tuple[DataFrame, DataFrame, np.ndarray]:
    """((key, block, place), (block, data: the keys), sizes of the blocks): ranges of about ``each`` keys."""
    keys = held(keys)
    blocks = max(1, -(-keys.count() // each))

    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block, at = TaskContext.get().partitionId(), 0
        for batch in batches:
            n = batch.num_rows
            yield pa.RecordBatch.from_arrays([batch.column("key"), pa.array(np.full(n, block, np.int32)), pa.array(np.arange(at, at + n, dtype=np.int32))], ["key", "block", "place"])
            at += n

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block, some in zip(batch.column("block").to_pylist(), batch.column("keys"), strict=True):
                yield _block(block, some.values.to_numpy(zero_copy_only=False))

    places = held(keys.repartitionByRange(blocks, "key").sortWithinPartitions("key").mapInArrow(number, "key bigint, block int, place int"))
    lists = places.groupBy("block").agg(F.array_sort(F.collect_list("key")).alias("keys"))
    with few_blocks(keys.sparkSession):
        data = held(lists.mapInArrow(join, "block int, data binary, part binary").drop("part"))
    discard(keys)
    sizes = np.zeros(blocks, np.int64)
    for r in places.groupBy("block").count().collect():
        sizes[r["block"]] = r["count"]
    return places, data, sizes


def _block(block: int | None, data: np.ndarray | None, part: np.ndarray | None = None) -> pa.RecordBatch:
    raw = lambda x: pa.array([None if x is None else np.ascontiguousarray(x).tobytes()], pa.binary())
    return pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), raw(data), raw(part)], ["block", "data", "part"])


BLOCKS = "block int, data binary, part binary"


def grid_of(cells: DataFrame, s: int) -> Grid:
    """The grid of a table of cells, whose blocks suit products of 2 s columns."""
    each = max(1, BLOCK_BYTES // (16 * s))
    of = {side: _numbered(cells.select(F.col(key).alias("key")).distinct(), each) for side, key in zip(SIDES, ("row_key", "col_key"), strict=True)}
    placed = cells
    for side, key, place in (("rb", "row_key", "row"), ("cb", "col_key", "col")):
        placed = placed.join(of[side][0].select(F.col("key").alias(key), F.col("block").alias(side), F.col("place").alias(place)), key)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, pair, n = [], None, 0

        def packed() -> pa.RecordBatch:
            raw = [pa.array([np.concatenate([p[i] for p in parts]).tobytes()], pa.binary()) for i in range(3)]
            return pa.RecordBatch.from_arrays([pa.array([pair[0]], pa.int32()), pa.array([pair[1]], pa.int32()), *raw], ["rb", "cb", "row", "col", "val"])

        for batch in batches:
            rb, cb, *rest = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("rb", "cb", "row", "col", "val"))
            cuts = [0, *(np.flatnonzero((np.diff(rb) != 0) | (np.diff(cb) != 0)) + 1), len(rb)]
            for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                if hi == lo:
                    continue
                now = int(rb[lo]), int(cb[lo])
                if parts and (now != pair or n >= MOST_CELLS):
                    yield packed()
                    parts, n = [], 0
                pair = now
                parts.append([x[lo:hi] for x in rest])
                n += hi - lo
        if parts:
            yield packed()
        _release()

    rows = placed.select("rb", "cb", "row", "col", F.col("value").alias("val")).repartition("rb", "cb").sortWithinPartitions("rb", "cb", "row", "col")
    table = held(rows.mapInArrow(pack, "rb int, cb int, row binary, col binary, val binary"))
    sums = cells.agg(F.sum(F.col("value") * F.col("value")).alias("norm2"), F.sum("value").alias("mass")).first()
    sizes = {side: of[side][2] for side in SIDES}
    for side in SIDES:
        discard(of[side][0])
    cell_count = float(sizes["rb"].sum()) * float(sizes["cb"].sum())
    return Grid(table, held(table.select(*SIDES).distinct().coalesce(1)), {side: of[side][1] for side in SIDES}, sizes, float(sums["norm2"]), float(sums["mass"]) / max(cell_count, 1))


def _triangles(data: np.ndarray, split: int) -> list[np.ndarray]:
    return [np.linalg.qr(data[:, :split], mode="r"), np.linalg.qr(data[:, split:], mode="r")]


def _stacked(old: list[np.ndarray] | None, new: list[np.ndarray]) -> list[np.ndarray]:
    return new if old is None else [np.linalg.qr(np.concatenate([a, b]), mode="r") for a, b in zip(old, new, strict=True)]


def _sent(triangles: list[np.ndarray]) -> np.ndarray:
    """Triangles as one array of full squares."""
    return np.concatenate([np.concatenate([r, np.zeros((r.shape[1] - len(r), r.shape[1]))]).ravel() for r in triangles])


def _turns(blocks: DataFrame, widths: tuple[int, ...]) -> list[np.ndarray]:
    """What turns each of a table's column groups into an orthonormal one; directions below the rank are dropped."""
    r = None
    for row in blocks.where("part is not null").select("part").toLocalIterator():
        raw, parts, at = np.frombuffer(bytes(row["part"])), [], 0
        for width in widths:
            parts.append(raw[at : at + width * width].reshape(width, width))
            at += width * width
        r = _stacked(r, parts)
    out = []
    for triangle in r:
        d = np.abs(np.diag(triangle))
        keep = np.flatnonzero(d > 1e-12 * max(d.max(initial=0), 1e-300))
        small = np.linalg.qr(triangle[:, keep], mode="r")
        turn = np.zeros((triangle.shape[1], len(keep)))
        turn[keep] = np.linalg.inv(small * np.where(np.diag(small) < 0, -1.0, 1.0)[:, None])
        out.append(turn)
    return out


def _beside(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.block([[a, np.zeros((len(a), b.shape[1]))], [np.zeros((len(b), a.shape[1])), b]])


def product(grid: Grid, values: DataFrame, side: str, width: int, turn: np.ndarray | None = None, split: int | None = None, gram: int = 0) -> DataFrame:
    """(block, data, part) of X (or X') times the blocks ``values`` (block, data: rows of ``width``) of ``side``'s opposite,
    turned. Parts: triangles of the sums' columns before and after ``split``, or Gram matrices of the first ``gram`` columns."""
    other = SIDES[1 - SIDES.index(side)]
    spark, sizes, total = grid.cells.sparkSession, grid.sizes[side], int(grid.sizes[side].sum())
    out_width, blocks = width if turn is None else turn.shape[1], len(grid.sizes[side])
    tasks = min(blocks, max(spark.sparkContext.defaultParallelism, -(-total * out_width * 8 // SUM_BYTES)))
    task = F.floor(F.col(side).cast("bigint") * tasks / blocks).cast("int").alias("task")
    none = lambda *names: [F.lit(None).cast("int" if n == "into" else "binary").alias(n) for n in names]
    needed = grid.pairs.select(task, F.col(other).alias("block")).distinct()
    sent = values.join(F.broadcast(needed), "block").select("task", F.col("block").alias("place"), *none("into"), "data", *none("row", "col", "val"))
    cells = grid.cells.select(task, F.col(other).alias("place"), F.col(side).alias("into"), *none("data"), "row", "col", "val")
    mine, theirs = ("row", "col") if side == "rb" else ("col", "row")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, now = {}, None
        for batch in batches:
            get = lambda name, i, kind, b=batch: np.frombuffer(b.column(name)[i].as_buffer(), kind)
            for i, into in enumerate(batch.column("into").to_pylist()):
                if into is None:
                    now = get("data", i, np.float64).reshape(-1, width)
                    now = now if turn is None else now @ turn
                    continue
                place, at, val = get(mine, i, np.int32), get(theirs, i, np.int32), get("val", i, np.float64)
                if side == "cb":
                    order = np.argsort(place, kind="stable")
                    place, at, val = place[order], at[order], val[order]
                if into not in sums:
                    sums[into] = np.zeros((sizes[into], out_width))
                for a in range(0, len(val), STEP_CELLS):
                    b = a + STEP_CELLS
                    _add_runs(sums[into], place[a:b], now[at[a:b]] * val[a:b, None])
        part = None
        for into in sorted(sums):
            x = sums.pop(into)
            if split is not None:
                part = _stacked(part, _triangles(x, split))
            elif gram:
                part = (0 if part is None else part) + x[:, :gram].T @ x[:, :gram]
            yield _block(into, x)
        if part is not None:
            yield _block(None, None, _sent(part) if split is not None else part)
        _release()

    dealt = sent.unionByName(cells).repartitionById(tasks, F.col("task")).sortWithinPartitions("place", F.col("into").asc_nulls_first())
    with few_blocks(spark):
        return held(dealt.mapInArrow(run, BLOCKS))


def _of_keys(keys: DataFrame, f: Callable[[np.ndarray], np.ndarray]) -> DataFrame:
    """Blocks of numbers that are functions of keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, block in enumerate(batch.column("block").to_pylist()):
                yield _block(block, f(np.frombuffer(batch.column("data")[i].as_buffer(), np.int64)))

    return keys.mapInArrow(run, BLOCKS).drop("part")


def _turned(blocks: DataFrame, width: int, turn: np.ndarray) -> DataFrame:
    """(block, data): blocks of rows of ``width``, turned."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, block in enumerate(batch.column("block").to_pylist()):
                yield _block(block, np.frombuffer(batch.column("data")[i].as_buffer()).reshape(-1, width) @ turn)

    return blocks.where("block is not null").select("block", "data").mapInArrow(run, BLOCKS).drop("part")


def _rows(keys: DataFrame, sources: list[tuple[DataFrame, int, np.ndarray]], split: int, buckets: int) -> DataFrame:
    """(key, x, q) in buckets: the sources (blocks, width, turn) beside each other, cut at ``split``. The sources' tables are
    deleted once their turned blocks are joined, so that never more than one copy is on the disk beside the one being made."""
    joined, spark, count = keys.select("block", F.col("data").alias("keys")), keys.sparkSession, len(sources)
    for i, (blocks, width, turn) in enumerate(sources):
        joined = joined.join(_turned(blocks, width, turn).withColumnRenamed("data", f"part{i}"), "block")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                raw = lambda name, kind, i=i, b=batch: np.frombuffer(b.column(name)[i].as_buffer(), kind)
                at = raw("keys", np.int64)
                both = np.concatenate([raw(f"part{j}", np.float64).reshape(len(at), -1) for j in range(count)], 1)
                out = pa.RecordBatch.from_arrays([pa.array(at), _lists(both[:, :split]), _lists(both[:, split:])], ["key", "x", "q"])
                yield from (out.slice(a, 5000) for a in range(0, out.num_rows, 5000))

    with few_blocks(spark):
        joined = held(joined)
        for blocks, _, _ in sources:
            discard(blocks)
        out = bucketed(joined.mapInArrow(run, "key bigint, x array<double>, q array<double>"), buckets, True)
    discard(joined)
    return out


@dataclass(frozen=True)
class ProjectedSides:
    """``rows``: (key, x: X R', q: L); ``cols``: (key, x: X' L, q: R'), both in buckets. ``ranks``: columns of R' and of L."""

    rows: DataFrame
    cols: DataFrame
    ranks: tuple[int, int]
    mean: float
    d: int
    n: int


def compress(cells: DataFrame, s: int, w: int, k: int, seed: int) -> ProjectedSides:
    """Both projections, as ``projection.compress`` makes them with its route "iterate"; both bases share the scans. The cells'
    table is deleted as soon as the grid has them."""
    grid, spark = grid_of(cells, s), cells.sparkSession
    discard(cells)
    d, n = (int(grid.sizes[side].sum()) for side in SIDES)
    normal = lambda side, salt: _of_keys(grid.keys[side], lambda keys: np_normal(keys[:, None], np.arange(s)[None, :], salt))
    z = product(grid, normal("rb", seed + 1), "cb", s)

    def start(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = None
        for batch in batches:
            for i, block in enumerate(batch.column("block").to_pylist()):
                keys = np.frombuffer(batch.column("keys")[i].as_buffer(), np.int64)
                both = np.concatenate([np_normal(keys[:, None], np.arange(s)[None, :], seed), np.frombuffer(batch.column("data")[i].as_buffer()).reshape(-1, s)], 1)
                part = _stacked(part, _triangles(both, s))
                yield _block(block, both)
        if part is not None:
            yield _block(None, None, _sent(part))

    with few_blocks(spark):
        base = held(grid.keys["cb"].withColumnRenamed("data", "keys").join(z.where("block is not null").select("block", "data"), "block").mapInArrow(start, BLOCKS))
    discard(z)
    widths = (s, s)
    for _ in range(w):
        turns = _turns(base, widths)
        moved = product(grid, base.where("block is not null").select("block", "data"), "rb", sum(widths), _beside(*turns))
        discard(base)
        widths = tuple(t.shape[1] for t in turns)
        base = product(grid, moved.select("block", "data"), "cb", sum(widths), split=widths[0])
        discard(moved)
    m, v = _turns(base, widths)
    ranks = m.shape[1], v.shape[1]
    moved = product(grid, base.where("block is not null").select("block", "data"), "rb", sum(widths), _beside(m, v), gram=ranks[0])
    yy = sum_arrays(moved.where("part is not null").select("part"), (ranks[0], ranks[0]))
    values, vectors = np.linalg.eigh((yy + yy.T) / 2)
    keep = values > values[-1] * 1e-13
    turn = (vectors[:, keep] / np.sqrt(values[keep]))[:, ::-1]
    lift = np.concatenate([turn, np.zeros((ranks[1], turn.shape[1]))])
    pick = np.concatenate([np.zeros((ranks[0], ranks[1])), np.eye(ranks[1])])
    left = product(grid, moved.where("block is not null").select("block", "data"), "cb", sum(ranks), lift)
    discard(grid.cells)
    discard(grid.pairs)
    rows = _rows(grid.keys["rb"], [(moved, sum(ranks), np.concatenate([pick, lift], 1))], ranks[1], bucket_count(spark, d, k))
    cols = _rows(grid.keys["cb"], [(left, lift.shape[1], np.eye(lift.shape[1])), (base, sum(widths), np.concatenate([np.zeros((widths[0], ranks[1])), v]))], lift.shape[1], bucket_count(spark, n, k))
    for table in grid.keys.values():
        discard(table)
    return ProjectedSides(rows, cols, (ranks[1], lift.shape[1]), grid.mean, d, n)


def solve(p: ProjectedSides, k: int, iterations: int, method: str = "cgram_hals", penalty: Penalty = NONE, seed: int = 7, normalize: str = "sweep", tolerance: float = 0.0, stop: str = "gain") -> tuple[DataFrame, DataFrame, list[tuple[int, float]]]:
    """(A, B: rows (key, f); trace), as ``solvers.solve_projected``: a pass over the rows, then one over the columns."""
    scale, (right, s) = 2 * np.sqrt(max(p.mean, 1e-12) / k), p.ranks
    a, b = (States(table, lambda r, salt=salt: with_start(r, k, salt, scale)) for table, salt in ((p.rows, seed), (p.cols, seed + 1)))
    kernel, rule, trace = KERNELS.get(method), Stop(tolerance, stop), []
    near_b, _, _ = row_pass(b, right, k, lambda x, f: f, s)

    def one_pass(update, component: int | None = None) -> np.ndarray:
        near, squares, _ = row_pass(a, s, k, update, right)
        if normalize != "none":
            size = np.where(squares > 0, np.sqrt(squares), 1.0) if component is None else _component_size(squares[component], k, component)
            a.divide(size)
            b.divide(1 / size)
            near = near / size
        return near

    def changed(f: np.ndarray, j: int, to: np.ndarray) -> np.ndarray:
        f = f.copy()
        f[:, j] = to
        return f

    for i in range(1, iterations + 1):
        for j in range(k) if method == "chals" else (None,):
            if j is None:
                near = one_pass(lambda x, f, t=near_b: kernel(x @ t, t.T @ t, f))
                update = lambda x, f, t=near: kernel(x @ t, t.T @ t, f, penalty)
            else:
                near = one_pass(lambda x, f, t=near_b, j=j: changed(f, j, residual_component(x, f, t, j)), j)
                update = lambda x, f, t=near, j=j: changed(f, j, residual_component(x, f, t, j, penalty))

            def measure(x, f, t=near):
                slope = f @ (t.T @ t) - x @ t
                return [((x - f @ t.T) ** 2).sum(), (np.where((f > 0) | (slope < 0), slope, 0.0) ** 2).sum()]

            near_b, _, (error, slope2) = row_pass(b, right, k, update, s, measure, 2)
        trace.append((i, 0.5 * float(error)))
        if rule.met(trace, lambda v=slope2: float(np.sqrt(v))):
            break
    if not iterations:
        return a.rows().select("key", "f"), b.f, trace
    return a.f, b.f, trace


def factorize(cells: DataFrame, k: int, s: int, w: int, iterations: int, method: str, penalty: Penalty, seed: int, normalize: str, tolerance: float, stop: str) -> tuple[DataFrame, DataFrame, list[tuple[int, float]]]:
    p = compress(cells, s, w, k, seed)
    return solve(p, k, iterations, method, penalty, seed, normalize, tolerance, stop)
