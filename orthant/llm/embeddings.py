"""Embedding near-duplicates (5): links of cosine 0.93 or more by an inverted multi-index.

Unit vectors are split in halves, each with a codebook (k-means on a bounded sample); pairs of codes are
the cells of a grid, and every vector is indexed in its cell. Each vector also visits its nearest cells
in the order of the sum of both half distances (multi-sequence order). How many it visits comes from
bounded sample queries compared with all rows: as many as reach ``TARGET`` of their true links in each
of the bands of cosines that begin at ``BANDS``, where each query counts alike within its cell and each cell alike,
so that a large group decides no more than a pair. A band with too few links in ``MOST_QUERIES`` queries is
judged by made partners at its least cosine. No bound but the number of cells stops the visits. Vectors
that meet in a cell are verified by their cosine in double precision. The number of codes grows with the
square root of the number of vectors, so that a cell holds about ``CELL_LOAD`` of them.

Equal vectors of one label are one class, indexed once. A cell is compared in shares of ``SHARE`` of
its vectors against a stream of the others, and what leaves it are sums of links and the edges of a
spanning forest, never all pairs. A pair that two cells see counts in one of them.

Defined cases: a null label, vectors that are null, empty, zero or hold null or non-finite components
link with nothing; vectors of different lengths don't link; repeated rows are vectors of their own that
link with each other; a null vec_id has no links and a null component, and counts for no one; an empty
table gives an empty result. Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import components
from .shared import materialize

COSINE = 0.93
TARGET = 0.995
CELL_LOAD, LEAST_CODES, MOST_CODES = 32, 8, 1024
SAMPLE, QUERIES, MOST_QUERIES = 8192, 1024, 8192
#: Least cosines of bands; cells of queries with links that a band needs to be judged by them.
BANDS, LEAST_CELLS = (COSINE, 0.95, 0.97), 30
SHARE = 1024


def unit(rows: list, width: int) -> np.ndarray:
    out = np.zeros((len(rows), width))
    for i, r in enumerate(rows):
        out[i, : len(r)] = r
    return out / np.linalg.norm(out, axis=1, keepdims=True)


def codebook(x: np.ndarray, k: int, seed: int, rounds: int = 10) -> np.ndarray:
    order = np.random.default_rng(seed)
    centers = x[order.permutation(len(x))[:k]].copy()
    for _ in range(rounds):
        code = (((centers**2).sum(1))[None, :] - 2 * x @ centers.T).argmin(1)
        n = np.bincount(code, minlength=len(centers))
        for j in range(x.shape[1]):
            sums = np.bincount(code, x[:, j], minlength=len(centers))
            centers[:, j] = np.where(n > 0, sums / np.maximum(n, 1), centers[:, j])
    return centers


class Grid:
    """Two codebooks; cell = code of the first half * codes + code of the second."""

    def __init__(self, sample: np.ndarray, codes: int):
        self.half = max(1, sample.shape[1] // 2)
        self.books = [codebook(x, min(codes, len(x)), i) for i, x in enumerate((sample[:, : self.half], sample[:, self.half :]))]
        self.k = len(self.books[0])

    def distances(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return tuple(np.maximum((h**2).sum(1)[:, None] + (b**2).sum(1)[None, :] - 2 * h @ b.T, 0) for h, b in zip((x[:, : self.half], x[:, self.half :]), self.books, strict=True))

    def cells(self, x: np.ndarray) -> np.ndarray:
        a, b = self.distances(x)
        return a.argmin(1) * self.k + b.argmin(1)

    def visits(self, x: np.ndarray, count: int) -> np.ndarray:
        """The ``count`` cells nearest to each vector, nearest first. The cell of ranks (i, j) has (i + 1)(j + 1)
        cells before or at it, so only ranks with a product of up to ``count`` can be among them."""
        a, b = self.distances(x)
        count = min(count, self.k * self.k)
        ranks = np.array([(i, j) for i in range(self.k) for j in range(self.k) if (i + 1) * (j + 1) <= count])
        oa, ob = a.argsort(1, kind="stable"), b.argsort(1, kind="stable")
        sums = np.take_along_axis(a, oa, 1)[:, ranks[:, 0]] + np.take_along_axis(b, ob, 1)[:, ranks[:, 1]]
        first = sums.argsort(1, kind="stable")[:, :count]
        return np.take_along_axis(oa, ranks[:, 0][first], 1) * self.k + np.take_along_axis(ob, ranks[:, 1][first], 1)

    def step(self, count: int) -> int:
        """Vectors whose visits fit in memory at a time."""
        count = min(count, self.k * self.k)
        return int(max(1, min(2048, (1 << 22) // sum(min(self.k, count // (i + 1)) for i in range(self.k)))))

    def rank(self, x: np.ndarray, cell: np.ndarray) -> np.ndarray:
        """Cells that are nearer to each vector than its given cell."""
        a, b = self.distances(x)
        out = np.zeros(len(x), np.int64)
        for i, c in enumerate(cell):
            out[i] = (a[i][:, None] + b[i][None, :] < a[i, c // self.k] + b[i, c % self.k]).sum()
        return out


def least_count(group: np.ndarray, query: np.ndarray, rank: np.ndarray, n: np.ndarray) -> int:
    """Least number of cells that reaches ``TARGET`` of links: ``n`` links of a ``query`` at each ``rank``. Queries weigh
    alike within their ``group``, and groups weigh alike."""
    of_query = np.bincount(query, n)
    one = np.unique(np.stack([group, query]), axis=1)
    weight = n / of_query[query] / np.bincount(one[0])[group] / len(np.unique(group))
    order = rank.argsort(kind="stable")
    reached = np.cumsum(weight[order])
    return int(rank[order][np.searchsorted(reached, TARGET - 1e-9)]) + 1


def _made_ranks(grid: Grid, q: np.ndarray, cosine: float, each: int = 4) -> np.ndarray:
    """The lesser ranks of each other's cells of queries and made partners of this cosine, ``each`` a query, in even directions."""
    q = np.repeat(q, each, axis=0)
    u = np.random.default_rng(7).standard_normal(q.shape)
    u -= (u * q).sum(1)[:, None] * q
    size = np.linalg.norm(u, axis=1, keepdims=True)
    made = cosine * q + (1 - cosine**2) ** 0.5 * np.divide(u, size, out=np.zeros_like(u), where=size > 1e-9)
    return np.minimum(grid.rank(q, grid.cells(made)), grid.rank(made, grid.cells(q)))


def _coarse(rank: np.ndarray) -> np.ndarray:
    """Ranks rounded up to an eighth of a power of two, so that a query has few of them."""
    unit_of = np.maximum(1, 1 << np.maximum(0, np.floor(np.log2(np.maximum(rank, 1))).astype(np.int64) - 3))
    return -(-rank // unit_of) * unit_of


def _sample_links(classes: DataFrame, grid: Grid, width: int, queries: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(unit vectors of sample queries, their groups, rows of query, band, rank, n) against all vectors."""
    chosen = classes.orderBy(F.xxhash64("rep", "h1"), "rep").limit(queries).select("key", "rep", "v").collect()
    keys, reps, q = [r["key"] for r in chosen], np.array([r["rep"] for r in chosen]), unit([r["v"] for r in chosen], width)
    spread = classes.sparkSession.sparkContext.broadcast((keys, reps, q, grid))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, reps, q, g = spread.value
        home = g.cells(q)
        of_key: dict[str, list[int]] = {}
        for i, k in enumerate(keys):
            of_key.setdefault(k, []).append(i)
        for whole in batches:
            for first in range(0, whole.num_rows, 1024):
                batch = whole.slice(first, 1024)
                x = unit(batch.column("v").to_pylist(), width)
                key, rep, cell = batch.column("key").to_pylist(), batch.column("rep").to_numpy(), g.cells(x)
                by: dict[str, list[int]] = {}
                for i, k in enumerate(key):
                    if k in of_key:
                        by.setdefault(k, []).append(i)
                found = [np.zeros((3, 0), np.int64)]
                for k, rows in by.items():
                    mine, theirs = np.array(rows), np.array(of_key[k])
                    near = x[mine] @ q[theirs].T
                    i, j = np.nonzero(near >= COSINE)
                    band = np.searchsorted(BANDS, near[i, j], side="right") - 1
                    i, j = mine[i], theirs[j]
                    on = rep[i] != reps[j]
                    i, j, band = i[on], j[on], band[on]
                    pair, back = np.unique(np.stack([j, cell[i]]), axis=1, return_inverse=True)
                    # a link is found if one of its ends visits the other
                    rank = np.minimum(g.rank(q[pair[0]], pair[1])[back.ravel()], g.rank(x[i], home[j]))
                    found.append(np.stack([j, band, _coarse(rank)]))
                same, n = np.unique(np.concatenate(found, axis=1), axis=1, return_counts=True)
                yield pa.RecordBatch.from_arrays([*map(pa.array, same), pa.array(n)], ["query", "band", "rank", "n"])

    seen = classes.select("key", "rep", "v").mapInArrow(run, "query long, band long, rank long, n long").groupBy("query", "band", "rank").agg(F.sum("n").alias("n")).collect()
    home, number = grid.cells(q), {k: i for i, k in enumerate(dict.fromkeys(keys))}
    group = np.unique(np.array([number[k] for k in keys]) * grid.k**2 + home, return_inverse=True)[1].ravel()
    return q, group, np.array([tuple(r) for r in seen], np.int64).reshape(-1, 4)


def _visit_count(classes: DataFrame, grid: Grid, width: int) -> int:
    """Cells to visit, from bounded sample queries against all vectors."""
    for queries in (QUERIES, MOST_QUERIES):
        q, group, links = _sample_links(classes, grid, width, queries)
        bands = [links[links[:, 1] == b] for b in range(len(BANDS))]
        enough = [len(np.unique(group[x[:, 0]])) >= LEAST_CELLS for x in bands]
        if all(enough) or len(q) < queries:
            break
    count = 4
    for x, told, cosine in zip(bands, enough, BANDS, strict=True):
        if len(x):
            count = max(count, least_count(group[x[:, 0]], x[:, 0], x[:, 2], x[:, 3]))
        if not told and len(q) == queries:  # if all vectors were asked, there are no other links
            made = _made_ranks(grid, q[:QUERIES], cosine)
            count = max(count, int(np.sort(made)[min(len(made) - 1, int(np.ceil(TARGET * len(made))) - 1)]) + 1)
    return min(count, grid.k**2)


def _meet(batches: Iterator[pa.RecordBatch], width: int, visits: int) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (key, cell, share), a share's own vectors first. Out: (a, b, n): n links of a if b is null, else an edge."""
    now, own, parent, sums = None, None, [], None
    out: list[tuple[int, int | None, int]] = []

    def root(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    def close() -> None:
        if own is not None:
            for i, rep in enumerate(own["rep"].tolist()):
                if sums[i]:
                    out.append((rep, None, int(sums[i])))
                if root(i) != i:
                    out.append((rep, int(own["rep"][root(i)]), 0))

    def link(i: np.ndarray, j: np.ndarray) -> None:
        for a, b in zip(i.tolist(), j.tolist(), strict=True):
            a, b = root(a), root(b)
            if a != b:
                parent[max(a, b)] = min(a, b)

    def part(b: dict, rows: np.ndarray) -> dict:
        return {k: v[rows] for k, v in b.items()}

    for batch in batches:
        n = batch.num_rows
        b = {k: batch.column(k).to_numpy(zero_copy_only=False) for k in ("rep", "copies", "cell", "home", "share", "member")}
        b["x"] = unit(batch.column("v").to_pylist(), width)
        none = np.full(visits, -1, np.int32).tobytes()  # of others than a cell's own vectors
        b["visits"] = np.stack([np.frombuffer(v or none, np.int32) for v in batch.column("visits").to_pylist()]) if n else np.zeros((0, visits), np.int32)
        key = np.array(batch.column("key").to_pylist(), object)
        edge = np.append(np.flatnonzero(np.append(True, (key[1:] != key[:-1]) | (b["cell"][1:] != b["cell"][:-1]) | (b["share"][1:] != b["share"][:-1]))), n) if n else np.zeros(1, int)
        for s, e in zip(edge[:-1], edge[1:], strict=True):
            name = (key[s], int(b["cell"][s]), int(b["share"][s]))
            rows = np.arange(s, e)
            fresh = part(b, rows[b["member"][s:e] == 0])
            if name != now:
                close()
                now, own, parent, sums = name, None, [], None
            if len(fresh["rep"]):
                first = 0 if own is None else len(own["rep"])
                own = fresh if own is None else {k: np.concatenate([own[k], fresh[k]]) for k in own}
                parent.extend(range(first, len(own["rep"])))
                sums = np.zeros(len(own["rep"]), np.int64) if sums is None else np.append(sums, np.zeros(len(fresh["rep"]), np.int64))
                near = fresh["x"] @ own["x"].T >= COSINE
                i, j = np.nonzero(near & (np.arange(len(own["rep"]))[None, :] < (first + np.arange(len(fresh["rep"])))[:, None]))
                i = i + first
                np.add.at(sums, i, own["copies"][j])
                np.add.at(sums, j, own["copies"][i])
                link(i, j)
            other = rows[b["member"][s:e] > 0]
            if own is None:
                continue
            for at in range(0, len(other), SHARE):
                m = part(b, other[at : at + SHARE])
                i, j = np.nonzero(m["x"] @ own["x"].T >= COSINE)
                # a visitor's pair counts where it is at home if the other one visits there and that cell comes first
                visiting = m["home"][i] != m["cell"][i]
                there = (own["visits"][j] == m["home"][i][:, None]).any(1) & (m["home"][i] < m["cell"][i])
                keep = ~(visiting & there)
                i, j = i[keep], j[keep]
                np.add.at(sums, j, m["copies"][i])
                got = np.zeros(len(m["rep"]), np.int64)
                np.add.at(got, i, own["copies"][j])
                opens = np.flatnonzero(np.append(True, i[1:] != i[:-1])) if len(i) else np.zeros(0, int)
                head = np.repeat(j[opens], np.diff(np.append(opens, len(i)))) if len(i) else j
                link(head, j)
                out += [(int(m["rep"][x]), None, int(got[x])) for x in np.flatnonzero(got)]
                out += [(int(m["rep"][i[o]]), int(own["rep"][j[o]]), 0) for o in opens]
        if len(out) > 20_000:
            yield pa.RecordBatch.from_arrays([pa.array([o[c] for o in out], pa.int64()) for c in range(3)], ["a", "b", "n"])
            out.clear()
    close()
    yield pa.RecordBatch.from_arrays([pa.array([o[c] for o in out], pa.int64()) for c in range(3)], ["a", "b", "n"])


def near_duplicates(embeddings: DataFrame) -> DataFrame:
    """vec_id, n_links, component_id, kept for every row."""
    v = F.col("embedding")
    sound = F.col("vec_id").isNotNull() & F.col("label").isNotNull() & v.isNotNull() & (F.size(v) > 0)
    sound &= ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0)
    # floats stay floats; other components are doubles, scaled so that no square overflows or vanishes
    kind = "float" if embeddings.schema["embedding"].dataType.elementType.typeName() == "float" else "double"
    most = F.array_max(F.transform(v, lambda x: F.abs(x.cast("double"))))
    as_kind = F.transform(v, lambda x: x + F.lit(0.0).cast("float")) if kind == "float" else F.transform(v, lambda x: F.coalesce(x.cast("double") / F.when(most > 0, most), F.lit(0.0)) + F.lit(0.0))
    keyed = embeddings.select("vec_id", F.coalesce(sound, F.lit(False)).alias("sound"), F.concat_ws("|", F.col("label").cast("string"), F.size(v).cast("string")).alias("key"), as_kind.alias("v"))
    rows = materialize(keyed.withColumn("h1", F.xxhash64("v")).withColumn("h2", F.hash("v")), "vectors")
    grouped = rows.where("sound").groupBy("key", "h1", "h2").agg(F.min("vec_id").alias("rep"), F.count("*").alias("copies"), F.first("v").alias("v"))
    classes = materialize(grouped, "vector-classes")
    n, width = classes.agg(F.count("*"), F.max(F.size("v"))).first()
    links = rows.sparkSession.createDataFrame([], "a long, b long, n long")
    if n:
        sample = unit([r["v"] for r in classes.orderBy(F.xxhash64("h1", "rep"), "rep").limit(SAMPLE).select("v").collect()], width)
        grid = Grid(sample, int(min(MOST_CODES, max(LEAST_CODES, (n / CELL_LOAD) ** 0.5))))
        visits = _visit_count(classes, grid, width)
        step = grid.step(visits)
        spread = classes.sparkSession.sparkContext.broadcast(grid)

        def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for a in range(0, batch.num_rows, step):
                    part = batch.slice(a, step)
                    x = unit(part.column("v").to_pylist(), width)
                    home, seen = spread.value.cells(x), spread.value.visits(x, visits).astype(np.int32)
                    yield pa.RecordBatch.from_arrays([*(part.column(c) for c in ("key", "rep", "copies", "v")), pa.array(home), pa.array([r.tobytes() for r in seen], pa.binary()), pa.array(seen.tolist(), pa.list_(pa.int32()))], ["key", "rep", "copies", "v", "home", "visits", "cells"])

        indexed = materialize(classes.select("key", "rep", "copies", "v").mapInArrow(index, f"key string, rep long, copies long, v array<{kind}>, home long, visits binary, cells array<int>"), "vector-index")
        loads = indexed.groupBy("key", "home").agg(F.ceil(F.count("*") / F.lit(float(SHARE))).cast("int").alias("shares")).withColumnRenamed("home", "cell")
        cells = F.array_distinct(F.concat(F.array("home"), F.transform("cells", lambda c: c.cast("long"))))
        sent = indexed.select("*", F.explode(cells).alias("cell")).drop("cells").join(loads, ["key", "cell"])
        mine = F.pmod(F.hash("rep"), F.col("shares"))
        # a vector at home opens its own share and joins the shares before it; a visitor joins all shares
        sent = sent.select("*", F.when(F.col("cell") == F.col("home"), mine).otherwise(F.col("shares") - 1).alias("last")).select("*", F.explode(F.sequence(F.lit(0), "last")).alias("share"))
        sent = sent.withColumn("member", F.when((F.col("cell") == F.col("home")) & (F.col("share") == F.col("last")), 0).otherwise(1))
        met = sent.select("key", "cell", "share", "member", "rep", "copies", "home", F.when(F.col("member") == 0, F.col("visits")).alias("visits"), "v").repartition("key", "cell", "share").sortWithinPartitions("key", "cell", "share", "member", "rep")
        links = materialize(met.mapInArrow(lambda it: _meet(it, width, visits), "a long, b long, n long"), "vector-links")
    sums = links.where("b is null").groupBy("a").agg(F.sum("n").alias("others")).withColumnRenamed("a", "rep")
    roots = components(links.where("b is not null").select("a", "b")).withColumnRenamed("node", "rep")
    named = classes.select("key", "h1", "h2", "rep", "copies").join(sums, "rep", "left").join(roots, "rep", "left")
    named = named.select("key", "h1", "h2", (F.coalesce("others", F.lit(0)) + F.col("copies") - 1).alias("links"), F.coalesce("root", "rep").alias("component")).withColumn("found", F.lit(True))
    out = rows.select("vec_id", "sound", "key", "h1", "h2").join(named, ["key", "h1", "h2"], "left")
    component = F.when(F.col("sound"), F.col("component")).otherwise(F.col("vec_id"))
    return out.select("vec_id", F.when(F.col("sound"), F.col("links")).otherwise(0).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(False)).alias("kept"))
