"""Connected components of an edge table by alternating star contractions.

Each round links every node's larger neighbours to its smallest one, then its smaller neighbours too;
both are one grouped minimum and one join, so no node's neighbours are ever gathered. Rounds are written
to the shared folder. The number of rounds grows with the logarithm of the longest path. An edge table of
at most ``ONE_TASK`` edges, counted first, is contracted by one task instead, which saves the rounds' jobs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import discard, materialize


#: Edges that one task contracts (16 bytes each, and a few times that while it works).
ONE_TASK = 1_000_000


def contract(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, roots): each node hooks to the least root beside it, then paths are halved, until nothing changes."""
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b, root = at[: len(u)], at[len(u) :], np.arange(len(nodes))
    while True:
        ra, rb = root[a], root[b]
        if (ra == rb).all():
            return nodes, nodes[root]
        np.minimum.at(root, np.maximum(ra, rb), np.minimum(ra, rb))
        while (root[root] != root).any():
            root = root[root]


def _contracted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    parts = [(b.column("u").to_numpy(), b.column("v").to_numpy()) for b in batches]
    if parts:
        nodes, roots = contract(*(np.concatenate([p[i] for p in parts]) for i in (0, 1)))
        for a in range(0, len(nodes), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(nodes[a : a + 100_000]), pa.array(roots[a : a + 100_000])], ["node", "root"])


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One contraction of (u, v) with u > v. Large: each node's larger neighbours join its least neighbour.
    Small: a node and its smaller neighbours do."""
    if large:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        out = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        least = edges.groupBy("u").agg(F.min("v").alias("m"))
        out = edges.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v")))
    return out.where("u > v").distinct()


def components(edges: DataFrame, most_rounds: int = 60, one_task: int = ONE_TASK) -> DataFrame:
    """(node, root) for every node of an edge (a, b): root is the smallest node of its component. Null and
    repeated edges and loops are ignored; no edges give an empty result."""
    now = materialize(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"), "a", "b").where("a is not null and b is not null and u > v").select("u", "v").distinct(), "component-edges")
    size = now.agg(F.count("*").alias("n"), F.sum(F.hash("u", "v").cast("long")).alias("h")).first()
    if size["n"] <= one_task:
        out = materialize(now.coalesce(1).mapInArrow(_contracted, "node long, root long"), "component-roots")
        discard(now)
        return out
    for _ in range(most_rounds):
        if not size["n"]:
            break
        nxt = materialize(_star(_star(now, True), False), "component-round")
        after = nxt.agg(F.count("*").alias("n"), F.sum(F.hash("u", "v").cast("long")).alias("h")).first()
        discard(now)
        now, same, size = nxt, after == size, after
        if same:
            break
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("root"))).distinct()
