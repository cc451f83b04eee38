"""Naive-Bayes-scaled linear classifiers over hashed text features.

A feature's weight is its class log-count ratio (indicator counts, smoothed) times a coefficient
of a linear hinge-loss model, which dual coordinate descent fits. Margins become probabilities by
a logistic curve that is fitted on margins of rows left out of the fit.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import materialize, text_parts

#: (bytes, offsets) -> (text index, bucket) of every feature occurrence, repeats allowed.
Featurizer = Callable[[np.ndarray, np.ndarray], tuple[np.ndarray, np.ndarray]]


@dataclass(frozen=True)
class LinearModel:
    """``table[bucket]`` is 0 or 1 + the index of ``weight``. ``slope`` and ``shift``: logistic curve."""

    table: np.ndarray
    weight: np.ndarray
    bias: float
    slope: float
    shift: float


def dual_coordinate_descent(rows: list[np.ndarray], values: list[np.ndarray], y: np.ndarray, dim: int, cost: np.ndarray, epochs: int = 12, seed: int = 7) -> tuple[np.ndarray, float]:
    """Minimises ||w||^2/2 + sum_i cost_i * hinge(y_i * w.x_i) with a bias as one more feature of value 1.
    One dual variable at a time goes to its box-constrained optimum; w is kept as the sum of the duals' rows."""
    w, b = np.zeros(dim), 0.0
    alpha = np.zeros(len(rows))
    curvature = np.array([float(v @ v) + 1.0 for v in values]) if rows else np.zeros(0)
    order = np.random.default_rng(seed)
    for _ in range(epochs):
        moved = 0.0
        for i in order.permutation(len(rows)):
            gradient = y[i] * (w[rows[i]] @ values[i] + b) - 1.0
            new = min(max(alpha[i] - gradient / curvature[i], 0.0), cost[i])
            step = (new - alpha[i]) * y[i]
            if step:
                w[rows[i]] += step * values[i]
                b += step
                moved = max(moved, abs(step))
                alpha[i] = new
        if moved < 1e-4:
            break
    return w, b


def logistic_fit(margin: np.ndarray, label: np.ndarray, weight: np.ndarray) -> tuple[float, float]:
    """Slope and shift of a weighted logistic curve through margins, with softened targets, by damped Newton steps."""
    pos, neg = weight[label > 0].sum(), weight[label <= 0].sum()
    if not pos or not neg:
        return 1.0, (2.0 if pos else -2.0) if len(label) else 0.0
    n_pos, n_neg = (label > 0).sum(), (label <= 0).sum()
    target = np.where(label > 0, (n_pos + 1) / (n_pos + 2), 1 / (n_neg + 2))
    theta = np.array([1.0, np.log(pos / neg)])
    x = np.stack([margin, np.ones_like(margin)], 1)

    def loss(t: np.ndarray) -> float:
        z = x @ t
        return float((weight * (np.logaddexp(0, z) - target * z)).sum() + 1e-3 * t[0] ** 2)

    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(x @ theta, -40, 40)))
        g = x.T @ (weight * (p - target)) + np.array([2e-3 * theta[0], 0])
        h = (x * (weight * p * (1 - p))[:, None]).T @ x + np.diag([2e-3, 1e-6])
        step, size, now = np.linalg.solve(h, g), 1.0, loss(theta)
        while size > 1e-4 and loss(theta - size * step) > now:
            size /= 2
        theta = theta - size * step
        if np.abs(size * step).max() < 1e-7:
            break
    return max(float(theta[0]), 1e-3), float(theta[1])


def training_sample(documents: DataFrame, labels: DataFrame, label: str, per_class: int) -> tuple[DataFrame, dict[int, float]]:
    """At most ``per_class`` labelled rows of each class (those whose ids hash lowest), with texts, and each
    sampled row's weight by class so that the weighted sample has the class shares of all labelled rows.
    Ids with contradicting labels are left out. ``documents`` holds only rows that may be learnt from."""
    marks = (
        labels.where(F.col("doc_id").isNotNull() & F.col(label).isin(0, 1))
        .groupBy("doc_id").agg(F.min(label).alias("low"), F.max(label).alias("high"))
        .where("low = high").select("doc_id", F.col("low").cast("int").alias("mark"))
    )
    counts = {int(r["mark"]): int(r["n"]) for r in marks.groupBy("mark").agg(F.count("*").alias("n")).collect()}
    chosen = None
    for c in (0, 1):
        part = marks.where(F.col("mark") == c).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class)
        chosen = part if chosen is None else chosen.unionByName(part)
    # at most 2 * per_class ids and marks: a proven bound for the broadcast
    sample = documents.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").dropDuplicates(["doc_id"])
    return sample, {c: counts.get(c, 0) / max(1, min(per_class, counts.get(c, 0))) for c in (0, 1)}


def _distinct(text: np.ndarray, feature: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    key = np.unique((text.astype(np.int64) << bits) | feature)
    return key >> bits, key & ((1 << bits) - 1)


def fit(documents: DataFrame, labels: DataFrame, label: str, featurize: Featurizer, bits: int, per_class: int, top: int, cost: float, least: int = 3, tasks: int = 12) -> LinearModel:
    """Fits on a bounded sample of labelled rows (``per_class`` rows of each class at most). What goes to the
    driver is bounded by ``tasks``, ``bits``, ``per_class`` and ``top``, not by the corpus."""
    sample, prior = training_sample(documents, labels, label, per_class)
    sample = materialize(sample.select("doc_id", "mark", F.coalesce("text", F.lit("")).alias("text")).repartition(tasks, "doc_id"), "sample")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tally, n = np.zeros((2, 1 << bits), np.uint16), [0, 0]
        for batch in batches:
            marks = batch.column("mark").to_numpy(zero_copy_only=False)
            for a, b, buf, off in text_parts(batch.column("text")):
                text, bucket = _distinct(*featurize(buf, off), bits)
                for c in (0, 1):
                    tally[c] += np.bincount(bucket[marks[a:b][text] == c], minlength=1 << bits).astype(np.uint16)
            for c in (0, 1):
                n[c] += int((marks == c).sum())
        yield pa.RecordBatch.from_pydict({"n0": [n[0]], "n1": [n[1]], "tally": [zlib.compress(tally.tobytes(), 1)]}, pa.schema([("n0", pa.int64()), ("n1", pa.int64()), ("tally", pa.binary())]))

    total, n = np.zeros((2, 1 << bits), np.int64), [0, 0]
    for row in sample.mapInArrow(count, "n0 long, n1 long, tally binary").toLocalIterator():
        total += np.frombuffer(zlib.decompress(bytes(row["tally"])), np.uint16).reshape(2, -1)
        n[0] += row["n0"]
        n[1] += row["n1"]
    # smoothed shares of texts that have the feature, each class's shares summing to 1
    ratio = np.log(((total[1] + 1) / (total[1].sum() + (1 << bits))) / ((total[0] + 1) / (total[0].sum() + (1 << bits))))
    a, b, na, nb = total[1], total[0], max(n[1], 1), max(n[0], 1)
    pooled = (a + b) / (na + nb)
    gain = np.where(a + b >= least, np.abs(a / na - b / nb) / np.sqrt(np.maximum(pooled * (1 - pooled), 1e-9) * (1 / na + 1 / nb)), 0)
    picked = np.argsort(-gain, kind="stable")[:top]
    picked = np.sort(picked[gain[picked] > 0])
    # the ratio from each class's own rate of texts, so that long texts of one class don't shift it
    ratio = np.log(((total[1][picked] + 1) / (na + 2)) / ((total[0][picked] + 1) / (nb + 2))) if len(picked) else ratio[:0]
    table = np.zeros(1 << bits, np.int32)
    table[picked] = np.arange(1, len(picked) + 1)

    spread = sample.sparkSession.sparkContext.broadcast(table)  # 4 << bits bytes, whatever the corpus

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[bytes] = []
            for a, b, buf, off in text_parts(batch.column("text")):
                text, bucket = featurize(buf, off)
                hit = spread.value[bucket]
                text, feature = _distinct(text[hit > 0], hit[hit > 0] - 1, bits)
                edges = np.searchsorted(text, np.arange(b - a + 1))
                out += [feature[edges[i] : edges[i + 1]].astype(np.int32).tobytes() for i in range(b - a)]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("mark"), pa.array(out, pa.binary())], ["doc_id", "mark", "features"])

    got = sorted(((r["doc_id"], r["mark"], np.frombuffer(bytes(r["features"]), np.int32)) for r in sample.mapInArrow(encode, "doc_id long, mark int, features binary").toLocalIterator()), key=lambda r: r[0])
    spread.unpersist()
    y = np.array([1.0 if r[1] else -1.0 for r in got])
    rows = [r[2] for r in got]
    values = [ratio[f] / max(1.0, np.sqrt(len(f))) for f in rows]
    if not len(y) or abs(y.sum()) == len(y):
        return LinearModel(table, np.zeros(len(picked), np.float32), 0.0, 1.0, 2.0 if len(y) and y[0] > 0 else -2.0)
    balance = np.where(y > 0, len(y) / (2 * max(1, (y > 0).sum())), len(y) / (2 * max(1, (y < 0).sum())))
    margin, folds = np.zeros(len(y)), np.arange(len(y)) % 3
    for k in range(3):
        own = np.flatnonzero(folds != k)
        w, bias = dual_coordinate_descent([rows[i] for i in own], [values[i] for i in own], y[own], len(picked), cost * balance[own])
        for i in np.flatnonzero(folds == k):
            margin[i] = w[rows[i]] @ values[i] + bias
    weight = np.array([prior[1] if v > 0 else prior[0] for v in y])
    slope, shift = logistic_fit(margin, y, weight / weight.mean())
    w, bias = dual_coordinate_descent(rows, values, y, len(picked), cost * balance)
    return LinearModel(table, (w * ratio).astype(np.float32), float(bias), slope, shift)


def score(frame: DataFrame, model: LinearModel, featurize: Featurizer, bits: int, threshold: float, schema: str, keep: list[str]) -> DataFrame:
    """``keep`` columns, then score and predicted of every row's whole text."""
    spread = frame.sparkSession.sparkContext.broadcast(model)
    names = [x.split()[0] for x in schema.split(", ")][: len(keep)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = spread.value
        for batch in batches:
            out = np.zeros(batch.num_rows)
            for a, b, buf, off in text_parts(batch.column("text")):
                text, bucket = featurize(buf, off)
                hit = m.table[bucket]
                on = hit > 0
                text, feature = _distinct(text[on], hit[on] - 1, bits)
                sums = np.bincount(text, m.weight[feature], minlength=b - a)
                sizes = np.bincount(text, minlength=b - a)
                out[a:b] = sums / np.maximum(1.0, np.sqrt(sizes)) + m.bias
            p = 1 / (1 + np.exp(-np.clip(m.slope * out + m.shift, -40, 40)))
            yield pa.RecordBatch.from_arrays([*(batch.column(f"k{i}") for i in range(len(keep))), pa.array(p), pa.array((p >= threshold).astype(np.int32))], [*names, "score", "predicted"])

    return frame.select(*(F.col(k).alias(f"k{i}") for i, k in enumerate(keep)), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(run, f"{schema}, score double, predicted int")
