"""Quality rules (4): base counts of every text, then robust multivariate outliers.

For each language and source a minimum-covariance-determinant estimate of transformed statistics is
found by concentration steps over all its rows: distances are computed, the nearest ``SUBSET`` share of
rows gives the next mean and covariance, and so on. ``STARTS`` starts (one of medians and absolute
deviations, the others of some ``START_ROWS`` rows each) go ``FIRST_STEPS`` steps side by side, that with the least
determinant goes on until no group's determinant falls by more than ``SETTLED`` of itself, and is then reweighted: mean and covariance of all rows within
the ``REWEIGHT`` quantile of it, which keeps the resistance and wastes no clean rows. Cuts are approximate quantiles
with a rank error of at most a 2000th. Each
step is a join of the written statistics with one row of parameters per group and start and a partial
aggregation, so a group of any size is never gathered. Rows whose squared Mahalanobis distance is above
the ``LEVEL`` quantile of its chi-square distribution go.

A group with fewer than ``LEAST_GROUP`` rows (ten a dimension) is judged with the other small groups of its language;
if they are too few together, with all such rows; below ``LEAST_FIT`` rows, less than a covariance needs, nothing is
rejected. Floors on
the spreads (``FLOOR``) regularise covariances, as half or more of a group's rows have no symbol, repeated line or
repeated word at all and their spread there is 0. At the cutoff each floor still lets its statistic reject alone
(about six repeated lines, or a share 0.17 off the center). The ratios are pulled towards usual values by a weight of
50 words, so that short texts don't stand out by chance. ``rejections`` counts what each group loses.

Defined cases: a null or empty text has no words and fails the base rule; null languages and sources
form groups of their own; null ids and repeated rows are rows like others; an empty table gives an empty
result. Extra columns are ignored, or handed on by ``kept_documents``.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from math import exp, factorial

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .shared import materialize, text_parts

SUBSET = 0.75
FIRST_STEPS, SETTLED, REWEIGHT = 2, 0.01, 0.975
STARTS, START_ROWS = 3, 60
#: Beyond so many steps an error is raised; subsets by exact quantiles settle in any case.
MOST_STEPS = 60
LEVEL = 0.999
LEAST_GROUP, LEAST_FIT = 60, 12
#: Groups whose table of parameters may be broadcast.
BROADCAST_GROUPS = 50_000
#: log mean word length, symbols, repeated lines, repeated words, capitals, marks.
FLOOR = (0.035, 0.12, 0.4, 0.035, 0.035, 0.035)
DIM = len(FLOOR)

_SYMBOL = K.lut(b"#*$%&|<>")
_CAPITAL = K.lut(bytes(range(65, 91)))
_MARK = K.lut(bytes(i for i in range(33, 127) if not chr(i).isalnum()))
_COUNTS = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_capitals long, n_marks long"
NAMES = [x.split()[0] for x in _COUNTS.split(", ")]


def count_slice(buf: np.ndarray, off: np.ndarray) -> list[np.ndarray]:
    """The counts of ``_COUNTS`` for each text of a slice."""
    n = len(off) - 1
    if not len(buf):
        return [np.zeros(n, np.int64)] * len(NAMES)
    inside = ~K.SPACE[buf]
    start, end, bounds = K.spans(inside, off)
    n_words = np.diff(bounds)
    chars = K.per_text(inside & ~K.CONTINUATION[buf], off)
    symbols, capitals, marks = (K.per_text(t[buf], off) for t in (_SYMBOL, _CAPITAL, _MARK))
    pre = K.prefix(buf)
    # lines: from a text's start or a line feed to the next one; only those with a word count
    lf = np.flatnonzero(buf == 10)
    line_start = np.unique(np.concatenate([off[:-1], lf + 1]))
    line_start = line_start[line_start < len(buf)]
    text = np.searchsorted(off, line_start, side="right") - 1
    nxt = np.searchsorted(lf, line_start)
    line_end = np.minimum(np.append(lf, len(buf))[nxt], off[text + 1])
    real = np.searchsorted(start, line_end) > np.searchsorted(start, line_start)
    line_start, line_end, text = line_start[real], line_end[real], text[real]
    key = K.mix(K.span_hash(pre, line_start, line_end) + text.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    _, first = np.unique(key, return_index=True)
    dup_lines = np.bincount(text, minlength=n) - np.bincount(text[first], minlength=n)
    # words in windows of five that the text holds twice or more
    hashes, at, owner = K.windows(K.span_hash(pre, start, end), bounds, 5)
    key = K.mix(hashes + owner.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    order = np.argsort(key)
    same = np.zeros(len(key) + 1, bool)
    same[1:-1] = key[order][1:] == key[order][:-1]
    twice = at[order[same[1:] | same[:-1]]]
    cover = np.zeros(len(start) + 1, np.int32)
    cover[twice] += 1
    cover[twice + 5] -= 1
    repeat = K.per_text(np.cumsum(cover[:-1]) > 0, bounds)
    return [n_words, chars, symbols, dup_lines, repeat, capitals, marks]


def counts(documents: DataFrame, keep: list[str]) -> DataFrame:
    """``keep`` columns and the counts of every whole text."""
    types = {f.name: f.dataType.simpleString() for f in documents.schema}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = np.zeros((len(NAMES), batch.num_rows), np.int64)
            for a, b, buf, off in text_parts(batch.column("text")):
                for row, x in zip(out, count_slice(buf, off), strict=True):
                    row[a:b] = x
            yield pa.RecordBatch.from_arrays([*(batch.column(f"k{i}") for i in range(len(keep))), *map(pa.array, out)], [*(f"k{i}" for i in range(len(keep))), *NAMES])

    frame = documents.select(*(F.col(k).alias(f"k{i}") for i, k in enumerate(keep)), F.coalesce("text", F.lit("")).alias("text"))
    out = frame.mapInArrow(run, ", ".join(f"k{i} {types[k]}" for i, k in enumerate(keep)) + ", " + _COUNTS)
    return out.select(*(F.col(f"k{i}").alias(k) for i, k in enumerate(keep)), *NAMES)


def base_failed() -> Column:
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def statistics() -> list[Column]:
    words, chars = F.col("n_words").cast("double"), F.col("word_chars").cast("double")
    return [
        F.log((chars + 300) / (words + 50)),
        F.log1p(100 * F.col("n_symbols") / (chars + 300)),
        F.log1p(F.col("n_dup_lines").cast("double")),
        F.col("n_repeat_words") / (words + 50),
        F.col("n_capitals") / (chars + 300),
        F.col("n_marks") / (chars + 300),
    ]


def chi2_below(x: float, even: int) -> float:
    return 1 - exp(-x / 2) * sum((x / 2) ** k / factorial(k) for k in range(even // 2))


def chi2_quantile(share: float, even: int) -> float:
    low, high = 0.0, 500.0
    for _ in range(80):
        mid = (low + high) / 2
        low, high = (mid, high) if chi2_below(mid, even) < share else (low, mid)
    return low


def consistency(share: float, even: int) -> float:
    """What the covariance of the nearest ``share`` of normal rows is multiplied by to be the covariance of all."""
    return share / chi2_below(chi2_quantile(share, even), even + 2)


CUTOFF = chi2_quantile(LEVEL, DIM)


def _distance() -> Column:
    total = None
    for i in range(DIM):
        for j in range(i, DIM):
            term = F.col("precision")[i * DIM + j] * (F.col(f"x{i}") - F.col("center")[i]) * (F.col(f"x{j}") - F.col("center")[j]) * (1.0 if i == j else 2.0)
            total = term if total is None else total + term
    return total


def _sums(frame: DataFrame) -> DataFrame:
    """Per fit and start: rows, and sums of deviations from the center and of their products."""
    d = [F.col(f"x{i}") - F.col("center")[i] for i in range(DIM)]
    sums = frame.groupBy("fit", "start").agg(F.count("*").alias("n"), F.first("center").alias("center"), *(F.sum(d[i]).alias(f"s{i}") for i in range(DIM)), *(F.sum(d[i] * d[j]).alias(f"q{i}_{j}") for i in range(DIM) for j in range(i, DIM)))
    return sums.select("fit", "start", "n", "center", F.array(*(f"s{i}" for i in range(DIM))).alias("s"), F.array(*(f"q{i}_{j}" for i in range(DIM) for j in range(i, DIM))).alias("q"))


_PARAMS = "fit string, start int, center array<double>, precision array<double>, log_det double"


def _invert(frames: Iterator[pd.DataFrame], scale: float) -> Iterator[pd.DataFrame]:
    """Precision matrices and log determinants of covariances from ``_sums``."""
    for f in frames:
        center, precision, log_det = [], [], []
        for n, c, s, q in zip(f["n"], f["center"], f["s"], f["q"], strict=True):
            mean = np.asarray(s) / n
            cov = np.zeros((DIM, DIM))
            cov[np.triu_indices(DIM)] = np.asarray(q) / n
            cov = cov + cov.T - np.diag(np.diag(cov)) - np.outer(mean, mean)
            center.append((np.asarray(c) + mean).tolist())
            full = scale * cov + np.diag(np.square(FLOOR))
            precision.append(np.linalg.inv(full).ravel().tolist())
            log_det.append(float(np.linalg.slogdet(full)[1]))
        yield pd.DataFrame({"fit": f["fit"], "start": f["start"], "center": center, "precision": precision, "log_det": log_det})


def _fitted(x: DataFrame, near: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """fit, center, precision: of the start with the least determinant. ``x``: fit, x0, x1, ..."""
    middle = x.groupBy("fit").agg(F.count("*").alias("n"), *(F.percentile_approx(f"x{i}", 0.5, 1000).alias(f"m{i}") for i in range(DIM))).where(F.col("n") >= LEAST_FIT)
    middle = materialize(middle, "rule-median")
    spread = x.join(near(middle), "fit").groupBy("fit").agg(*(F.percentile_approx(F.abs(F.col(f"x{i}") - F.col(f"m{i}")), 0.5, 1000).alias(f"d{i}") for i in range(DIM)))
    start = F.array(*(v for i in range(DIM) for j in range(DIM) for v in [1 / (F.pow(1.4826 * F.col(f"d{i}"), 2) + FLOOR[i] ** 2) if i == j else F.lit(0.0)]))
    medians = F.array(*(f"m{i}" for i in range(DIM))).alias("center")
    params = middle.join(spread, "fit").select("fit", F.lit(0).alias("start"), medians, start.alias("precision"), F.lit(0.0).alias("log_det"))
    # the other starts: rows whose hashes leave about START_ROWS of a fit
    place = F.pmod(F.xxhash64("start", *(f"x{i}" for i in range(DIM))), F.lit(1 << 30)) / F.lit(float(1 << 30))
    few = x.join(near(middle.select("fit", "n", medians)), "fit").withColumn("start", F.explode(F.array(*(F.lit(i) for i in range(1, STARTS))))).where(place * F.col("n") < START_ROWS)
    params = params.unionByName(_sums(few).mapInPandas(lambda it: _invert(it, 1.0), _PARAMS))
    scale = consistency(SUBSET, DIM)
    params = materialize(params, "rule-params")
    least = F.min(F.struct("log_det", "start", "center", "precision")).alias("best")
    for step in range(MOST_STEPS):
        far = x.join(near(params), "fit").withColumn("far", _distance())
        cut = far.groupBy("fit", "start").agg(F.percentile_approx("far", SUBSET, 2000).alias("cut"))
        nearest = far.join(near(materialize(cut, "rule-cut")), ["fit", "start"]).where("far <= cut")
        last, params = params, materialize(_sums(nearest).mapInPandas(lambda it: _invert(it, scale), _PARAMS), "rule-params")
        if step + 1 == FIRST_STEPS:
            params = materialize(params.groupBy("fit").agg(least).select("fit", "best.start", "best.center", "best.precision", "best.log_det"), "rule-params")
        if step + 1 > FIRST_STEPS:
            fallen = last.select("fit", "start", F.col("log_det").alias("was")).join(params, ["fit", "start"]).agg(F.max(F.col("was") - F.col("log_det"))).first()[0]
            if fallen is None or fallen <= SETTLED:
                break
    else:
        raise RuntimeError("concentration steps did not settle")
    close = x.join(near(params), "fit").where(_distance() <= chi2_quantile(REWEIGHT, DIM))
    final = _sums(close).mapInPandas(lambda it: _invert(it, consistency(REWEIGHT, DIM)), _PARAMS)
    return materialize(final.select("fit", "center", "precision"), "rule-final")


def judged(documents: DataFrame, keep: list[str] | None = None) -> DataFrame:
    """``keep`` columns (doc_id by default), the counts, base_failed, distance (null: not judged), kept. Where
    texts are kept, they are counted twice, for the fit and for the verdict, and not written between."""
    keep = keep or ["doc_id"]
    wide = keep != ["doc_id"]
    lang, source = (F.coalesce(F.concat(F.lit("="), F.col(k).cast("string")), F.lit("-")) for k in ("lang", "source"))
    work = documents.select(*keep, *([] if "text" in keep else ["text"]), lang.alias("_lang"), source.alias("_source"))
    rows = materialize(counts(work, ["_lang", "_source"] if wide else [*keep, "_lang", "_source"]).withColumn("base_failed", base_failed()), "rule-counts")
    sound = rows.where("not base_failed").select("_lang", "_source", *(x.alias(f"x{i}") for i, x in enumerate(statistics())))
    groups = materialize(sound.groupBy("_lang", "_source").agg(F.count("*").alias("n")), "rule-groups")
    few = groups.count() <= BROADCAST_GROUPS
    near = lambda x: F.broadcast(x) if few else x
    small = groups.where(F.col("n") < LEAST_GROUP).groupBy("_lang").agg(F.sum("n").alias("rest"))
    # the fit that judges a group: its own, that of its language's small groups, or that of all other rows
    fits = groups.join(small, "_lang", "left").select("_lang", "_source", F.when(F.col("n") >= LEAST_GROUP, F.concat_ws("\x1f", "_lang", "_source")).when(F.col("rest") >= LEAST_GROUP, F.col("_lang")).otherwise(F.lit("")).alias("fit"))
    fits = materialize(fits, "rule-fits")
    x = sound.join(near(fits), ["_lang", "_source"]).select("fit", *(f"x{i}" for i in range(DIM)))
    params = _fitted(x, near)
    if wide:
        rows = counts(work, [*keep, "_lang", "_source"]).withColumn("base_failed", base_failed())
    scored = rows.select("*", *(x.alias(f"x{i}") for i, x in enumerate(statistics()))).join(near(fits), ["_lang", "_source"], "left").join(near(params), "fit", "left")
    scored = scored.withColumn("distance", F.when(~F.col("base_failed"), _distance()))
    return scored.select(*keep, *NAMES, "base_failed", "distance", (~F.col("base_failed") & (F.coalesce("distance", F.lit(0.0)) <= CUTOFF)).alias("kept"))


def verdicts(documents: DataFrame) -> DataFrame:
    return judged(documents).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "distance", "kept")


def rejections(documents: DataFrame) -> DataFrame:
    """lang, source, n, base_failed, rejected: rows of each group, those the base rule drops, and those dropped beyond it."""
    out = judged(documents, ["lang", "source"])
    lost = [F.count_if(c).alias(k) for k, c in (("base_failed", F.col("base_failed")), ("rejected", ~F.col("base_failed") & ~F.col("kept")))]
    return out.groupBy("lang", "source").agg(F.count("*").alias("n"), *lost)


def kept_documents(documents: DataFrame) -> DataFrame:
    """The rows of ``documents`` that are kept, with all their columns, whatever their names."""
    inner = documents.select("doc_id", "text", "lang", "source", F.struct(*(F.col(f"`{c}`") for c in documents.columns if c != "text")).alias("_row"))
    out = judged(inner, ["text", "_row"]).where("kept")
    return out.select(*(F.col("text") if c == "text" else F.col("_row")[c].alias(c) for c in documents.columns))
