"""Quality classifier (2) and toxicity classifier (3).

Quality: indicators of one- and two-token n-grams (tokens are runs of letters and digits, or runs of
other marks), scaled by naive Bayes log-count ratios, then a hinge-loss linear model fitted by dual
coordinate descent. Toxicity: the same for character n-grams of lower-cased text.

Defined cases: a null or empty text has no features and gets the model's score for none; a null doc_id
is scored, never learnt from and not held out; repeated rows are scored alike, each on its own; an empty
table gives an empty result; with no labelled row, or rows of one class only, the score is constant.
Extra columns are ignored. Both fit on a bounded sample of labelled rows: ``PER_CLASS`` of each class.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import linear
from .kernels import CONTINUATION, LOWER, SPACE, U64, mix, owner, prefix, span_hash
from .shared import id_remainder

#: Labelled rows of each class that a model is fitted on, at most.
PER_CLASS = 3000
#: Score from which a text counts as class 1.
THRESHOLD = 0.7
QUALITY_BITS, TOXIC_BITS = 20, 22
TOXIC_ORDERS = (3, 4, 5, 6)

_KIND = np.ones(256, np.uint8) * 2  # 0 space, 1 letters, digits and non-ASCII, 2 other marks
_KIND[SPACE] = 0
for _a, _b in ((48, 58), (65, 91), (97, 123), (128, 256)):
    _KIND[_a:_b] = 1


def token_ngrams(buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of tokens, of pairs of neighbours, and of one feature for a token that repeats the one before."""
    kind = _KIND[buf]
    if not len(kind):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    edge = np.ones(len(kind), bool)
    edge[1:] = kind[1:] != kind[:-1]
    edge[off[:-1][off[:-1] < len(kind)]] = True
    start = np.flatnonzero(edge)
    end = np.append(start[1:], len(kind))
    real = kind[start] > 0
    start, end = start[real], end[real]
    bounds = np.searchsorted(start, off)
    h, text = span_hash(prefix(buf), start, end), owner(bounds)
    if len(h) < 2:
        return text, (h >> U64(64 - QUALITY_BITS)).astype(np.int64)
    same = text[1:] == text[:-1]
    left, right = h[:-1][same], h[1:][same]
    pair = mix(left * U64(3) + right)
    pair[left == right] = U64(0x1234567 << 36)
    return np.concatenate([text, text[1:][same]]), (np.concatenate([h, pair]) >> U64(64 - QUALITY_BITS)).astype(np.int64)


def char_ngrams(buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all character n-grams of the ``TOXIC_ORDERS``, ASCII lower-cased, white space as one kind."""
    if not len(buf):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    low = LOWER[buf]
    low[SPACE[buf]] = 32
    start = np.flatnonzero(~CONTINUATION[buf])
    bounds = np.searchsorted(start, off)
    text, pre = owner(bounds), prefix(low)
    edges = np.append(start, len(buf))
    out_t, out_b = [], []
    for n in TOXIC_ORDERS:
        if len(start) < n:
            continue
        last = len(start) - n + 1
        inside = np.flatnonzero(text[:last] == text[n - 1 :])
        h = span_hash(pre, edges[inside], edges[inside + n])
        out_t.append(text[inside])
        out_b.append((h >> U64(64 - TOXIC_BITS)).astype(np.int64))
    if not out_t:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(out_t), np.concatenate(out_b)


def _classify(documents: DataFrame, labels: DataFrame, label: str, modulus: int, remainder: int, featurize: linear.Featurizer, bits: int, top: int, cost: float) -> DataFrame:
    docs = documents.select("doc_id", "text", F.coalesce(id_remainder("doc_id", modulus) == remainder, F.lit(False)).alias("held_out"))
    model = linear.fit(docs.where(~F.col("held_out")), labels.where(id_remainder("doc_id", modulus) != remainder), label, featurize, bits, PER_CLASS, top, cost)
    return linear.score(docs, model, featurize, bits, THRESHOLD, "doc_id long, held_out boolean", ["doc_id", "held_out"])


def quality_scores(documents: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score (higher: good quality likelier), predicted, for every row of ``documents``."""
    return _classify(documents, labels, "quality", 4, 2, token_ngrams, QUALITY_BITS, 60_000, 1.0)


def toxicity_scores(documents: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score (higher: toxic likelier), predicted, for every row of ``documents``."""
    return _classify(documents, labels, "toxic", 3, 1, char_ngrams, TOXIC_BITS, 8192, 1.0)


def good_documents(documents: DataFrame, learn_from: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``documents`` that the quality classifier accepts, with all their columns, whatever their
    names. The model learns from ``learn_from``, which may hold rows that went before."""
    teach = learn_from.select("doc_id", "text").where(F.coalesce(id_remainder("doc_id", 4) != 2, F.lit(False)))
    model = linear.fit(teach, labels.where(id_remainder("doc_id", 4) != 2), "quality", token_ngrams, QUALITY_BITS, PER_CLASS, 60_000, 1.0)
    row = F.struct(*(F.col(f"`{c}`") for c in documents.columns))
    inner = documents.select(row.alias("row"), "text")
    kind = inner.schema["row"].dataType.simpleString()
    out = linear.score(inner, model, token_ngrams, QUALITY_BITS, THRESHOLD, "row " + kind, ["row"]).where("predicted = 1")
    return out.select(*(F.col("row")[c].alias(c) for c in documents.columns))
