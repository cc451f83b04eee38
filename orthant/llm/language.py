"""Language ID (10): a linear-chain conditional random field over the words of a text.

Each word is an observation with affixes of one to three characters, its inner n-grams and itself (the
lexicon) as features, all hashed; the labels are the learnt languages, with learnt transitions. Training
sequences are spliced from texts of different languages, so that switches inside a text are seen; the
gradient comes from forward-backward. A text's prediction is the language with the most posterior mass
over all its words, and the score is that language's share of the mass.

A text is one chain. To let all parts of many texts advance together it is cut into runs of ``RUN`` words; the
product of a run's transfer matrices carries messages from one run to the next, so that posteriors are those of the
whole chain. Runs grow where these products would take more than ``PRODUCTS`` numbers.

Defined cases: a null text, or one without a letter, is ``und`` with score 0; a null lang is never learnt
from; a null doc_id is predicted, not held out and never learnt from; repeated rows are predicted alike;
ties go to the language first in order; an empty table gives an empty result; with no labelled row all
texts are ``und`` with score 0. Extra columns are ignored. The model is fitted on a bounded sample of every
language: ``PER_LANGUAGE`` texts, and of each up to ``PIECES`` pieces of ``PIECE`` words that hashes choose
among all its words. More than ``LANGUAGES`` languages raise an error, as none is left out.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import kernels as K
from .shared import id_remainder, text_parts

PER_LANGUAGE = 250
#: Words of a piece that training sequences are spliced from; pieces of a sampled text, at most.
PIECE, PIECES = 20, 20
#: The tables of weights take about 5 MB a language where the model is fitted.
LANGUAGES = 200
RUN, PRODUCTS = 64, 8_000_000
BITS = 16
#: Characters of an affix; inner n-grams; the last family is the whole word.
AFFIXES, NGRAMS = (1, 2, 3), (2, 3, 4)
_LETTER = regex.compile(r"\p{L}")
_U = np.uint64


@dataclass(frozen=True)
class Tagger:
    """``emission[family]``: buckets x languages. ``jump``: log weights of label pairs; ``prior``: of first labels."""

    languages: tuple[str, ...]
    emission: np.ndarray
    jump: np.ndarray
    prior: np.ndarray


def features(buf: np.ndarray, off: np.ndarray) -> tuple[list[tuple[np.ndarray, np.ndarray]], int, np.ndarray]:
    """Per family (word index, bucket) of its features; number of words; each text's first word and one more."""
    low = K.LOWER[buf]
    start, end, bounds = K.words(low, off)
    out = []
    if not len(start):
        return out, 0, bounds
    pre = K.prefix(low)
    chars = np.flatnonzero(~K.CONTINUATION[low])
    edge = np.append(chars, len(low))
    c0, c1 = np.searchsorted(chars, start), np.searchsorted(chars, end)
    every = np.arange(len(start))

    def add(word: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
        out.append((word, (K.span_hash(pre, a, b) >> _U(64 - BITS)).astype(np.int32)))

    for n in AFFIXES:
        long = np.flatnonzero(c1 - c0 >= n)
        add(long, start[long], edge[c0[long] + n])
        add(long, edge[c1[long] - n], end[long])
    owner = np.searchsorted(c0, np.arange(len(chars)), side="right") - 1
    for n in NGRAMS:
        at = np.flatnonzero((owner >= 0) & (np.arange(len(chars)) + n <= c1[np.maximum(owner, 0)]))
        add(owner[at], edge[at], edge[at + n])
    add(every, start, end)
    return out, len(start), bounds


FAMILIES = 2 * len(AFFIXES) + len(NGRAMS) + 1


def emissions(families: list[tuple[np.ndarray, np.ndarray]], n: int, weight: np.ndarray) -> np.ndarray:
    """words x languages."""
    total = np.zeros((n, weight.shape[2]), np.float32)
    for w, (word, bucket) in zip(weight, families, strict=True):
        got = w[bucket]
        if len(word) == n and (n == 0 or (word[0] == 0 and word[-1] == n - 1)) and np.array_equal(word, np.arange(n)):
            total += got
        elif len(word):
            opens = np.flatnonzero(np.append(True, word[1:] != word[:-1]))
            total[word[opens]] += np.add.reduceat(got, opens, axis=0)
    return total


def posteriors(scores: np.ndarray, jump: np.ndarray, prior: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """Forward-backward over padded runs (runs x steps x languages): label posteriors, expected counts of label
    pairs, and the log partition sum. Steps beyond ``length`` have posterior 0."""
    runs, steps, k = scores.shape
    top = scores.max(axis=2, keepdims=True)
    e = np.exp(scores - top)
    t = np.exp(jump - jump.max())
    live = np.arange(steps)[None, :] < length[:, None]
    forward = np.empty_like(e)
    scale = np.ones((runs, steps), e.dtype)
    now = e[:, 0] * np.exp(prior - prior.max())
    for i in range(steps):
        if i:
            now = (now @ t) * e[:, i]
        scale[:, i] = np.maximum(now.sum(axis=1), 1e-30)
        now = now / scale[:, i, None]
        forward[:, i] = now
    backward = np.ones((runs, k), e.dtype)
    gamma = np.zeros_like(e)
    pairs = np.zeros((k, k))
    for i in range(steps - 1, -1, -1):
        on = live[:, i]
        g = forward[:, i] * backward
        gamma[:, i] = np.where(on[:, None], g / np.maximum(g.sum(axis=1, keepdims=True), 1e-30), 0)
        if i:
            v = e[:, i] * backward / scale[:, i, None]
            pairs += t * (np.where(on[:, None], forward[:, i - 1], 0).T.astype(float) @ v.astype(float))
            backward = np.where(on[:, None], v @ t.T, backward)
    log_z = float(((np.log(scale) + top[:, :, 0]) * live).sum() + (jump.max() * (length - 1)).sum() + len(length) * prior.max())
    return gamma, pairs, log_z


def as_runs(scores: np.ndarray, bounds: np.ndarray, run: int = RUN) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Words cut into runs inside texts: (padded scores, lengths, index of each run's first word)."""
    n = np.diff(bounds)
    count = (n + run - 1) // run
    text = np.repeat(np.arange(len(n)), count)
    k = np.arange(len(text)) - np.repeat(np.cumsum(count) - count, count)
    first = bounds[text] + k * run
    length = np.minimum(run, bounds[text + 1] - first)
    index = np.minimum(first[:, None] + np.arange(run)[None, :], max(len(scores) - 1, 0))
    return scores[index], length, first


def chain_mass(scores: np.ndarray, jump: np.ndarray, prior: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """texts x labels: sums of the label posteriors of all words of each text, a text being one chain."""
    k, n = len(prior), np.diff(bounds)
    out = np.zeros((len(n), k))
    if not len(scores):
        return out
    run = max(RUN, int(-(-len(scores) * k * k // PRODUCTS)))
    run = min(run, int(n.max()))
    e, length, first = as_runs(scores, bounds, run)
    e = np.exp(e - e.max(axis=2, keepdims=True))
    text = np.searchsorted(bounds, first, side="right") - 1
    rank = (first - bounds[text]) // run
    t = np.exp(jump - jump.max()).astype(e.dtype)
    start = np.exp(prior - prior.max()).astype(e.dtype)
    live = np.arange(run)[None, :] < length[:, None]
    several = bool((rank > 0).any())
    product = None
    if several:  # of T diag(e) over a run's words
        product = np.broadcast_to(np.eye(k, dtype=e.dtype), (len(first), k, k)).copy()
        for i in range(run):
            step = (product @ t) * e[:, i, None, :]
            step /= np.maximum(step.max(axis=(1, 2), keepdims=True), 1e-30)
            product = np.where(live[:, i, None, None], step, product)
    enter = np.tile(start, (len(first), 1))
    if several:
        one = rank == 0
        # a first run begins with the prior instead of a transition
        now = e[one, 0] * start
        for i in range(1, run):
            step = (now @ t) * e[one, i]
            now = np.where(live[one, i][:, None], step / np.maximum(step.sum(axis=1, keepdims=True), 1e-30), now)
        # message after each first run, then on through the products
        after = np.zeros((len(first), k), e.dtype)
        after[one] = now / np.maximum(now.sum(axis=1, keepdims=True), 1e-30)
        # out[r] is the message after run r: that after run r - 1 times run r's product
        order = np.argsort(rank, kind="stable")
        edges = np.searchsorted(rank[order], np.arange(rank.max() + 2))
        for turn in range(1, len(edges) - 1):
            at = order[edges[turn] : edges[turn + 1]]
            got = np.einsum("rk,rkj->rj", after[at - 1], product[at])
            after[at] = got / np.maximum(got.sum(axis=1, keepdims=True), 1e-30)
            enter[at] = after[at - 1]
    forward = np.empty_like(e)
    now = enter
    for i in range(run):
        if i:
            now = (now @ t) * e[:, i]
        else:
            now = np.where((rank == 0)[:, None], enter * e[:, 0], (enter @ t) * e[:, 0])
        now = now / np.maximum(now.sum(axis=1, keepdims=True), 1e-30)
        forward[:, i] = now
    leave = np.ones((len(first), k), e.dtype)
    if several:
        from_end = np.repeat(np.bincount(text, minlength=len(n))[n > 0], np.bincount(text, minlength=len(n))[n > 0]) - 1 - rank
        order = np.argsort(from_end, kind="stable")
        edges = np.searchsorted(from_end[order], np.arange(from_end.max() + 2))
        for turn in range(1, len(edges) - 1):
            at = order[edges[turn] : edges[turn + 1]]
            got = np.einsum("rjk,rk->rj", product[at + 1], leave[at + 1])
            leave[at] = got / np.maximum(got.sum(axis=1, keepdims=True), 1e-30)
    backward, mass = leave, np.zeros((len(first), k))
    for i in range(run - 1, -1, -1):
        on = live[:, i, None]
        g = forward[:, i] * backward
        mass += np.where(on, g / np.maximum(g.sum(axis=1, keepdims=True), 1e-30), 0)
        v = (e[:, i] * backward) @ t.T
        backward = np.where(on, v / np.maximum(v.sum(axis=1, keepdims=True), 1e-30), backward)
    np.add.at(out, text, mass)
    return out


def train(texts: list[tuple[str, int]], languages: tuple[str, ...], epochs: int = 6, seed: int = 5) -> Tagger:
    """Stochastic gradient ascent on the likelihood of spliced sequences. ``texts``: (text, language's index)."""
    k = len(languages)
    weight = np.zeros((FAMILIES, 1 << BITS, k), np.float32)
    squares = np.full((FAMILIES, 1 << BITS, k), 1e-3, np.float32)
    jump, prior = np.eye(k) * 2.0, np.zeros(k)
    order = np.random.default_rng(seed)
    pieces = []  # runs of words of one language; a sequence is three of them
    for text, label in texts:
        words = text.split()
        pieces += [(" ".join(words[a : a + PIECE]), label) for a in range(0, len(words), PIECE)]
    for epoch in range(epochs):
        places = order.permutation(len(pieces))
        for a in range(0, len(places), 384):
            chosen = [pieces[i] for i in places[a : a + 384]]
            groups = [chosen[i : i + 3] for i in range(0, len(chosen), 3)]
            raw = [" ".join(p for p, _ in g).encode() for g in groups]
            off = np.append(0, np.cumsum([len(r) for r in raw])).astype(np.int64)
            families, n, bounds = features(np.frombuffer(b"".join(raw), np.uint8), off)
            if not n:
                continue
            gold = np.concatenate([np.repeat([y for _, y in g], [len(K.words(np.frombuffer(p.encode(), np.uint8), np.array([0, len(p.encode())]))[0]) for p, _ in g]) for g in groups])
            scores, length, first = as_runs(emissions(families, n, weight), bounds)
            gamma, pairs, _ = posteriors(scores.astype(float), jump, prior, length)
            flat = np.zeros((n, k))
            live = np.arange(RUN)[None, :] < length[:, None]
            flat[(first[:, None] + np.arange(RUN))[live]] = gamma[live]
            delta = -flat
            delta[np.arange(n), gold] += 1
            inner = np.ones(n, bool)
            inner[first] = False
            at = np.flatnonzero(inner)
            seen = np.zeros((k, k))
            np.add.at(seen, (gold[at - 1], gold[at]), 1)
            jump += 0.5 * ((seen - pairs) / max(1, len(at)) - 1e-3 * jump)
            prior += 0.1 * (np.bincount(gold[first], minlength=k) - flat[first].sum(axis=0)) / max(1, len(first))
            for f, (word, bucket) in enumerate(families):
                hit, where = np.unique(bucket, return_inverse=True)
                g = np.stack([np.bincount(where, delta[word, c], minlength=len(hit)) for c in range(k)], 1).astype(np.float32)
                g -= 1e-3 * weight[f, hit]
                squares[f, hit] += g * g
                weight[f, hit] += 0.25 * g / np.sqrt(squares[f, hit])
    return Tagger(languages, weight, jump, prior)


def _pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts of the pieces that hashes choose among all of each text, in their order."""
    for batch in batches:
        out = []
        for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
            words = (text or "").split()
            n = -(-len(words) // PIECE)
            order = K.mix(np.arange(n, dtype=_U) + K.mix(np.array([doc], np.int64).view(_U)))
            chosen = np.sort(order.argsort(kind="stable")[:PIECES])
            out.append(" ".join(w for i in chosen.tolist() for w in words[i * PIECE : (i + 1) * PIECE]))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("lang"), pa.array(out, pa.string())], ["doc_id", "lang", "text"])


def _sample(labelled: DataFrame) -> tuple[list[tuple[str, int]], tuple[str, ...]]:
    counts = labelled.groupBy("lang").agg(F.count("*").alias("n")).limit(LANGUAGES + 1).collect()
    if len(counts) > LANGUAGES:
        raise ValueError(f"more than {LANGUAGES} languages to learn")
    languages = tuple(sorted(r["lang"] for r in counts))
    if not languages:
        return [], ()
    # hashes below a bar that leaves a few times the wanted rows of a language; then the lowest of them
    shares = {r["lang"]: min(1.0, 4.0 * (PER_LANGUAGE + 25) / r["n"]) for r in counts}
    bars = F.create_map(*(x for k, v in shares.items() for x in (F.lit(k), F.lit(v))))
    place = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) / F.lit(float(1 << 20))
    ids = labelled.where(place < bars[F.col("lang")]).select("doc_id", "lang", place.alias("place"))
    ids = ids.withColumn("turn", F.row_number().over(Window.partitionBy("lang").orderBy("place", "doc_id"))).where(F.col("turn") <= PER_LANGUAGE).select("doc_id").distinct()
    # at most LANGUAGES * PER_LANGUAGE ids
    chosen = labelled.join(F.broadcast(ids), "doc_id").select("doc_id", "lang", "text")
    rows = chosen.mapInArrow(_pieces, "doc_id long, lang string, text string").dropDuplicates(["doc_id"]).collect()
    where = {x: i for i, x in enumerate(languages)}
    return [(r["text"], where[r["lang"]]) for r in sorted(rows, key=lambda r: r["doc_id"]) if r["lang"] in where and _LETTER.search(r["text"])], languages


def predict(documents: DataFrame, tagger: Tagger | None) -> DataFrame:
    spread = documents.sparkSession.sparkContext.broadcast(tagger)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = spread.value
        for batch in batches:
            n = batch.num_rows
            label, score = ["und"] * n, np.zeros(n)
            lettered = np.array([_LETTER.search(t) is not None for t in batch.column("text").to_pylist()], bool) if m is not None else np.zeros(n, bool)
            for a, b, buf, off in text_parts(batch.column("text")) if lettered.any() else ():
                families, words, bounds = features(buf, off)
                if not words:
                    continue
                mass = chain_mass(emissions(families, words, m.emission), m.jump, m.prior, bounds)
                best, total = mass.argmax(axis=1), np.maximum(mass.sum(axis=1), 1e-30)
                for i in np.flatnonzero(lettered[a:b]):
                    label[a + i], score[a + i] = m.languages[best[i]], min(1.0, mass[i, best[i]] / total[i])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(label), pa.array(score)], ["doc_id", "held_out", "lang_pred", "score"])

    return documents.select("doc_id", "held_out", F.coalesce("text", F.lit("")).alias("text")).mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")


def language_predictions(documents: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every whole text."""
    docs = documents.select("doc_id", "text", "lang", F.coalesce(id_remainder("doc_id", 4) == 2, F.lit(False)).alias("held_out"))
    texts, languages = _sample(docs.where("not held_out and lang is not null and doc_id is not null").select("doc_id", "text", "lang"))
    return predict(docs, train(texts, languages) if texts else None)
