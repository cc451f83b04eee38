"""N-gram Jaccard join (8): links between texts whose word shingles overlap by three quarters or more.

Texts with the same set of shingles are one class. Classes are joined by token-combination prefixes.
Shingles are put in one order, rare ones before frequent ones (by a sketch that counts all shingles),
and a set's prefix is extended until it holds so many keys that a partner, which may lack only
``n - ceil(0.75 n)`` of its shingles, must share one. A rare shingle is a key by itself. Frequent ones
are dealt into groups by hash, and each pair of one group is a key, so that k shingles of a group
count k - 1. The number of groups goes with the size band of a set; sets are keyed for their own band
and the next lower one, and two partners always have one of these in common.

Keys travel as packed arrays in hash buckets; pairs of shingles that are both very frequent (``HOT``
more than a usual bucket of the sketch) are rows of their own, so that no bucket has to hold such a
list. A bucket yields the pairs of short lists. In long lists each set meets the list's most central
sets of its size, those with the least share of rare shingles; what is then still in different
components is compared with other central sets, and in the end pair by pair, but only sets outside
their list's main component. No list is cut and no link is lost: what is skipped can't reach the
similarity (sizes, positions, frequent shingles) or adds nothing to a component.

Each class has a bitmap of its shingles, about a byte a shingle. Bits that only one of two bitmaps has
bound the overlap from above; pairs within that bound are verified on whole texts.

Defined cases: a null or empty text has no shingles and links with nothing; texts under five words are
one shingle; repeated rows and exact copies share a class; rows with one id but different texts share
a component; a null id gives a null component and links nothing; an empty table gives an empty result.
Extra columns are ignored, or handed on by ``representatives``.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .components import components
from .shared import discard, materialize, text_parts

WIDTH = 5
#: Buckets of the shingle counter, and the parts in which its sums are made.
SKETCH_BITS, SKETCH_PARTS = 23, 32
#: Keys that one bucket holds, about.
BUCKET_KEYS = 150_000
#: A list of up to so many sets gives all its pairs at once.
SHORT_LIST = 12
#: Heads of long lists that a bucket compares a set with at first.
PIVOTS = 3
#: Further rounds of stars over long lists before pairs are compared one by one.
STAR_ROUNDS = 2
#: Sets outside their list's main component that meet the others as one array, about.
GATHERED = 64
#: Occurrences above the usual load from which a shingle's pairs with others like it leave the buckets.
HOT = 50_000
#: Ids that may be broadcast to pick texts; more are joined by a shuffle.
BROADCAST_IDS = 500_000
#: Members that one copy of a pivot's text is compared with.
PIVOT_SHARE = 1000
#: Set signatures that a task remembers, so that copies in its rows send their keys once.
REMEMBERED = 500_000

_ENTRY = np.dtype([("k", "<u8"), ("s", "<u8"), ("n", "<u4"), ("lim", "<u4")])
_U = np.uint64


def shingle_sets(buf: np.ndarray, off: np.ndarray) -> list[np.ndarray]:
    """Each text's sorted distinct shingle hashes."""
    n = len(off) - 1
    if not len(buf):
        return [np.zeros(0, _U)] * n
    low = K.LOWER[buf]
    start, end, bounds = K.words(low, off)
    h = K.span_hash(K.prefix(low), start, end)
    windows, _, text = K.windows(h, bounds, WIDTH)
    edges = np.searchsorted(text, np.arange(n + 1))
    out = []
    for i in range(n):
        m = bounds[i + 1] - bounds[i]
        if m >= WIDTH:
            u = np.sort(windows[edges[i] : edges[i + 1]])
            keep = np.ones(len(u), bool)
            np.not_equal(u[1:], u[:-1], out=keep[1:])
            out.append(u[keep])
        elif m:
            w = h[bounds[i] : bounds[i + 1]]
            out.append(K.mix((w * K._WINDOW[:m]).sum(keepdims=True) + _U(int(m) * 0x9E3779B97F4A7C15 % (1 << 64))))
        else:
            out.append(windows[:0])
    return out


def signature(u: np.ndarray) -> np.uint64:
    m = K.mix(u)
    return K.mix(m.sum(keepdims=True) + np.bitwise_xor.reduce(m, keepdims=True) * _U(3) + _U(len(u) * 0xD6E8FEB86659FD93 % (1 << 64)))[0]


def bitmap(u: np.ndarray) -> bytes:
    """A power of two of bits, at least four a shingle, with each shingle's bit set."""
    size = max(64, 1 << (4 * len(u) - 1).bit_length())
    on = np.zeros(size, bool)
    on[(K.mix(u ^ _U(0x5851F42D4C957F2D)) & _U(size - 1)).astype(np.int64)] = True
    return np.packbits(on, bitorder="little").tobytes()


_ONES = np.array([bin(i).count("1") for i in range(256)], np.uint8)


def most_overlap(x: bytes, y: bytes, nx: int, ny: int) -> int:
    """Upper bound of the overlap of two sets from their bitmaps: a bit that one alone has is a shingle that the
    other lacks."""
    a, b = np.frombuffer(x, np.uint8), np.frombuffer(y, np.uint8)
    while len(a) > len(b):
        a = a[: len(a) // 2] | a[len(a) // 2 :]
    while len(b) > len(a):
        b = b[: len(b) // 2] | b[len(b) // 2 :]
    return min(nx - int(_ONES[a & ~b].sum()), ny - int(_ONES[b & ~a].sum()))


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (doc_id, n, s, bits; bits for one row of a class at least) and, at the end of a partition, the parts of
    its shingle counts."""
    size = 1 << SKETCH_BITS
    tally, waiting, held, seen = None, [], 0, set()

    def add() -> None:
        nonlocal tally, waiting, held
        if waiting:
            if tally is None:
                tally = np.zeros(size, np.uint32)
            at = np.sort((np.concatenate(waiting) >> _U(64 - SKETCH_BITS)).astype(np.int32))
            step = size // SKETCH_PARTS
            edges = np.searchsorted(at, np.arange(0, size + 1, step))
            for i, (a, b) in enumerate(zip(edges[:-1], edges[1:], strict=True)):
                tally[i * step : (i + 1) * step] += np.bincount(at[a:b] - i * step, minlength=step).astype(np.uint32)
            waiting, held = [], 0

    names = ["doc_id", "n", "s", "bits", "part", "counts"]
    for batch in batches:
        known = batch.column("doc_id").is_valid().to_pylist()
        for a, b, buf, off in text_parts(batch.column("text")):
            ns, ss, bits = np.zeros(b - a, np.int64), np.zeros(b - a, _U), [None] * (b - a)
            for i, u in enumerate(shingle_sets(buf, off)):
                if len(u):
                    ns[i], ss[i] = len(u), signature(u)
                    if known[a + i] and (key := int(ss[i])) not in seen:
                        if len(seen) < REMEMBERED:
                            seen.add(key)
                        bits[i] = bitmap(u)
                        waiting.append(u)
                        held += len(u)
            if held > 500_000:
                add()
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(a, b - a), pa.array(ns), pa.array(ss.view(np.int64)), pa.array(bits, pa.binary()), pa.nulls(len(ns), pa.int32()), pa.nulls(len(ns), pa.binary())], names)
    add()
    if tally is not None:
        for part, x in enumerate(np.split(tally, SKETCH_PARTS)):
            yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.nulls(1, pa.int64()), pa.nulls(1, pa.int64()), pa.nulls(1, pa.binary()), pa.array([part], pa.int32()), pa.array([zlib.compress(x.tobytes(), 1)], pa.binary())], names)


def _sum_counts(frame: pd.DataFrame) -> pd.DataFrame:
    total = None
    for raw in frame["counts"]:
        x = np.frombuffer(zlib.decompress(raw), np.uint32).astype(np.uint64)
        total = x if total is None else total + x
    return pd.DataFrame({"part": frame["part"].iloc[:1], "salt": [0], "counts": [zlib.compress(np.minimum(total, (1 << 32) - 1).astype(np.uint32).tobytes(), 1)]})


def frequent_buckets(counts: DataFrame, hot: int = HOT) -> np.ndarray:
    """Packed bits of the counter's buckets that hold frequent shingles, and of those with very frequent ones
    (two rows); SKETCH_BITS fixes their size."""
    total = np.zeros(1 << SKETCH_BITS, np.uint32)
    summed = counts.groupBy("part", "salt").applyInPandas(_sum_counts, "part int, salt int, counts binary").groupBy("part").applyInPandas(_sum_counts, "part int, salt int, counts binary")
    step = len(total) // SKETCH_PARTS
    for row in summed.toLocalIterator():
        total[row["part"] * step : (row["part"] + 1) * step] = np.frombuffer(zlib.decompress(bytes(row["counts"])), np.uint32)
    load = float(np.median(total))
    return np.stack([np.packbits(total > load + 5 * np.sqrt(load) + 6), np.packbits(total > load + 5 * np.sqrt(load) + hot)])


def band_edges(most: int = 1 << 40) -> list[int]:
    """Least sizes of the size bands: a set's partner is in its own band or in one beside it."""
    edges = [1]
    while edges[-1] < most:
        edges.append(edges[-1] * 4 // 3 + 1)
    return edges


_BANDS = np.array(band_edges())


def prefix_keys(u: np.ndarray, frequent: np.ndarray, hot: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(keys, limit of the overlap that is left if this is the first key in common, whether it is a pair of two
    ``hot`` shingles) of a set. A set of one shingle can only link with its own class."""
    hot = np.zeros(len(u), bool) if hot is None else hot
    n = len(u)
    need = n - (3 * n + 3) // 4 + 1
    rare = u[~frequent]
    keys = rare[:need]
    limits = n - np.arange(len(keys))
    if len(rare) >= need:
        return keys, limits, np.zeros(len(keys), bool)
    common, hot = u[frequent], hot[frequent]
    band = int(np.searchsorted(_BANDS, n, side="right")) - 1
    out, both_hot = [keys], [np.zeros(len(keys), bool)]
    for space in {band, max(band - 1, 0)}:
        groups = K.mix(common ^ _U(0xABCDEF)) % _U(max(1, int(_BANDS[space]) // 4))
        order = np.argsort(groups, kind="stable")
        first = np.ones(len(order), bool)
        first[1:] = groups[order][1:] != groups[order][:-1]
        opens = np.zeros(len(order), bool)
        opens[order[first]] = True  # a group's first shingle in the set's order counts nothing
        stop = int(np.searchsorted(np.cumsum(~opens), need - len(rare))) + 1
        member, group, heat = common[:stop], groups[:stop], hot[:stop]
        order = np.argsort(group, kind="stable")
        member, group, heat = member[order], group[order], heat[order]
        step = 1
        while step < len(member):
            same = group[step:] == group[:-step]
            if not same.any():
                break
            out.append(K.mix(member[:-step][same] * _U(3) + member[step:][same] + _U((space + 1) * 0x9E3779B97F4A7C15 % (1 << 64))))
            both_hot.append(heat[:-step][same] & heat[step:][same])
            step += 1
    combined = np.concatenate(out)
    return combined, np.concatenate([limits, np.full(len(combined) - len(keys), len(common))]), np.concatenate(both_hot)


def _need(a, b):
    """Least overlap of sets of sizes a and b with 100 * overlap >= 75 * union."""
    return (3 * (a + b) + 6) // 7


def _band(n: np.ndarray) -> np.ndarray:
    return np.searchsorted(_BANDS, n, side="right")


def _stars(s: np.ndarray, n: np.ndarray, lim: np.ndarray, group: np.ndarray, long: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each set in long lists, ``PIVOTS`` of its lists' heads at most, and heads of bands side by side. A list has
    a head for each size band: its most central set, that with the least share of rare shingles, and of those the one
    with the least hash, so that lists of one group of copies have few heads, and all buckets mostly the same."""
    if not len(long):
        return long, long
    part = group[long] * 256 + _band(n[long])
    order = np.lexsort((K.mix(s[long]), -(lim[long] * 64 // n[long]), part))
    by, first = long[order], np.ones(len(long), bool)
    first[1:] = part[order][1:] != part[order][:-1]
    heads, place = by[first], np.cumsum(first) - 1
    beside = np.flatnonzero((part[order][first][1:] == part[order][first][:-1] + 1))
    head, member = heads[place], by
    need = _need(n[head], n[member])
    ok = (head != member) & (np.minimum(lim[head], lim[member]) >= need) & (np.minimum(n[head], n[member]) >= need)
    head, member = head[ok], member[ok]
    order = np.lexsort((s[head], K.mix(s[head]), -(lim[head] * 64 // n[head]), s[member]))
    head, member = head[order], member[order]
    fresh = np.ones(len(member), bool)
    fresh[1:] = (s[member][1:] != s[member][:-1]) | (s[head][1:] != s[head][:-1])
    head, member = head[fresh], member[fresh]
    start = np.flatnonzero(np.append(True, s[member][1:] != s[member][:-1])) if len(member) else np.zeros(0, np.int64)
    turn = np.arange(len(member)) - np.repeat(start, np.diff(np.append(start, len(member))))
    return np.concatenate([head[turn < PIVOTS], heads[beside]]), np.concatenate([member[turn < PIVOTS], heads[beside + 1]])


def _bucket_pairs(table: pa.Table) -> pa.Table:
    """Candidates of one bucket. Rows with a null key are pairs (a, b, na, nb); others are entries
    (key, a: set, na: size, nb: limit) of long lists."""
    x = np.concatenate([np.frombuffer(b.as_buffer(), _ENTRY) for c in table.column("entries").chunks for b in c] or [np.zeros(0, _ENTRY)])
    k = x["k"]
    order = np.argsort(k)
    same = np.zeros(len(k) + 1, bool)
    same[1:-1] = k[order][1:] == k[order][:-1]
    x = x[order[same[1:] | same[:-1]]]
    x = x[np.lexsort((x["s"], x["n"], x["k"]))]
    if len(x):
        fresh = np.ones(len(x), bool)
        fresh[1:] = (x["k"][1:] != x["k"][:-1]) | (x["s"][1:] != x["s"][:-1])
        x = x[fresh]
    k, s, n, lim = x["k"], x["s"], x["n"].astype(np.int64), x["lim"].astype(np.int64)
    opens = np.ones(len(x), bool)
    opens[1:] = k[1:] != k[:-1]
    group = np.cumsum(opens) - 1
    size = np.bincount(group, minlength=1)[group] if len(x) else np.zeros(0, np.int64)
    lo, hi = ([x] for x in _stars(s, n, lim, group, np.flatnonzero(size > SHORT_LIST)))
    for d in range(1, SHORT_LIST):
        i = np.flatnonzero((group[d:] == group[:-d]) & (size[d:] <= SHORT_LIST)) if len(x) > d else np.zeros(0, np.int64)
        if not len(i):
            break
        lo.append(i)
        hi.append(i + d)
    i, j = np.concatenate(lo), np.concatenate(hi)
    need = _need(n[i], n[j])
    ok = (i != j) & (np.minimum(lim[i], lim[j]) >= need) & (np.minimum(n[i], n[j]) >= need)
    i, j = i[ok], j[ok]
    swap = s[i].view(np.int64) > s[j].view(np.int64)
    i, j = np.where(swap, j, i), np.where(swap, i, j)
    _, once = np.unique(K.mix(s[i]) + s[j], return_index=True)
    i, j = i[once], j[once]
    # of a long list, what can reach any of its sets
    least = np.minimum.reduceat(n, np.flatnonzero(opens))[group] if len(x) else size
    long = np.flatnonzero((size > SHORT_LIST) & (lim >= _need(n, np.maximum(least, (3 * n + 3) // 4))))
    si = s.view(np.int64) if len(x) else np.zeros(0, np.int64)
    return pa.table({
        "key": pa.concat_arrays([pa.nulls(len(i), pa.int64()), pa.array(k[long].view(np.int64) if len(long) else np.zeros(0, np.int64))]),
        "a": np.concatenate([si[i], si[long]]), "b": pa.concat_arrays([pa.array(si[j]), pa.nulls(len(long), pa.int64())]),
        "na": np.concatenate([n[i], n[long]]), "nb": np.concatenate([n[j], lim[long]]),
    })


def _compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by (a, salt), the pivot's row (null b) first."""
    pivot, pivot_of = None, None
    for batch in batches:
        a, b = batch.column("a").to_pylist(), batch.column("b").to_pylist()
        out_a, out_b = [], []
        for lo, hi, buf, off in text_parts(batch.column("text")):
            for i, u in enumerate(shingle_sets(buf, off), lo):
                if b[i] is None:
                    pivot, pivot_of = u, a[i]
                elif pivot_of == a[i]:
                    both = np.concatenate([pivot, u])
                    both.sort()
                    shared = int((both[1:] == both[:-1]).sum())
                    if 100 * shared >= 75 * (len(both) - shared):
                        out_a.append(a[i])
                        out_b.append(b[i])
        yield pa.RecordBatch.from_arrays([pa.array(out_a, pa.int64()), pa.array(out_b, pa.int64())], ["a", "b"])


def _possible(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The pairs whose bitmaps allow enough overlap."""
    for batch in batches:
        na, nb = batch.column("na").to_numpy(), batch.column("nb").to_numpy()
        x, y, need = batch.column("xa").to_pylist(), batch.column("xb").to_pylist(), _need(na, nb)
        keep = [i for i in range(batch.num_rows) if most_overlap(x[i], y[i], int(na[i]), int(nb[i])) >= need[i]]
        yield batch.select(["a", "b"]).take(pa.array(keep, pa.int64()))


def possible(pairs: DataFrame, classes: DataFrame) -> DataFrame:
    """The pairs (a, b), a written table, of which the bitmaps in ``classes`` (s, n, bits) allow a link."""
    needed = pairs.select(F.col("a").alias("s")).union(pairs.select("b")).distinct()
    few = pairs.limit(BROADCAST_IDS // 2 + 1).count() <= BROADCAST_IDS // 2
    bits = materialize(classes.select("s", "n", "bits").join(F.broadcast(needed) if few else needed, "s", "left_semi"), "jaccard-bits")
    side = [bits.select(F.col("s").alias(c), F.col("n").alias(f"n{c}"), F.col("bits").alias(f"x{c}")) for c in "ab"]
    out = materialize(pairs.join(side[0], "a").join(side[1], "b").mapInArrow(_possible, "a long, b long"), "jaccard-possible")
    discard(bits)
    return out


def verified(pairs: DataFrame, documents: DataFrame, classes: DataFrame, repeated: bool = True) -> DataFrame:
    """The pairs (a, b) of set signatures, a written table, whose sets overlap enough: those that their bitmaps
    allow, by their whole texts. ``repeated``: ids may stand on several rows."""
    pairs = possible(pairs, classes)
    if pairs.isEmpty():
        return pairs
    needed = materialize(pairs.select(F.col("a").alias("s")).union(pairs.select("b")).distinct().join(classes.select("s", "rep"), "s"), "jaccard-needed")
    few = needed.count() <= BROADCAST_IDS
    ids = needed.withColumnRenamed("rep", "doc_id")
    # an id may stand on several rows; the text's own signature tells which
    texts = documents.select("doc_id", "text").join(F.broadcast(ids) if few else ids, "doc_id")
    if repeated:
        texts = _signed(texts).where("s = own").dropDuplicates(["s"])
    texts = materialize(texts.select("s", "text"), "jaccard-texts")
    load = pairs.groupBy("a").agg(F.floor((F.count("*") - 1) / PIVOT_SHARE).cast("int").alias("last"))
    pivots = load.join(texts.withColumnRenamed("s", "a"), "a").select("a", F.explode(F.sequence(F.lit(0), F.col("last"))).alias("salt"), F.lit(None).cast("long").alias("b"), "text")
    members = pairs.select("a", "b").join(load, "a").select("a", F.pmod(F.hash("b"), F.col("last") + 1).alias("salt"), "b").join(texts.withColumnRenamed("s", "b"), "b").select("a", "salt", "b", "text")
    rows = pivots.unionByName(members)
    out = rows.repartition("a", "salt").sortWithinPartitions("a", "salt", F.col("b").asc_nulls_first()).select("a", "b", "text").mapInArrow(_compare, "a long, b long")
    out = materialize(out, "jaccard-links")
    discard(texts, needed, pairs)
    return out


def _signed(texts: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = np.zeros(batch.num_rows, _U)
            for lo, _, buf, off in text_parts(batch.column("text")):
                for i, u in enumerate(shingle_sets(buf, off), lo):
                    own[i] = signature(u) if len(u) else 0
            yield pa.RecordBatch.from_arrays([batch.column("s"), batch.column("text"), pa.array(own.view(np.int64))], ["s", "text", "own"])

    return texts.select("s", "text").mapInArrow(run, "s long, text string, own long")


def candidates(documents: DataFrame, total_keys: int, frequent: np.ndarray) -> tuple[DataFrame, DataFrame | None]:
    """(pairs and entries of long lists as ``_bucket_pairs`` gives them, entries (key, s, n, lim) of the lists of hot
    pairs of shingles, if there are any)."""
    spread = documents.sparkSession.sparkContext.broadcast(frequent)  # 2 * 2 ** SKETCH_BITS bits
    buckets = max(48, total_keys // BUCKET_KEYS)

    def index(hot_ones: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            waiting, held, seen = [], 0, set()

            def flush() -> pa.RecordBatch:
                x = np.concatenate(waiting)
                if hot_ones:
                    return pa.RecordBatch.from_arrays([pa.array(x["k"].view(np.int64)), pa.array(x["s"].view(np.int64)), pa.array(x["n"].astype(np.int64)), pa.array(x["lim"].astype(np.int64))], ["key", "s", "n", "lim"])
                at = ((x["k"] >> _U(32)) * _U(buckets) >> _U(32)).astype(np.int64)
                order = np.argsort(at, kind="stable")
                x, at = x[order], at[order]
                edges = np.append(np.flatnonzero(np.append(True, at[1:] != at[:-1])), len(at))
                return pa.RecordBatch.from_arrays([pa.array(at[edges[:-1]]), pa.array([x[p:q].tobytes() for p, q in zip(edges[:-1], edges[1:], strict=True)], pa.binary())], ["bucket", "entries"])

            for batch in batches:
                for _, _, buf, off in text_parts(batch.column("text")):
                    for u in shingle_sets(buf, off):
                        if len(u) < 2:
                            continue
                        s = signature(u)
                        if int(s) in seen:
                            continue
                        if len(seen) < REMEMBERED:
                            seen.add(int(s))
                        at = (u >> _U(64 - SKETCH_BITS)).astype(np.int64)
                        often, very = ((x[at >> 3] >> (7 - (at & 7)).astype(np.uint8) & 1).view(bool) for x in spread.value)
                        keys, limits, heat = prefix_keys(u, often, very)
                        keys, limits = keys[heat == hot_ones], limits[heat == hot_ones]
                        x = np.empty(len(keys), _ENTRY)
                        x["k"], x["s"], x["n"], x["lim"] = keys, s, len(u), limits
                        waiting.append(x)
                        held += len(x)
                    if held > 200_000:
                        yield flush()
                        waiting, held = [], 0
            if waiting:
                yield flush()

        return run

    texts = documents.select(F.coalesce("text", F.lit("")).alias("text"))
    found = texts.mapInArrow(index(False), "bucket long, entries binary").groupBy("bucket").applyInArrow(_bucket_pairs, "key long, a long, b long, na long, nb long")
    hot = texts.mapInArrow(index(True), "key long, s long, n long, lim long").distinct() if frequent[1].any() else None
    return found, hot


_LIST = ("s", "n", "lim", "root")


def _rooted(lists: DataFrame, edges: DataFrame) -> DataFrame:
    """Entries of the lists that still hold sets of different components, with their components' roots."""
    roots = components(edges).withColumnRenamed("node", "s")
    rooted = lists.join(roots, "s", "left").withColumn("root", F.coalesce("root", "s"))
    mixed = rooted.groupBy("key").agg(F.min("root").alias("r0"), F.max("root").alias("r1")).where("r0 <> r1").select("key")
    return materialize(rooted.join(mixed, "key").select("key", *_LIST), "jaccard-open")


def _need_of(n0: F.Column, n1: F.Column) -> F.Column:
    return F.floor((3 * (n0 + n1) + 6) / 7)


def _star_pairs(left: DataFrame, turn: int) -> DataFrame:
    """Each entry with a central set of its list, of its own size band or one beside it."""
    banded = left.withColumn("band", F.floor(F.log("n") / np.log(4 / 3)).cast("int"))
    central = F.struct(F.floor(F.col("lim") * 16 / F.col("n")), F.xxhash64("s", F.lit(turn)))
    heads = banded.groupBy("key", "band").agg(F.max_by(F.struct(*_LIST), central).alias("h"))
    heads = heads.select("key", F.explode(F.array(F.col("band") - 1, F.col("band"), F.col("band") + 1)).alias("band"), "h")
    reach = (F.col("h.root") != F.col("root")) & (F.least("h.lim", "lim", "h.n", "n") >= _need_of(F.col("h.n"), F.col("n")))
    return banded.join(heads, ["key", "band"]).where(reach).select(F.least("h.s", "s").alias("a"), F.greatest("h.s", "s").alias("b")).distinct()


def _rest_pairs(left: DataFrame) -> DataFrame:
    """Each entry outside its list's main component with all the others. The former meet the others as arrays of
    about ``GATHERED``, and a pair that shares many keys becomes a row once for each number of arrays of its lists."""
    roots = left.groupBy("key", "root").agg(F.count("*").alias("m"))
    main = roots.groupBy("key").agg(F.max_by("root", F.struct("m", "root")).alias("main"), (F.sum("m") - F.max("m")).alias("others"))
    parts = F.greatest(F.lit(1), F.pow(F.lit(2), F.ceil(F.log2(F.col("others") / GATHERED)))).cast("long")
    odd = left.join(main.withColumn("parts", parts), "key").where("root <> main").withColumn("part", F.pmod(F.xxhash64("s"), F.col("parts")))
    odd = odd.groupBy("key", "parts", "part").agg(F.collect_list(F.struct(*_LIST)).alias("odd"))
    reach = lambda o: (o.root != F.col("root")) & (F.least(o.lim, F.col("lim"), o.n, F.col("n")) >= _need_of(o.n, F.col("n")))
    met = left.join(odd, "key").select("s", "parts", "part", F.transform(F.filter("odd", reach), lambda o: o.s).alias("with")).where(F.size("with") > 0)
    met = met.groupBy("s", "parts", "part").agg(F.array_distinct(F.flatten(F.collect_list("with"))).alias("with"))
    return met.select("s", F.explode("with").alias("t")).select(F.least("s", "t").alias("a"), F.greatest("s", "t").alias("b")).distinct()


def _long_list_links(lists: DataFrame, edges: DataFrame, done: DataFrame, documents: DataFrame, classes: DataFrame, repeated: bool) -> DataFrame:
    """Links that long lists add. Only pairs whose ends are not yet in one component matter: ``STAR_ROUNDS`` stars,
    each list around others of its central sets, join most of what belongs together, and what is left is compared
    pair by pair, each pair once."""
    found = edges.limit(0)
    for turn in range(STAR_ROUNDS + 1):
        left = _rooted(lists, edges.unionByName(found))
        if left.isEmpty():
            break
        pairs = _star_pairs(left, turn) if turn < STAR_ROUNDS else _rest_pairs(left)
        pairs = materialize(pairs.join(done, ["a", "b"], "left_anti"), "jaccard-rest")
        if not pairs.isEmpty():
            found = found.unionByName(verified(pairs, documents, classes, repeated))
            done = done.unionByName(pairs)
        lists = left.drop("root")
    return found


def classes_and_edges(documents: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(rows: doc_id, n, s; classes: s, rep; links between classes: a, b), written tables."""
    sound = documents.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    scanned = materialize(sound.mapInArrow(_scan, "doc_id long, n long, s long, bits binary, part int, counts binary"), "jaccard-scan")
    rows = materialize(scanned.where("part is null").select("doc_id", "n", "s"), "jaccard-sets")
    frequent = frequent_buckets(scanned.where("part is not null").select("part", F.pmod(F.monotonically_increasing_id() / F.lit(1 << 33), F.lit(16)).cast("int").alias("salt"), "counts"))
    with_id = rows.where("n > 0 and doc_id is not null")
    of_class = scanned.where("n > 0 and doc_id is not null").groupBy("s", "n").agg(F.min("doc_id").alias("rep"), F.first("bits", ignorenulls=True).alias("bits"))
    classes = materialize(of_class, "jaccard-classes")
    discard(scanned)
    total = rows.agg(F.sum(F.floor(F.col("n") / 4) + 1)).first()[0] or 0
    met, hot = candidates(documents.where("doc_id is not null"), total, frequent)
    found = materialize(met, "jaccard-candidates")
    first = materialize(found.where("key is null").select("a", "b").distinct(), "jaccard-pairs")
    repeated = not with_id.groupBy("doc_id").agg(F.count("*").alias("rows")).where("rows > 1").isEmpty()
    edges = verified(first, documents, classes, repeated)
    lists = found.where("key is not null").select("key", F.col("a").alias("s"), F.col("na").alias("n"), F.col("nb").alias("lim"))
    lists = lists if hot is None else lists.unionByName(materialize(hot, "jaccard-hot"))
    edges = edges.unionByName(_long_list_links(lists, edges, first, documents, classes, repeated))
    discard(found)
    ids = with_id.select("doc_id", "s").distinct()
    twins = ids.join(ids.groupBy("doc_id").agg(F.min("s").alias("a"), F.max("s").alias("z")).where("a <> z"), "doc_id").where("s <> a").select("a", F.col("s").alias("b"))
    return rows, classes, edges.unionByName(twins)


def join_components(documents: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable by links), one row per row of ``documents``."""
    rows, classes, edges = classes_and_edges(documents)
    named = classes.join(components(edges).withColumnRenamed("node", "s"), "s", "left").withColumn("root", F.coalesce("root", "s"))
    least = named.groupBy("root").agg(F.min("rep").alias("component_id"))
    of_set = materialize(named.join(least, "root").select(F.col("s").alias("s2"), "component_id"), "jaccard-components")
    out = rows.join(of_set, (F.col("s") == F.col("s2")) & (F.col("n") > 0), "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id")).alias("component_id"))


def representatives(documents: DataFrame) -> DataFrame:
    """The rows of ``documents`` of which one per component stays (the one with the smallest doc_id), with all
    their columns, whatever their names. Texts without words and rows without an id stay."""
    found = materialize(join_components(documents), "jaccard-rows")
    gone = materialize(found.where("doc_id <> component_id").select(F.col("doc_id").alias("id")).distinct(), "jaccard-gone")
    few = gone.count() <= BROADCAST_IDS
    worded = F.coalesce(F.regexp_like("text", F.lit(r"[^\x20\x09-\x0D]")), F.lit(False))
    # the rows travel as structs, so that no column of theirs meets a name used here
    left = documents.select(F.col("doc_id").alias("id"), worded.alias("worded"), F.struct("*").alias("row")).join(F.broadcast(gone) if few else gone, "id", "left_anti")
    twice = materialize(found.where("n_shingles > 0").groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1 and doc_id is not null").select(F.col("doc_id").alias("id"), F.lit(True).alias("twice")), "jaccard-twice")
    if not twice.isEmpty():
        # rows that share their id: one with words stays
        mark = left.join(twice, "id", "left").withColumn("again", F.coalesce(F.col("twice") & F.col("worded"), F.lit(False)))
        left = mark.where(~F.col("again")).select("row").unionByName(mark.where("again").dropDuplicates(["id"]).select("row"))
    return left.select("row.*")
