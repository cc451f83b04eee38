"""Mixture-controlled packing (7): deficit round-robin over source queues into windows of sequences.

Every source is a queue of documents. In each round a queue is granted its share of a window's tokens
and sends documents as long as its credit covers the start of the next one; what it overdraws counts
against its next rounds, in whatever partition those are. With constant shares a document's round
follows from the tokens before it in its queue, so rounds need prefix sums and no loop: the fluid
schedule F(v) = sum over queues of min(queue, share * v) is linear between the points at which a queue
runs dry, and a document with c tokens before it joins window floor(F(c / share) / window). Windows
follow one another without gaps, sequences are cut from that stream at every ``length`` tokens, and so
only the last sequence can need padding.

Defined cases: a null text is empty and has one token, the closing id; a null source is a queue of its
own; null ids and repeated rows are documents like others; an empty table gives no pieces; a text of any
length is cut over as many sequences as it needs. Extra columns are ignored. The table of sources is held on the driver: more than ``MAX_SOURCES`` raise an error.
"""

from __future__ import annotations

import base64
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .shared import materialize, release

LENGTH = 2048
#: Sequences in a window.
WINDOW_SEQUENCES = 64
CLOSING_ID = 1
MAX_SOURCES = 1_000_000
#: Documents in one stretch of a queue, about; a stretch is put in order by one task.
STRETCH = 2000

#: A run of this many blanks is beyond the fast tokenizer; its text goes to the reference one.
LONG_BLANK = re.compile(r"\s{2000}")

_encoders: dict[int, object] = {}


def _encoder(ranks_file: bytes, pattern: str, special: dict[str, int]):
    key = hash((len(ranks_file), ranks_file[:64], ranks_file[-64:]))
    if key not in _encoders:
        import tiktoken

        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, ranks_file.splitlines())}
        _encoders[key] = tiktoken.Encoding("packing", pat_str=pattern, mergeable_ranks=ranks, special_tokens=special)
    return _encoders[key]


def _reference(model: bytes):
    key = hash(("reference", len(model), model[-64:]))
    if key not in _encoders:
        import tokenizers

        _encoders[key] = tokenizers.Tokenizer.from_str(model.decode())
    return _encoders[key]


def tokenized(documents: DataFrame, ranks_path: str, pattern: str, special: dict[str, int], model_path: str, closing_id: int = CLOSING_ID) -> DataFrame:
    """(rid, doc_id, source, doc_tokens, ids): ids as little-endian uint32, with the closing id. Both files hold the
    same vocabulary."""
    read = []
    for path in (ranks_path, model_path):  # parts of the installation, on the driver; workers get their bytes
        with open(path, "rb") as f:
            read.append(documents.sparkSession.sparkContext.broadcast(f.read()))
    spread, model = read

    def encoded(encoder, text: str) -> list[int]:
        if LONG_BLANK.search(text):
            return _reference(model.value).encode(text, add_special_tokens=False).ids
        return encoder.encode(text, allowed_special="all")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _encoder(spread.value, pattern, special)
        for batch in batches:
            texts, n = batch.column("text"), batch.num_rows
            for a in range(0, n, 128):
                ids = [np.array([*encoded(encoder, t), closing_id], np.uint32) for t in texts.slice(a, 128).to_pylist()]
                part = batch.slice(a, 128)
                yield pa.RecordBatch.from_arrays([part.column("rid"), part.column("doc_id"), part.column("source"), pa.array([len(x) for x in ids], pa.int64()), pa.array([x.astype("<u2" if not len(x) or x.max() < 65536 else "<u4").tobytes() for x in ids], pa.binary())], ["rid", "doc_id", "source", "doc_tokens", "packed"])
            release()

    return documents.select(F.monotonically_increasing_id().alias("rid"), "doc_id", "source", F.coalesce("text", F.lit("")).alias("text")).mapInArrow(run, "rid long, doc_id long, source string, doc_tokens long, packed binary")


def positions(docs: DataFrame, window_tokens: int, targets: dict[str | None, float] | None = None) -> DataFrame:
    """(rid, position): where each document starts in the stream. ``docs``: rid, source, doc_tokens, a written
    table. ``targets``: shares by source; by default the sources' own token shares, with which all queues run
    dry together and every window has the corpus's proportions."""
    sources = docs.groupBy("source").agg(F.sum("doc_tokens").alias("tokens"), F.count("*").alias("n")).limit(MAX_SOURCES + 1).collect()
    if len(sources) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources")
    total, rows = sum(r["tokens"] for r in sources), sum(r["n"] for r in sources)
    share = {r["source"]: (targets or {}).get(r["source"], 0.0) if targets else r["tokens"] / max(total, 1) for r in sources}
    least = min((x for x in share.values() if x > 0), default=1.0) * 1e-6
    share = {k: max(x, least) for k, x in share.items()}  # a source without a target comes last
    dry = sorted((r["tokens"] / share[r["source"]], r["source"] or "", r["tokens"], share[r["source"]]) for r in sources)
    at, served, done, open_share = [0.0], [0.0], 0.0, sum(share.values())
    for v, _, tokens, s in dry:
        served.append(done + v * open_share)
        at.append(v)
        done, open_share = done + tokens, open_share - s
    knots = docs.sparkSession.sparkContext.broadcast((np.array(at), np.array(served)))

    @F.pandas_udf("long")
    def round_of(v: pd.Series) -> pd.Series:
        x, y = knots.value
        return pd.Series((np.interp(v.to_numpy(), x, y) // window_tokens).astype(np.int64))

    shares = docs.sparkSession.createDataFrame([(k, float(x)) for k, x in share.items()], "of string, share double")
    stretches = max(1, min(1 << 20, rows // STRETCH))
    d = docs.select("rid", "source", "doc_tokens").withColumn("stretch", F.pmod(F.xxhash64("rid"), F.lit(stretches)))
    heads = d.groupBy("source", "stretch").agg(F.sum("doc_tokens").alias("all")).withColumn("head", F.sum("all").over(Window.partitionBy("source").orderBy("stretch")) - F.col("all"))
    heads = heads.select(F.col("source").alias("of2"), F.col("stretch").alias("s2"), "head")
    inside = Window.partitionBy("source", "stretch").orderBy("rid")
    d = d.withColumn("before", F.sum("doc_tokens").over(inside) - F.col("doc_tokens"))
    d = d.join(heads, (F.col("stretch") == F.col("s2")) & F.col("source").eqNullSafe(F.col("of2"))).join(F.broadcast(shares), F.col("source").eqNullSafe(F.col("of")))
    d = materialize(d.select("rid", "source", "doc_tokens", (F.col("before") + F.col("head")).alias("queued"), round_of((F.col("before") + F.col("head")) / F.col("share")).alias("window")), "pack-rounds")
    sizes = d.groupBy("window").agg(F.sum("doc_tokens").alias("all")).withColumn("block", F.shiftright("window", 12))
    blocks = sizes.groupBy("block").agg(F.sum("all").alias("of_block"))
    blocks = blocks.select(F.col("block").alias("b2"), (F.sum("of_block").over(Window.partitionBy(F.lit(0)).orderBy("block")) - F.col("of_block")).alias("block_head"))
    starts = sizes.withColumn("in_block", F.sum("all").over(Window.partitionBy("block").orderBy("window")) - F.col("all")).join(blocks, F.col("block") == F.col("b2"))
    starts = starts.select(F.col("window").alias("w2"), (F.col("in_block") + F.col("block_head")).alias("window_head"))
    turn = Window.partitionBy("window").orderBy("source", "queued")
    return d.withColumn("in_window", F.sum("doc_tokens").over(turn) - F.col("doc_tokens")).join(starts, F.col("window") == F.col("w2")).select("rid", "window", (F.col("in_window") + F.col("window_head")).alias("position"))


def pack(documents: DataFrame, ranks_path: str, pattern: str, special: dict[str, int], model_path: str, length: int = LENGTH, window_sequences: int = WINDOW_SEQUENCES, targets: dict[str | None, float] | None = None, closing_id: int = CLOSING_ID) -> DataFrame:
    """Pieces: doc_id, start, length, doc_tokens, sequence_id, offset, window, ids (little-endian uint32)."""
    docs = materialize(tokenized(documents, ranks_path, pattern, special, model_path, closing_id), "pack-ids")
    placed = positions(docs, length * window_sequences, targets)
    joined = docs.join(placed.hint("shuffle_hash"), "rid")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                part = batch.slice(a, 256)
                n, pos = part.column("doc_tokens").to_numpy(), part.column("position").to_numpy()
                count = (pos + n - 1) // length - pos // length + 1
                doc = np.repeat(np.arange(len(n)), count)
                k = np.arange(len(doc)) - np.repeat(np.cumsum(count) - count, count)
                sequence = pos[doc] // length + k
                begin = np.maximum(sequence * length, pos[doc])
                end = np.minimum((sequence + 1) * length, pos[doc] + n[doc])
                raw = part.column("packed").to_pylist()
                ids = [np.frombuffer(x, "<u2" if len(x) == 2 * m else "<u4") for x, m in zip(raw, n, strict=True)]
                start = begin - pos[doc]
                pieces = [ids[d][s : s + m].astype("<u4").tobytes() for d, s, m in zip(doc, start, end - begin, strict=True)]
                take = pa.array(doc)
                yield pa.RecordBatch.from_arrays([part.column("doc_id").take(take), pa.array(start), pa.array(end - begin), part.column("doc_tokens").take(take), pa.array(sequence), pa.array(begin - sequence * length), part.column("window").take(take), pa.array(pieces, pa.binary())], ["doc_id", "start", "length", "doc_tokens", "sequence_id", "offset", "window", "ids"])
            release()

    return joined.select("doc_id", "doc_tokens", "position", "window", "packed").mapInArrow(cut, "doc_id long, start long, length long, doc_tokens long, sequence_id long, offset long, window long, ids binary")


def packed_public(documents: DataFrame) -> DataFrame:
    """The pieces with the public byte-level BPE vocabulary."""
    import public_tokenizers

    pieces = pack(documents, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, {"<|endoftext|>": 50256}, public_tokenizers.path("byte_bpe_50k.json"))
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset", "ids")


def packed_digests(documents: DataFrame) -> DataFrame:
    """The same with the ids' checksum only."""
    return packed_public(documents).drop("ids")
