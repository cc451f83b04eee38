"""Random numbers as functions of keys, alike in Spark, NumPy and SQL: they depend neither on partitions nor on order."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: The prime modulus, the start's multipliers and the constants of the three squaring rounds.
PRIME = 2147483647
KEY_FACTOR, STREAM_FACTOR, SEED_FACTOR, START = 48271, 16807, 69621, 12345
ROUNDS = (11, 101, 1009)


def hash_int(key: Column, stream: int | Column, seed: int) -> Column:
    stream = stream if isinstance(stream, Column) else F.lit(stream)
    k = F.pmod(key.cast("long"), F.lit(PRIME).cast("long"))
    u = F.pmod(k * KEY_FACTOR + stream.cast("long") * STREAM_FACTOR + F.lit(seed * SEED_FACTOR + START), F.lit(PRIME).cast("long"))
    for c in ROUNDS:
        u = F.pmod(u * u + k + F.lit(c), F.lit(PRIME).cast("long"))
    return u


def hash_uniform(key: Column, stream: int | Column, seed: int) -> Column:
    return (hash_int(key, stream, seed).cast("double") + F.lit(0.5)) / F.lit(float(PRIME))


def hash_normal(key: Column, stream: int | Column, seed: int) -> Column:
    """Standard normal, from the two uniforms of streams 2j and 2j + 1."""
    twice = stream * 2 if isinstance(stream, Column) else F.lit(2 * stream)
    return F.sqrt(F.lit(-2.0) * F.log(hash_uniform(key, twice, seed))) * F.cos(F.lit(2.0 * math.pi) * hash_uniform(key, twice + 1, seed))


def np_uniform(keys: np.ndarray, streams: np.ndarray | int, seed: int) -> np.ndarray:
    k = np.mod(np.asarray(keys, np.int64), PRIME)
    u = np.mod(k * KEY_FACTOR + np.asarray(streams, np.int64) * STREAM_FACTOR + seed * SEED_FACTOR + START, PRIME)
    for c in ROUNDS:
        u = np.mod(u * u + k + c, PRIME)
    return (u + 0.5) / PRIME


def np_normal(keys: np.ndarray, streams: np.ndarray, seed: int) -> np.ndarray:
    streams = np.asarray(streams, np.int64)
    return np.sqrt(-2 * np.log(np_uniform(keys, 2 * streams, seed))) * np.cos(2 * math.pi * np_uniform(keys, 2 * streams + 1, seed))
