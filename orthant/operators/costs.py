"""Cost models: operations and memory of one iteration, by method and sizes, and the published measurements."""

from __future__ import annotations

#: Published per-update measurements (flops in millions, seconds, memory in floats) of two sets:
#: dense d=400 n=4096 k=20 s=25, sparse d=5000 n=1000 k=60 s=72.
PUBLISHED = (
    ("dense", "mu", 270.0, 0.031, 1700000.0),
    ("dense", "cmu", 13.0, 0.023, 310000.0),
    ("dense", "hals", 260.0, 0.332, 1700000.0),
    ("dense", "chals", 3200.0, 0.575, 310000.0),
    ("dense", "gram_hals", 14.0, 0.035, 1700000.0),
    ("dense", "cgram_hals", 8.6, 0.023, 310000.0),
    ("sparse", "mu", 2400.0, 0.068, 5300000.0),
    ("sparse", "cmu", 150.0, 0.048, 1200000.0),
    ("sparse", "hals", 2400.0, 2.678, 5300000.0),
    ("sparse", "chals", 430000.0, 4.775, 1200000.0),
    ("sparse", "gram_hals", 1300.0, 0.069, 5300000.0),
    ("sparse", "cgram_hals", 98.0, 0.047, 1200000.0),
)
SHAPES = {"dense": (400, 4096, 20, 25), "sparse": (5000, 1000, 60, 72)}
#: k and s of the published sets, whose kinds the matrices of the given tables stand for.
RANKS = {kind: shape[2:] for kind, shape in SHAPES.items()}
METHODS = ("mu", "hals", "gram_hals", "cmu", "chals", "cgram_hals")


def flops(method: str, d: int, n: int, k: int, s: int, model: str = "theory") -> float:
    """Sizes are numbers or columns. ``theory``: leading terms, one side; ``counted``: both sides and the Gram terms of the compressed forms."""
    if model == "counted" and method in ("cmu", "cgram_hals"):
        return 2.0 * (d + n) * k * ((2 * s if method == "cmu" else s) + k)
    return {"mu": 8.0 * d * n * k, "hals": 8.0 * d * n * k, "gram_hals": 4.0 * d * n * k, "cmu": 4.0 * d * k * s, "chals": 4.0 * d * n * k * s, "cgram_hals": 2.0 * d * k * s}[method]


def memory_floats(method: str, d: int, n: int, k: int, s: int) -> float:
    return 1.0 * (2 * s + k) * (d + n) if method.startswith("c") else 1.0 * d * n + d * k + n * k


def bytes_reduced(method: str, n: int, k: int, s: int, partitions: int) -> float:
    """Bytes that one iteration sends between nodes: two s x k partial sums of every partition, or n x k ones."""
    return 16.0 * s * k * partitions if method.startswith("c") else 8.0 * n * k * partitions
