"""Strategy of a factorization, from sizes alone, before any job runs.

A plan is a list of steps (operation, placement, scans of X, bytes that travel). ``explain`` prints it.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from ..operators.costs import flops, memory_floats

#: What the driver may hold of column-sized blocks.
DRIVER_BYTES = 1 << 30
#: What one block of columns may take there, of which it holds several beside their copies in transit.
COLUMN_BYTES = 64 << 20
#: Columns up to which X' X (8 n^2 bytes per partition) is worth a scan.
GRAM_COLUMNS = 4096


def choose_route(n: int, s: int, w: int) -> str:
    """"gram": two scans whatever w; "iterate": w + 3 scans and n x s blocks only."""
    return "gram" if n <= GRAM_COLUMNS and 8 * n * n <= DRIVER_BYTES else "iterate"


def choose_placement(d: int, n: int, k: int, s: int, budget: int = DRIVER_BYTES // 4) -> str:
    """"driver" where the compressed state fits one machine, so that iterations cost no jobs."""
    return "driver" if 8 * memory_floats("cgram_hals", d, n, k, s) <= budget else "distributed"


def choose_column_side(n: int, k: int, s: int) -> str:
    """"driver" where each of several blocks of columns is small enough for it, else "tables"."""
    return "driver" if 8 * n * max(k, s) <= COLUMN_BYTES else "tables"


@dataclass(frozen=True)
class Step:
    operation: str
    placement: str
    scans: int
    bytes_moved: float


@dataclass
class MatrixPlan:
    method: str
    d: int
    n: int
    k: int
    s: int
    w: int
    iterations: int
    partitions: int
    steps: list[Step] = field(default_factory=list)

    @classmethod
    def build(cls, method: str, d: int, n: int, k: int, s: int, w: int, iterations: int, partitions: int = 200) -> MatrixPlan:
        plan = cls(method, d, n, k, s, w, iterations, partitions)
        compressed = method.startswith("c")
        if compressed:
            route = choose_route(n, s, w)
            plan.steps.append(Step(f"project ({route})", "distributed", 2 if route == "gram" else w + 3, 8.0 * partitions * (n * n if route == "gram" else n * s * (w + 1))))
        place = choose_placement(d, n, k, s) if compressed else "distributed"
        each = 16.0 * s * k * partitions if compressed else 8.0 * n * k * partitions
        jobs = 2 * k if method in ("hals", "chals") else 2
        plan.steps.append(Step(f"{iterations} x {method}, {jobs} jobs each", place, 0 if compressed else 2 * iterations, 0.0 if place == "driver" else each * iterations))
        return plan

    def scans(self) -> int:
        return sum(s.scans for s in self.steps)

    def explain(self) -> str:
        head = f"{self.method}: d={self.d} n={self.n} k={self.k} s={self.s} w={self.w}, {flops(self.method, self.d, self.n, self.k, self.s):.3g} flops an iteration, {memory_floats(self.method, self.d, self.n, self.k, self.s):.3g} floats"
        return "\n".join([head, *(f"  {s.operation}: {s.placement}, {s.scans} scans of X, {s.bytes_moved:.3g} bytes moved" for s in self.steps)])
