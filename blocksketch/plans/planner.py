"""Sizes from accuracy, loss rate and memory, and the choice between products."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import functions as F

from ..operators.costs import CostModel
from ..operators.matrix import CoordMatrix


def plan_dimension(eps: float, theta: float | None = None, b: int = 1, rank: int = 1) -> tuple[int, int]:
    """(width, slices): d = 2 rank / (eps theta), or 2 rank / eps for the expected error, rounded up to blocks of b."""
    d = 2 * rank / (eps * (theta if theta is not None else 1))
    slices = math.ceil(round(d, 9) / b)
    return slices * b, slices


def plan_spares(slices: int, rate: float = 0.05, risk: float | None = None) -> int:
    """Spare slices for a loss rate: its share of the slices, or the fewest that lose more with probability at most `risk`."""
    if risk is None:
        return math.ceil(round(rate * slices, 9))
    e = 0
    while True:
        k = slices + e
        more = 1 - sum(math.comb(k, x) * rate**x * (1 - rate) ** (k - x) for x in range(e + 1))
        if more <= risk:
            return e
        e += 1


def plan_block(memory: float, n: int, convention: str = "inputs") -> tuple[float, float]:
    """(band height a, block side b) that fill a worker's memory of entries: inputs only (2an, 2b^2), or inputs and output (2an + a^2, 3b^2)."""
    if convention == "inputs":
        return memory / (2 * n), math.sqrt(memory / 2)
    return -n + math.sqrt(n * n + memory), math.sqrt(memory / 3)


@dataclass(frozen=True)
class Stats:
    """Sizes of a product of an m x n and an n x l matrix; nnz of each; products: entry pairs that share a contraction index."""

    m: int
    n: int
    l: int  # noqa: E741
    nnz_a: int
    nnz_b: int
    products: int


def stats(a: CoordMatrix, b: CoordMatrix) -> Stats:
    """One aggregate over the column counts of A joined to the row counts of B."""
    x = a.df.groupBy("c").agg(F.count("*").alias("x"))
    y = b.df.groupBy(F.col("i").alias("c")).agg(F.count("*").alias("y"))
    r = x.join(y, "c", "full").agg(F.sum("x"), F.sum("y"), F.sum(F.coalesce(F.col("x") * F.col("y"), F.lit(0)))).first()
    return Stats(a.rows, a.cols, b.cols, r[0] or 0, r[1] or 0, int(r[2] or 0))


def sketch_pays(s: Stats, slices: int, spares: int, b: int) -> bool:
    """Whether a sketched product does fewer multiplications than the exact sparse one, counting the sketching itself."""
    k = slices + spares
    row = lambda nnz, rows: b * (1 - (1 - 1 / b) ** (nnz / max(rows, 1)))
    z = k * b
    dense = s.m * s.l * z
    sparse = k * s.m * s.l * row(s.nnz_a, s.m) * row(s.nnz_b, s.l) / b
    return min(dense, sparse) + k * (s.nnz_a + s.nnz_b) < s.products


def plan_multiply(s: Stats, model: CostModel | None = None) -> str:
    """`band` where the result grows at least as the square of the contraction, where both coincide or one task suffices; else `block`."""
    model = model or CostModel()
    a, b = plan_block(model.memory_entries, s.n)
    if s.m * s.l >= s.n**2 or a >= min(s.m, s.l) or b >= max(s.m, s.l, s.n):
        return "band"
    return "block"


def plan_rectangular(m: int, n: int, l: int, memory: int, model: CostModel | None = None, steps: int = 24) -> tuple[int, int, int]:  # noqa: E741
    """Sides (p, q, r) of rectangular blocks with the least total cost under pq + qr + pr <= memory: a grid in the logarithm, refined around its best."""
    model = model or CostModel()

    def cost(p: float, q: float, r: float) -> float:
        tasks = (m / p) * (n / q) * (l / r)
        return tasks * (model.alpha * 3 + model.beta * (p * q + q * r + p * r) + model.gamma * p * q * r)

    top = (m, n, l)
    lo, hi = [0.0] * 3, [math.log(x) for x in top]
    best = (1.0, 1.0, 1.0)
    for _ in range(4):
        axes = [[math.exp(a + (b - a) * t / steps) for t in range(steps + 1)] for a, b in zip(lo, hi, strict=True)]
        fine = [(p, q, r) for p in axes[0] for q in axes[1] for r in axes[2] if p * q + q * r + p * r <= memory]
        best = min(fine, key=lambda x: cost(*x), default=best)
        for d in range(3):
            w = (hi[d] - lo[d]) / steps
            lo[d], hi[d] = max(0.0, math.log(best[d]) - w), min(math.log(top[d]), math.log(best[d]) + w)
    return tuple(max(1, math.floor(x + 1e-9)) for x in best)


def task_counts(m: int, n: int, l: int, b: int, z: int) -> dict[str, int]:  # noqa: E741
    up = lambda x, y: -(-x // y)
    cells, slices = up(m, b) * up(l, b), up(z, b)
    return {"sketch": (up(m, b) + up(l, b)) * slices, "compute": cells * slices, "reduce": cells, "exact_compute": cells * up(n, b)}
