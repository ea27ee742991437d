"""Cost formulas as columns over a table of sizes, and money from task logs."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class CostModel:
    """Seconds per message, per entry moved and per operation; memory of a worker in entries; dollars per 100 ms."""

    alpha: float = 1e-2
    beta: float = 1e-8
    gamma: float = 1e-10
    memory_entries: int = 48_000_000
    price_per_100ms: float = 0.000004897

    def worker_time(self, messages: Column, entries: Column, flops: Column) -> Column:
        return self.alpha * messages + self.beta * entries + self.gamma * flops

    def dollars(self, ms: Column) -> Column:
        """Each started 100 ms is paid."""
        return F.ceil(ms / 100) * F.lit(self.price_per_100ms)


def band_costs(t: DataFrame) -> DataFrame:
    """t(m, n, l, a): entries moved, messages, operations and tasks of the band product."""
    m, n, l, a = (F.col(c).cast("double") for c in "mnla")  # noqa: E741
    return t.withColumns({"band_entries": 2 * n * m * l / a + m * l, "band_messages": m * l / (a * a), "band_flops": m * n * l, "band_tasks": F.ceil(m / a) * F.ceil(l / a)})


def block_costs(t: DataFrame) -> DataFrame:
    """t(m, n, l, b): of the two phases of the block product."""
    m, n, l, b = (F.col(c).cast("double") for c in "mnlb")  # noqa: E741
    return t.withColumns({
        "block_compute_entries": 3 * n * m * l / b, "block_compute_messages": n * m * l / (b * b * b), "block_compute_tasks": F.ceil(m / b) * F.ceil(l / b) * F.ceil(n / b),
        "block_reduce_entries": n * m * l / b, "block_reduce_writes": m * l, "block_reduce_messages": n * m * l / (b * b * b), "block_reduce_tasks": F.ceil(m / b) * F.ceil(l / b), "block_flops": m * n * l,
    })


def rbs_costs(t: DataFrame) -> DataFrame:
    """t(m, l, b, z): tasks of sketching, computing and reducing."""
    m, l, b = (F.col(c).cast("double") for c in "mlb")  # noqa: E741
    slices = F.ceil(F.col("z") / F.col("b"))
    return t.withColumns({"rbs_sketch_tasks": (F.ceil(m / b) + F.ceil(l / b)) * slices, "rbs_compute_tasks": F.ceil(m / b) * F.ceil(l / b) * slices, "rbs_reduce_tasks": F.ceil(m / b) * F.ceil(l / b)})


def replicated_costs(t: DataFrame) -> DataFrame:
    """t(n, p, c): memory, entries moved and messages of each of p processors for an n x n product with c copies of the inputs, up to constants."""
    n, p, c = (F.col(x).cast("double") for x in ("n", "p", "c"))
    return t.withColumns({"memory_entries": c * n * n / p, "moved_entries": n * n / F.sqrt(c * p), "messages": F.sqrt(p / (c * c * c)) + F.log2(c)})


def work_per_task(n: Column) -> tuple[Column, Column]:
    """Operations of a task of the band (a = 1) and the block product (b = sqrt n) with memory 2n."""
    return n.cast("double"), F.pow(n.cast("double"), 1.5)


def dollars(log: DataFrame, model: CostModel) -> DataFrame:
    return log.agg(F.sum(F.ceil(F.col("t_ms") / 100)).alias("units"), (F.sum(F.ceil(F.col("t_ms") / 100)) * F.lit(model.price_per_100ms)).alias("dollars"))


def iteration_time(phase_ms: float, invoke_s: float = 9.0) -> float:
    return invoke_s + phase_ms / 1000


def saving(base: Column, other: Column) -> Column:
    return 1 - other / base
