"""Task logs and the policies that decide which slices of each output cell are waited for.

A log has a row (bi, bj, k, t_ms, status) per compute task. Losses never depend on the sketch: the log has a seed of its own."""

from __future__ import annotations

import random
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.hashing import P

CELL = ("bi", "bj")


#: In Spark a row number is an INT, and 20001 times one overflows beyond 107374 tasks.
_SPARK_PLACE = "CAST(row_number() {over} AS BIGINT)"


def log_sql(bi: int, bj: int, k: int, seed: int = 1, source: str | None = None) -> str:
    """SQL for a log of bi x bj x k tasks, in Spark and DuckDB alike: of 3000 jobs two take 375 s, 5 % about 100 s, the others 30 to 50 s.

    Jobs are ranked by a hash and quotas follow the rank, so the profile is exact."""
    if source:
        return _log_text(bi, bj, k, _draws(seed), source)
    cells = f"SELECT CAST(a.i AS INT) AS bi, CAST(b.i AS INT) AS bj, CAST(c.i AS INT) AS k FROM {_series(bi)} a CROSS JOIN {_series(bj)} b CROSS JOIN {_series(k)} c"
    return _log_text(bi, bj, k, _draws(seed), cells, place=_SPARK_PLACE)


def _draws(seed: int) -> list[int]:
    draw = random.Random(f"log:{seed}")
    return [draw.randint(1, P - 1) for _ in range(4)]


def _log_text(bi: int, bj: int, k: int, w: list, cells: str, key: str = "", place: str = "row_number() {over}") -> str:
    """The log over `cells`; with a key, one log for each of its values. w: the numbers of the hash, or columns of them."""
    x = f"((CAST(bi AS BIGINT) * 1000003 + bj * 1009 + k) % {P})"
    q = f"({w[0]} * {x}) % {P}"
    for y in w[1:3]:
        q = f"((({q} + {y}) % {P}) * {x}) % {P}"
    total, out, slow = bi * bj * k, 2 * bi * bj * k // 3000, bi * bj * k * 5 // 100
    rest = max(total - slow, 1)
    by = f"({q} + {w[3]}) % {P}, bi, bj, k"
    first, part = (f"{key}, ", f"PARTITION BY {key} ") if key else ("", "")
    number = place.format(over=f"OVER ({part}ORDER BY {by})")
    return f"""SELECT {first}bi, bj, k, CAST(CASE WHEN r < {out} THEN 375000 WHEN r < {slow} THEN 95000 + (r * 7919) % 10001
      ELSE 30000 + CAST(floor(((r - {slow}) * 20001) / {rest}) AS BIGINT) END AS BIGINT) AS t_ms, 'done' AS status
    FROM (SELECT {first}bi, bj, k, {number} - 1 AS r FROM ({cells}) AS cells) AS ranked"""


def _series(n: int) -> str:
    return f"(SELECT explode(sequence(0, {n - 1})) AS i)"


def task_log(spark: SparkSession, bi: int, bj: int, k: int, seed: int = 1) -> DataFrame:
    """The log; metadata of as many rows as tasks, ranked in one task."""
    return spark.sql(log_sql(bi, bj, k, seed))


def task_logs(spark: SparkSession, bi: int, bj: int, k: int, seeds: list[int]) -> DataFrame:
    """The logs of many seeds in one DataFrame, with the seed as `run`."""
    values = ", ".join(f"({s}, {', '.join(f'CAST({x} AS BIGINT)' for x in _draws(s))})" for s in seeds)
    cells = f"SELECT run, w0, w1, w2, w3, CAST(a.i AS INT) AS bi, CAST(b.i AS INT) AS bj, CAST(c.i AS INT) AS k FROM {_series(bi)} a CROSS JOIN {_series(bj)} b CROSS JOIN {_series(k)} c CROSS JOIN (VALUES {values}) AS runs(run, w0, w1, w2, w3)"
    return spark.sql(_log_text(bi, bj, k, ["w0", "w1", "w2", "w3"], cells, "run", _SPARK_PLACE))


def log_duck(bi: int, bj: int, k: int, seed: int = 1) -> str:
    cells = f"SELECT CAST(a.i AS INT) AS bi, CAST(b.i AS INT) AS bj, CAST(c.i AS INT) AS k FROM range(0, {bi}) a(i) CROSS JOIN range(0, {bj}) b(i) CROSS JOIN range(0, {k}) c(i)"
    return log_sql(bi, bj, k, seed, cells)


@dataclass(frozen=True)
class Policy:
    """kind: all, first (n earliest), drop (all but the n slowest), deadline (t up to n ms, or the least earliest), each by cell, or
    shared (one set of n slices for all cells, by their slowest cell). Failed tasks never survive."""

    kind: str
    n: int = 0
    least: int = 1


def ranked(log: DataFrame, cell: tuple[str, ...] = CELL) -> DataFrame:
    """Tasks that ended, with rank by time within their cell (then by slice) and the cell's number of tasks."""
    by = W.partitionBy(*cell)
    done = log.filter("status = 'done'")
    return done.withColumn("rank", F.row_number().over(by.orderBy("t_ms", "k"))).withColumn("tasks", F.count("*").over(by))


def survivors(log: DataFrame, policy: Policy) -> DataFrame:
    """(bi, bj, k, t_ms) of the slices that count in each cell."""
    if policy.kind == "shared":
        slowest = log.groupBy("k").agg(F.max(F.when(F.col("status") == "done", F.col("t_ms")).otherwise(F.lit(2**62))).alias("worst"))
        chosen = slowest.filter(F.col("worst") < 2**62).withColumn("r", F.row_number().over(W.orderBy("worst", "k"))).filter(F.col("r") <= policy.n)
        return log.join(F.broadcast(chosen.select("k")), "k").select(*CELL, "k", "t_ms")
    r = ranked(log)
    if policy.kind == "first":
        r = r.filter(F.col("rank") <= policy.n)
    elif policy.kind == "drop":
        r = r.filter(F.col("rank") <= F.col("tasks") - policy.n)
    elif policy.kind == "deadline":
        r = r.filter((F.col("t_ms") <= policy.n) | (F.col("rank") <= policy.least))
    elif policy.kind != "all":
        raise ValueError(policy.kind)
    return r.select(*CELL, "k", "t_ms")


def speculated(log: DataFrame, multiple: float = 1.5, seed: int = 9) -> DataFrame:
    """Each task is started again at multiple * median; the faster of the two counts."""
    median = log.agg(F.percentile("t_ms", 0.5).alias("median"))
    fresh = 30000 + F.pmod(F.lit(seed) * 104729 + F.col("bi") * 7919 + F.col("bj") * 104723 + F.col("k") * 1299709, F.lit(20001))
    again = F.floor(F.col("median") * multiple).cast("long") + fresh
    return log.crossJoin(F.broadcast(median)).select(*CELL, "k", F.least("t_ms", again).alias("t_ms"), "status")


def phase_time(chosen: DataFrame) -> DataFrame:
    """One row, phase_ms: when the last cell has all it waits for."""
    return chosen.agg(F.max("t_ms").alias("phase_ms"))


def sketch_losses(log: DataFrame, lost: DataFrame) -> DataFrame:
    """The log without tasks whose sketch blocks were lost: lost(side, block, k), side a for row blocks and b for column blocks."""
    a = lost.filter("side = 'a'").select(F.col("block").alias("bi"), "k")
    b = lost.filter("side = 'b'").select(F.col("block").alias("bj"), "k")
    return log.join(F.broadcast(a), ["bi", "k"], "left_anti").join(F.broadcast(b), ["bj", "k"], "left_anti").select("bi", "bj", "k", "t_ms", "status")


def profile(log: DataFrame, multiple: float = 2.0) -> DataFrame:
    """Median, share beyond multiple of the median, and maximum of job times."""
    median = log.agg(F.percentile("t_ms", 0.5).alias("median"))
    return log.crossJoin(F.broadcast(median)).agg(F.max("median").alias("median_ms"), F.avg((F.col("t_ms") > multiple * F.col("median")).cast("double")).alias("share_slow"), F.max("t_ms").alias("max_ms"), F.count("*").alias("tasks"))
