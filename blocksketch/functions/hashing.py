"""The hash family: per slice a pairwise bucket and a four-wise sign, polynomials modulo 2^31 - 1 in BIGINT arithmetic.

Indices must lie in [0, 2^31 - 1). The same text runs in Spark and in any SQL engine with 64-bit integers."""

from __future__ import annotations

import random
from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

P = 2**31 - 1


@dataclass(frozen=True)
class HashFamily:
    """`slices` independent hash pairs drawn from `seed`."""

    slices: int
    seed: int = 42

    @cached_property
    def rows(self) -> list[tuple[int, ...]]:
        """(k, u1, u0, w3, w2, w1, w0) of each slice."""
        out = []
        for k in range(self.slices):
            draw = random.Random(f"{self.seed}:{k}")
            out.append((k, *(draw.randint(1, P - 1) for _ in range(6))))
        return out

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, "k int, u1 long, u0 long, w3 long, w2 long, w1 long, w0 long")

    def values_sql(self) -> str:
        """The family as a SQL table `fam`."""
        return "fam(k, u1, u0, w3, w2, w1, w0) AS (VALUES " + ", ".join(f"({', '.join(f'CAST({x} AS {t})' for x, t in zip(r, ['INT', *['BIGINT'] * 6], strict=True))})" for r in self.rows) + ")"

    def bucket(self, c: Column, k: int, width: int) -> Column:
        _, u1, u0, *_ = self.rows[k]
        return (((F.lit(u1) * c + F.lit(u0)) % P) % width).cast("int")

    def sign(self, c: Column, k: int) -> Column:
        _, _, _, *w = self.rows[k]
        q = F.lit(w[0]) * c % P
        for x in w[1:3]:
            q = ((q + F.lit(x)) % P) * c % P
        return (F.lit(1) - F.lit(2) * (((q + F.lit(w[3])) % P) % 2)).cast("long")

    def entries(self, c: Column, v: Column, width: int, chosen: list[int] | None = None) -> Column:
        """Array of (k, h, sv): what an entry v in column c adds to each slice."""
        c = c.cast("long")
        return F.array(*[F.struct(F.lit(k).alias("k"), self.bucket(c, k, width).alias("h"), (self.sign(c, k) * v).alias("sv")) for k in (chosen if chosen is not None else range(self.slices))])


def bucket_sql(c: str, width: int) -> str:
    return f"CAST(((u1 * {c} + u0) % {P}) % {width} AS INT)"


def sign_sql(c: str) -> str:
    q = f"(w3 * {c}) % {P}"
    for w in ("w2", "w1"):
        q = f"((({q} + {w}) % {P}) * {c}) % {P}"
    return f"CAST(1 - 2 * ((({q} + w0) % {P}) % 2) AS BIGINT)"
