"""Count-sketches, alone and stacked: K = N + e independent slices of width b in place of the contraction index."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import HashFamily, P
from .matrix import CoordMatrix


def stacked_sketch(a: CoordMatrix, b: int, family: HashFamily, chosen: list[int] | None = None) -> DataFrame:
    """(i, k, h, v): the unscaled sketch of each row. Entries of a row meet in a map-side sum before the only exchange."""
    e = a.df.select("i", F.inline(family.entries(F.col("c"), F.col("v"), b, chosen)))
    return e.groupBy("i", "k", "h").agg(F.sum("sv").alias("v"))


def sketch_right(a: CoordMatrix, b: int, family: HashFamily) -> DataFrame:
    """(k, h, j, v): the same family applied from the left to a matrix whose rows are the contraction index."""
    e = a.df.select(F.col("c").alias("j"), F.inline(family.entries(F.col("i"), F.col("v"), b)))
    return e.groupBy("k", "h", "j").agg(F.sum("sv").alias("v"))


def count_sketch(a: CoordMatrix, b: int, seed: int = 42, k: int = 0) -> DataFrame:
    """(i, h, v): one slice."""
    return stacked_sketch(a, b, HashFamily(k + 1, seed), [k]).drop("k")


def mapped_sketch(a: CoordMatrix, mapping: DataFrame) -> DataFrame:
    """(i, h, v) under an explicit mapping(c, h, s) of columns to buckets and signs."""
    return a.df.join(mapping, "c").groupBy("i", "h").agg(F.sum(F.col("v") * F.col("s")).alias("v"))


def located_sketch(a: CoordMatrix, b: int, family: HashFamily) -> DataFrame:
    """As stacked_sketch with double entries, by tasks of one row block: entries are dealt by row block once, and each task adds them, batch after
    batch, into a b x K*b accumulator, so what moves is nnz(A) and never K times that, and memory is bounded by the accumulator."""
    slices, seed = family.slices, family.seed

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        u = np.array(HashFamily(slices, seed).rows, np.int64)
        acc: dict[int, np.ndarray] = {}
        for pdf in batches:
            c, v = pdf["c"].to_numpy(np.int64), pdf["v"].to_numpy(float)
            i = pdf["i"].to_numpy(np.int64)
            for k, u1, u0, w3, w2, w1, w0 in u.tolist():
                h = ((u1 * c + u0) % P) % b
                q = w3 * c % P
                q = ((q + w2) % P) * c % P
                q = ((q + w1) % P) * c % P
                s = 1 - 2 * (((q + w0) % P) % 2)
                for bi in np.unique(i // b):
                    at = i // b == bi
                    block = acc.setdefault(int(bi), np.zeros((b, slices * b)))
                    np.add.at(block, (i[at] % b, k * b + h[at]), s[at] * v[at])
        for bi, block in acc.items():
            r, z = np.nonzero(block)
            yield pd.DataFrame({"i": bi * b + r, "k": (z // b).astype(np.int32), "h": (z % b).astype(np.int32), "v": block[r, z]})

    dealt = a.df.withColumn("bi", F.floor(F.col("i") / b)).repartition("bi").sortWithinPartitions("bi").select("i", "c", "v")
    return dealt.mapInPandas(run, "i long, k int, h int, v double")


def sketch_tasks(rows: int, b: int, family: HashFamily) -> int:
    """Tasks of the distributed sketch: one per row block and slice."""
    return -(-rows // b) * family.slices
