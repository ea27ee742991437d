"""Connected components of an edge table."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Kept, released


@released
def forest(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Edges (u, v) of one task to a spanning forest of stars: each node with the smallest node it reaches here."""
    up: dict[int, int] = {}

    def root(x: int) -> int:
        while (y := up.get(x, x)) != x:
            up[x] = up.get(y, y)
            x = y
        return x

    for pdf in batches:
        for a, b in zip(pdf["u"].tolist(), pdf["v"].tolist(), strict=True):
            a, b = root(a), root(b)
            up[max(a, b)] = up[min(a, b)] = min(a, b)
    yield pd.DataFrame({"u": (u := [x for x in up if root(x) != x]), "v": [root(x) for x in u]}, dtype="int64")


def components(edges: DataFrame, kept: Kept, most: int = 500_000, rounds: int = 60) -> DataFrame:
    """edges(a, b) to labels(node, component), component being the smallest node that can be reached; nodes without a link have no row.

    Each task first reduces its own edges to a forest. Up to `most` forest edges are joined by one task; more go through star contractions."""
    both = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v")
    cur = kept.keep(both.mapInPandas(forest, "u long, v long"))
    if cur.count() <= most:
        low = kept.keep(cur.coalesce(1).mapInPandas(forest, "u long, v long")).select("u", F.col("v").alias("component"))
    else:
        low = contracted(cur.distinct(), kept, rounds)
    return low.select(F.col("u").alias("node"), "component").union(low.select(F.col("component").alias("node"), "component").distinct())


def contracted(edges: DataFrame, kept: Kept, rounds: int = 60) -> DataFrame:
    """edges(u, v), v < u, to (u, component) by star contractions.

    Each round points every larger neighbour, then every smaller one, at the smallest of a node's neighbourhood; the number of
    rounds grows with the logarithm of the graph. Minima are partial aggregates, so a hub costs no more than its links."""
    cur, seen = kept.keep(edges), None
    for _ in range(rounds):
        both = cur.union(cur.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct(F.col("u").alias("u"), F.col("m").alias("v")), F.struct(F.greatest("v", "m").alias("u"), F.least("v", "m").alias("v")))).alias("e"))
        new = kept.keep(small.select("e.u", "e.v").filter("u <> v").distinct())
        state = new.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        kept.drop(cur)
        cur = new
        if state == seen:
            break
        seen = state
    return cur.groupBy("u").agg(F.min("v").alias("component"))
