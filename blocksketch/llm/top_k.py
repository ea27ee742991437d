"""Exact top-k search by tiles: products of query blocks and shards, a partial selection in each tile, and a merge by tree.

Components become integers floor(1024 * x). Rows are dealt to shards and queries to blocks by hash, each sized so that a tile fits a task; a
tile multiplies its matrices in runs of rows, keeps the k best of each query after every run, and hands on at most k per query. Top lists are
merged in steps of `fan` shards, so no task gathers more than fan * k rows of a query. A query's own row is no candidate; ties go to the
smaller vec_id. Products are exact: double precision while every sum stays below 2^53, Python integers
beyond (a score that 64 bits cannot hold is the nearest that they can).

Defined results: vectors that are null, empty-handed of a vec_id, or hold null or non-finite components take no part; vectors of different
lengths are compared on their common components; repeated rows are candidates each; fewer candidates than k give shorter lists.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Kept, table


def integers(vectors: DataFrame, scale: int = 1024) -> DataFrame:
    """(vec_id, v array<double> of whole numbers) of the vectors that take part."""
    fine = F.col("embedding").isNotNull() & F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    v = F.transform("embedding", lambda x: F.floor(x.cast("double") * scale).cast("double"))
    return vectors.filter(fine & F.col("vec_id").isNotNull()).select(F.col("vec_id").cast("long").alias("vec_id"), v.alias("v"))


def matrix(rows: pd.Series, width: int) -> np.ndarray:
    out = np.zeros((len(rows), width))
    for i, r in enumerate(rows):
        out[i, : len(r)] = r
    return out


def _best(query: np.ndarray, ids: np.ndarray, score: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best of each query, by score and then id."""
    order = np.lexsort((ids, -score, query))
    q = query[order]
    rank = np.arange(len(q)) - np.searchsorted(q, q)
    return order[rank < k]


def _tile(k: int, run: int):
    def tile(queries: pd.DataFrame, shard: pd.DataFrame) -> pd.DataFrame:
        out = pd.DataFrame({"query_id": np.zeros(0, np.int64), "vec_id": np.zeros(0, np.int64), "score": np.zeros(0, np.int64)})
        if queries.empty or shard.empty:
            return out
        width = max(map(len, [*queries["v"], *shard["sv"]]))
        q, qid = matrix(queries["v"], width), queries["vec_id"].to_numpy()
        top = [(np.zeros(0, np.int64),) * 3]
        for begin in range(0, len(shard), run):
            part = shard.iloc[begin : begin + run]
            s, ids = matrix(part["sv"], width), part["sid"].to_numpy()
            exact = np.abs(q).max(initial=0) * np.abs(s).max(initial=0) * max(width, 1) < 2**53
            whole = np.vectorize(int, otypes=[object])
            p = (q @ s.T).astype(np.int64) if exact else np.clip(whole(q) @ whole(s).T, -(2**63) + 2, 2**63 - 1).astype(np.int64)
            p[qid[:, None] == ids[None, :]] = np.iinfo(np.int64).min + 1
            if len(ids) > k:
                least = -np.partition(-p, k - 1, axis=1)[:, k - 1 : k]  # the k-th best: all as good as it stay, for ties
                at, of = np.nonzero(p >= least)
            else:
                at, of = np.nonzero(np.ones_like(p, bool))
            fine = qid[at] != ids[of]
            at, of = at[fine], of[fine]
            top.append((at, ids[of], p[at, of]))
            at, ids, score = (np.concatenate(x) for x in zip(*top, strict=True))
            keep = _best(at, ids, score, k)
            top = [(at[keep], ids[keep], score[keep])]
        at, ids, score = top[0]
        return pd.DataFrame({"query_id": qid[at], "vec_id": ids, "score": score})

    return tile


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 10, shard_rows: int = 20_000, block_rows: int = 4_000, fan: int = 16, run: int = 2_048) -> DataFrame:
    """vectors and queries (vec_id, v) to query_id, rank, vec_id, score."""
    n, m = vectors.count(), queries.count()
    shards, blocks = max(1, math.ceil(n / shard_rows)), max(1, math.ceil(m / block_rows))
    spread = lambda c, of, by: F.pmod(F.xxhash64(*c), F.lit(of)).cast("int").alias(by)
    # New names on one side: both may come from one table.
    s = vectors.select(F.col("vec_id").alias("sid"), F.col("v").alias("sv"), spread(["vec_id", "v"], shards, "shard"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"))
    q = queries.dropDuplicates(["vec_id"]).select("vec_id", "v", spread(["vec_id"], blocks, "block"), F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("shard"))
    best = q.groupBy("block", "shard").cogroup(s.groupBy("block", "shard")).applyInPandas(_tile(k, run), "query_id long, vec_id long, score long")
    order = [F.desc("score"), F.asc("vec_id")]
    while shards > fan:
        shards = math.ceil(shards / fan)
        group = F.pmod(F.xxhash64("vec_id", F.lit(shards)), F.lit(shards))
        best = best.withColumn("g", group).withColumn("r", F.row_number().over(W.partitionBy("query_id", "g").orderBy(*order))).filter(F.col("r") <= k).drop("g", "r")
    best = best.withColumn("rank", F.row_number().over(W.partitionBy("query_id").orderBy(*order))).filter(F.col("rank") <= k)
    return best.select("query_id", "rank", "vec_id", "score")


def op6_tiled_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = Kept(spark).keep(integers(table(spark, sf_dir, "embeddings")))
    return top_k(rows, rows.filter(F.col("vec_id") % 100 == 0))


ORACLE = """
WITH fine AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(1024 * CAST(x AS DOUBLE)) AS BIGINT)) AS v
  FROM embeddings WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), scored AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id, CAST(list_dot_product(CAST(q.v AS DOUBLE[]), CAST(c.v AS DOUBLE[])) AS BIGINT) AS score
  FROM fine q JOIN fine c ON q.vec_id % 100 = 0 AND q.vec_id <> c.vec_id
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS r FROM scored
)
SELECT query_id, CAST(r AS INTEGER) AS rank, vec_id, score FROM ranked WHERE r <= 10
"""
