"""Streaming workloads over the events table, each equal to its batch twin."""

from __future__ import annotations

import os
import tempfile

from pyspark.sql import functions as F

from .. import sources
from ..functions.hashing import HashFamily
from ..operators import multiply, sketch
from ..streaming import stream
from . import sql
from .products import B

QUERIES, ORACLES = {}, {}


def query(oracle: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle:
            ORACLES[f.__name__] = oracle
        return f

    return add


@query(f"WITH {sql.family(3)}, {sql.with_('f4')} {sql.sketch('f4', 16)}")
def stream_sketch_users(spark, d):
    return stream.finished(stream.running_sketch(sources.stream(spark, d), 16, HashFamily(3)))


_CENTS = "count(*) AS n, CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) AS BIGINT) AS cents"


@query(f"SELECT CAST(time_bucket(INTERVAL 1 DAY, ts) AS TIMESTAMP) AS start, event_type, {_CENTS} FROM events GROUP BY 1, 2")
def stream_tumbling(spark, d):
    return stream.finished(stream.windowed(sources.stream(spark, d), "1 day")).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query(f"SELECT CAST(date_trunc('hour', ts) - INTERVAL 1 HOUR * (h + (hour(ts) % 6)) AS TIMESTAMP) AS start, event_type, {_CENTS} FROM events, (VALUES (0), (6)) AS s(h) GROUP BY 1, 2")
def stream_sliding(spark, d):
    return stream.finished(stream.windowed(sources.stream(spark, d), "12 hours", "6 hours")).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("WITH g AS (SELECT *, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 8 HOUR THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM g) SELECT min(ts) AS start, user_id, count(*) AS n FROM s GROUP BY user_id, k")
def stream_session(spark, d):
    return stream.finished(stream.sessions(sources.stream(spark, d), "8 hours")).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("SELECT count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids FROM events")
def stream_dedup(spark, d):
    return stream.finished(stream.deduplicated(sources.stream(spark, d)).select("event_id"), "append").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))


@query("SELECT c_mktsegment, event_type, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY c_mktsegment, event_type")
def stream_static_join(spark, d):
    """Events as they arrive meet the customer table; its size decides how, and state holds the counts only."""
    customer = sources.load(spark, d, "customer").select("c_custkey", "c_mktsegment")
    joined = sources.stream(spark, d).join(customer, F.col("user_id") == F.col("c_custkey"))
    return stream.finished(joined.groupBy("c_mktsegment", "event_type").agg(F.count("*").alias("n")))


@query()
def stream_late(spark, d):
    """Day windows behind a watermark of one day: closed windows only, in append mode."""
    e = sources.stream(spark, d).withWatermark("ts", "1 day")
    return stream.finished(stream.windowed(e, "1 day"), "append").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query()
def stream_gate(spark, d):
    """Slices' totals per cell arrive as files; a cell comes out with its fourth."""
    a, b, family = sources.supplier_part(spark, d), sources.part_month(spark, d), HashFamily(5)
    parts = multiply.sketched_partials(sketch.stacked_sketch(a, B, family), sketch.sketch_right(b, B, family), B)
    totals = parts.groupBy("bi", "bj", "k").agg(F.sum("v").alias("total"))
    place = spark.conf.get("spark.checkpoint.dir", None)
    path = f"{place}/gate-{os.urandom(6).hex()}" if place else tempfile.mkdtemp(prefix="gate-")
    totals.repartition(5, "k").write.mode("overwrite").parquet(path)
    return stream.finished(stream.gate(spark.readStream.schema(totals.schema).parquet(path), 4), "append")
