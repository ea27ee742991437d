import datetime as dt
import os

from helpers import DATA
from pyspark.sql import functions as F

from blocksketch import sources
from blocksketch.functions.hashing import HashFamily
from blocksketch.operators import sketch
from blocksketch.streaming import stream


def test_running_sketch_equals_batch(spark, tmp_path):
    e = sources.load(spark, DATA, "events")
    for k in range(3):
        e.filter(F.col("event_id") % 3 == k).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    live = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in")).withColumn("ts", F.col("ts").cast("timestamp"))
    got = stream.finished(stream.running_sketch(live, 16, HashFamily(2)))
    want = sketch.stacked_sketch(sources.user_hour(spark, DATA), 16, HashFamily(2))
    key = lambda df: {tuple(r) for r in df.select("i", "k", "h", "v").collect()}
    assert key(got) == key(want)


def test_late_rows_and_duplicates(spark, tmp_path):
    schema = "event_id long, ts timestamp, event_type string, value double, user_id long"
    day = lambda n, h=0: dt.datetime(2024, 1, n, h)
    for n, rows in enumerate([[(1, day(1), "a", 1.0, 1), (2, day(10), "a", 1.0, 1)], [(5, day(11), "a", 1.0, 1)], [(3, day(2), "a", 5.0, 1), (2, day(10), "a", 1.0, 1), (4, day(20), "a", 1.0, 1)]]):
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(tmp_path / f"in/f{n}"))
        for f in (tmp_path / f"in/f{n}").iterdir():
            os.utime(f, (1_700_000_000 + 1000 * n,) * 2)
    read = lambda: spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(tmp_path / "in"))
    once = stream.finished(stream.deduplicated(read(), "15 days").select("event_id"), "append")
    assert sorted(r.event_id for r in once.collect()) == [1, 2, 3, 4, 5]
    closed = stream.finished(stream.windowed(read().withWatermark("ts", "1 day"), "1 day"), "append")
    assert closed.filter("start = timestamp'2024-01-02'").count() == 0
    assert closed.filter("start = timestamp'2024-01-01'").first().n == 1


def test_gate_emits_each_cell_once(spark, tmp_path):
    rows = [(0, 0, k, 10 * k) for k in range(5)] + [(0, 1, k, k) for k in range(2)]
    df = spark.createDataFrame(rows, "bi int, bj int, k int, total long")
    df.repartition(4, "k").write.parquet(str(tmp_path / "in"))
    got = stream.finished(stream.gate(spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in")), 3), "append").collect()
    assert [(r.bi, r.bj, r.n_survivors) for r in got] == [(0, 0, 3)]


def test_stream_meets_a_table(spark):
    import duckdb

    from blocksketch.workloads import streams

    con = duckdb.connect()
    for t in ("events", "customer"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    want = con.execute(streams.ORACLES["stream_static_join"]).fetchall()
    assert sorted(tuple(r) for r in streams.stream_static_join(spark, DATA).collect()) == sorted(want) and want
