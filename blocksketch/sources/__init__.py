"""Tables in, matrices in and out: Parquet scans, pivots of the given tables, other formats, bucketed sinks, file streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators.matrix import CoordMatrix

FORMATS = ("parquet", "orc", "json", "csv")
MATRIX = "i BIGINT, c BIGINT, v BIGINT"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def month_index(ts, first_year: int):
    return (F.year(ts) - first_year) * 12 + F.month(ts) - 1


def supplier_part(spark: SparkSession, sf_dir: str) -> CoordMatrix:
    """Quantity by supplier and part."""
    return CoordMatrix.of(load(spark, sf_dir, "lineitem"), "l_suppkey", "l_partkey", F.col("l_quantity").cast("long"))


def part_month(spark: SparkSession, sf_dir: str) -> CoordMatrix:
    """Quantity by part and month of shipping from January 1995."""
    return CoordMatrix.of(load(spark, sf_dir, "lineitem"), "l_partkey", month_index(F.col("l_shipdate"), 1995), F.col("l_quantity").cast("long"))


def supplier_part_months(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """The rows (i, c, v) that supplier_part and part_month sum up."""
    line, quantity = load(spark, sf_dir, "lineitem"), F.col("l_quantity").cast("long")
    return CoordMatrix.parts(line, "l_suppkey", "l_partkey", quantity), CoordMatrix.parts(line, "l_partkey", month_index(F.col("l_shipdate"), 1995), quantity)


def customer_month(spark: SparkSession, sf_dir: str) -> CoordMatrix:
    """Orders by customer and month from January 1995."""
    return CoordMatrix.of(load(spark, sf_dir, "orders"), "o_custkey", month_index(F.col("o_orderdate"), 1995))


def user_hour(spark: SparkSession, sf_dir: str) -> CoordMatrix:
    """Events by user and hour of January 2024."""
    e = load(spark, sf_dir, "events")
    return CoordMatrix.of(e, "user_id", (F.dayofmonth("ts") - 1) * 24 + F.hour("ts"))


def type_k(spark: SparkSession, sf_dir: str) -> CoordMatrix:
    """Events by type (in sorted order) and the number k in their JSON."""
    from ..operators.matrix import numbered

    e = load(spark, sf_dir, "events")
    types = numbered(e, "event_type", "type_id")
    return CoordMatrix.of(e.join(F.broadcast(types), "event_type"), "type_id", F.get_json_object("props", "$.k").cast("long"))


def k_hour(spark: SparkSession, sf_dir: str) -> CoordMatrix:
    """Events by the number k in their JSON and hour of January 2024: few rows, all cells positive once there are many events."""
    return CoordMatrix.of(load(spark, sf_dir, "events"), F.get_json_object("props", "$.k").cast("long"), (F.dayofmonth("ts") - 1) * 24 + F.hour("ts"))


def order_months(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(c, n): orders by month from January 1995."""
    return load(spark, sf_dir, "orders").groupBy(month_index(F.col("o_orderdate"), 1995).cast("long").alias("c")).agg(F.count("*").alias("n"))


def event_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A task log out of the events: each event is a task of the cell of its block of 16 users and its day, and took the time since its user's last one."""
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    gap = us - F.lag(us).over(W.partitionBy("user_id").orderBy("ts", "event_id"))
    e = load(spark, sf_dir, "events").select((F.col("user_id") / 16).cast("int").alias("bi"), (F.dayofmonth("ts") - 1).alias("bj"), F.col("event_id").alias("k"), F.floor(gap / 1000).cast("long").alias("t_ms"), F.lit("done").alias("status"))
    return e.filter("t_ms is not null")


def embedding_dim(spark: SparkSession, sf_dir: str, scale: int | None = 1000) -> CoordMatrix:
    """Vectors by dimension, rounded to whole numbers of 1/scale, or as doubles."""
    e = load(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("d", "x"))
    v = F.col("x").cast("double")
    return CoordMatrix.of(e, "vec_id", "d", v if scale is None else F.floor(v * scale + 0.5).cast("long"))


def save(m: CoordMatrix, path: str, fmt: str = "parquet") -> None:
    w = m.df.write.mode("overwrite")
    (w.option("header", True) if fmt == "csv" else w).format(fmt).save(path)


def read(spark: SparkSession, path: str, fmt: str, rows: int, cols: int) -> CoordMatrix:
    r = spark.read.schema(MATRIX)
    return CoordMatrix((r.option("header", True) if fmt == "csv" else r).format(fmt).load(path), rows, cols)


def save_blocks(df: DataFrame, path: str, key: str = "bi") -> None:
    """Partitioned by row block, so that a later read of some blocks prunes the rest."""
    df.write.mode("overwrite").partitionBy(key).parquet(path)


def save_bucketed(df: DataFrame, table: str, key: str = "c", buckets: int = 8) -> None:
    """A table bucketed by the contraction index: products of two such tables need no exchange before the join."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def stream(spark: SparkSession, sf_dir: str, name: str = "events") -> DataFrame:
    """The table as a file stream, with its timestamp in UTC as watermarks need it."""
    schema = load(spark, sf_dir, name).schema
    df = spark.readStream.schema(schema).option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)
    return df.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in df.columns else df
