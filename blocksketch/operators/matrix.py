"""Coordinate matrices: (i, c, v) DataFrames with a declared shape, and matrix algebra on them. An absent entry is zero."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


@dataclass(frozen=True)
class CoordMatrix:
    """rows x cols; df has i BIGINT, c BIGINT and a number v, one row for each (i, c) that is present. Sketches hash indices below 2^31 - 1."""

    df: DataFrame
    rows: int
    cols: int

    @staticmethod
    def parts(df: DataFrame, i: str | Column, c: str | Column, v: str | Column | None = None) -> DataFrame:
        """(i, c, v) before sums: a cell's value is the sum of its rows'."""
        col = lambda x: F.col(x) if isinstance(x, str) else x
        out = df.select(col(i).cast("long").alias("i"), col(c).cast("long").alias("c"), (F.lit(1).cast("long") if v is None else col(v)).alias("v"))
        return out.filter("i is not null and c is not null and v is not null")

    @staticmethod
    def of(df: DataFrame, i: str | Column, c: str | Column, v: str | Column | None = None, shape: tuple[int, int] | None = None) -> CoordMatrix:
        """Sums v (default: counts rows) by two index columns; the shape is declared or found by one aggregate."""
        out = CoordMatrix.parts(df, i, c, v).groupBy("i", "c").agg(F.sum("v").alias("v"))
        if shape is None:
            top = out.agg(F.max("i"), F.max("c")).first()
            shape = ((top[0] if top[0] is not None else -1) + 1, (top[1] if top[1] is not None else -1) + 1)
        return CoordMatrix(out, *shape)

    def validate(self) -> CoordMatrix:
        """Raises unless entries are non-null, within the shape and unique, and the shape is one that the hash family tells apart."""
        if max(self.rows, self.cols) > (1 << 31) - 1:
            raise ValueError("an index beyond 2^31 - 1 would share its bucket and sign with another")
        bad = self.df.filter(f"i is null or c is null or v is null or i < 0 or c < 0 or i >= {self.rows} or c >= {self.cols}").limit(1).count()
        twice = self.df.groupBy("i", "c").count().filter("count > 1").limit(1).count()
        if bad or twice:
            raise ValueError("entries are null, out of range or repeated")
        return self

    def with_(self, df: DataFrame, rows: int | None = None, cols: int | None = None) -> CoordMatrix:
        return replace(self, df=df, rows=self.rows if rows is None else rows, cols=self.cols if cols is None else cols)

    @property
    def t(self) -> CoordMatrix:
        return CoordMatrix(self.df.select(F.col("c").alias("i"), F.col("i").alias("c"), "v"), self.cols, self.rows)

    def map(self, f) -> CoordMatrix:
        """Applies f, with f(0) = 0, to the entries."""
        return self.with_(self.df.select("i", "c", f(F.col("v")).alias("v")))

    def scale(self, by) -> CoordMatrix:
        return self.map(lambda v: v * by)

    def add(self, other: CoordMatrix, sign: int = 1) -> CoordMatrix:
        both = self.df.unionByName(other.df.withColumn("v", F.col("v") * sign))
        return self.with_(both.groupBy("i", "c").agg(F.sum("v").alias("v")))

    def hadamard(self, other: CoordMatrix) -> CoordMatrix:
        return self.with_(self.df.alias("a").join(other.df.alias("b"), ["i", "c"]).select("i", "c", (F.col("a.v") * F.col("b.v")).alias("v")))

    def diag_scale(self, left: DataFrame) -> CoordMatrix:
        """Row i times left(i, s)."""
        return self.with_(self.df.join(left, "i").select("i", "c", (F.col("v") * F.col("s")).alias("v")))

    def rows_where(self, condition: str) -> CoordMatrix:
        return self.with_(self.df.filter(condition))

    def slice(self, i0: int, i1: int, c0: int, c1: int) -> CoordMatrix:
        cut = self.df.filter((F.col("i") >= i0) & (F.col("i") < i1) & (F.col("c") >= c0) & (F.col("c") < c1))
        return CoordMatrix(cut.select((F.col("i") - i0).alias("i"), (F.col("c") - c0).alias("c"), "v"), i1 - i0, c1 - c0)

    def below(self, other: CoordMatrix) -> CoordMatrix:
        """This matrix on top of other."""
        low = other.df.withColumn("i", F.col("i") + self.rows)
        return CoordMatrix(self.df.unionByName(low), self.rows + other.rows, max(self.cols, other.cols))

    def matvec(self, x: DataFrame) -> DataFrame:
        """x(c, x) to (i, y)."""
        return self.df.join(x, "c").groupBy("i").agg(F.sum(F.col("v") * F.col("x")).alias("y"))

    def row_norms(self) -> DataFrame:
        return self.df.groupBy("i").agg(F.sum(F.col("v") * F.col("v")).alias("sq"))

    def col_norms(self) -> DataFrame:
        return self.df.groupBy("c").agg(F.sum(F.col("v") * F.col("v")).alias("sq"))

    def frobenius_sq(self) -> DataFrame:
        return self.df.agg(F.coalesce(F.sum(F.col("v").cast("double") * F.col("v")), F.lit(0.0)).alias("sq"))

    def trace(self) -> DataFrame:
        return self.df.filter("i = c").agg(F.coalesce(F.sum("v"), F.lit(0)).alias("trace"))

    def dense_rows(self) -> DataFrame:
        """(i, row ARRAY<DOUBLE>)."""
        m = F.map_from_entries(F.collect_list(F.struct("c", F.col("v").cast("double"))))
        filled = F.transform(F.sequence(F.lit(0).cast("long"), F.lit(self.cols - 1).cast("long")), lambda c: F.coalesce(F.try_element_at(F.col("m"), c), F.lit(0.0)))
        return self.df.groupBy("i").agg(m.alias("m")).select("i", filled.alias("row"))

    def to_blocks(self, b: int, br: int | None = None) -> DataFrame:
        """(bi, bj, nrows, ncols, data): dense row-major blocks of b rows and br (default b) columns; absent blocks are zero."""
        br = br or b
        rows, cols = self.rows, self.cols
        key = self.df.select((F.col("i") / b).cast("int").alias("bi"), (F.col("c") / br).cast("int").alias("bj"), F.struct((F.col("i") % b).cast("int").alias("r"), (F.col("c") % br).cast("int").alias("s"), F.col("v").cast("double").alias("v")).alias("e"))
        packed = key.groupBy("bi", "bj").agg(F.collect_list("e").alias("e")).select("bi", "bj", "e.r", "e.s", "e.v")
        packed = packed.withColumn("nrows", F.least(F.lit(b), F.lit(rows) - F.col("bi") * b).cast("int")).withColumn("ncols", F.least(F.lit(br), F.lit(cols) - F.col("bj") * br).cast("int"))

        def fill(batches):
            import numpy as np
            import pandas as pd

            for pdf in batches:
                data = []
                for r, s, v, n, m in zip(pdf["r"], pdf["s"], pdf["v"], pdf["nrows"], pdf["ncols"], strict=True):
                    data.append(np.bincount(r * m + s, v, n * m))
                yield pd.DataFrame({"bi": pdf["bi"], "bj": pdf["bj"], "nrows": pdf["nrows"], "ncols": pdf["ncols"], "data": data})

        return packed.mapInPandas(fill, "bi int, bj int, nrows int, ncols int, data array<double>")

    @staticmethod
    def from_blocks(blocks: DataFrame, rows: int, cols: int, b: int, br: int | None = None) -> CoordMatrix:
        at = blocks.select("bi", "bj", "ncols", F.posexplode("data").alias("p", "v")).filter("v <> 0")
        i = F.col("bi").cast("long") * b + (F.col("p") / F.col("ncols")).cast("long")
        c = F.col("bj").cast("long") * (br or b) + F.col("p") % F.col("ncols")
        return CoordMatrix(at.select(i.alias("i"), c.cast("long").alias("c"), "v"), rows, cols)


def identity(indices: DataFrame, key: str, n: int) -> CoordMatrix:
    """n x n: one on the diagonal for each value of key, zero rows for the rest."""
    at = F.col(key).cast("long")
    return CoordMatrix(indices.select(at.alias("i"), at.alias("c")).filter("i is not null").distinct().select("i", "c", F.lit(1).cast("long").alias("v")), n, n)


def generated(spark, rows: int, cols: int, value) -> CoordMatrix:
    """Entries value(x, y) of the one-based row and column."""
    x, y = (F.col("id") / cols).cast("long"), F.col("id") % cols
    cells = spark.range(rows * cols).select(x.alias("i"), y.alias("c"))
    return CoordMatrix(cells.select("i", "c", value(F.col("i") + 1, F.col("c") + 1).alias("v")), rows, cols)


def numbered(df: DataFrame, key: str, index: str = "c") -> DataFrame:
    """A dictionary: each distinct value of key with its place in sorted order, from 0, without one task seeing all keys."""
    return indexed(df.select(key).filter(F.col(key).isNotNull()).distinct(), index, key)


def indexed(df: DataFrame, index: str, *order: str) -> DataFrame:
    """All rows with their place, from 0, in the order of the columns named; rows that agree in these are told apart by all other columns, so only rows
    that are equal in full may change places. Ranges are sorted in parallel; their sizes, one number per task, give each range its start."""
    rest = [c for c in df.columns if c not in order]
    placed = df.repartitionByRange(*map(F.col, order)).sortWithinPartitions(*order, *rest).withColumn("__at", F.monotonically_increasing_id())
    part, at = F.shiftrightunsigned("__at", 33), F.col("__at").bitwiseAND((1 << 33) - 1)
    placed = placed.select(*df.columns, part.alias("__p"), at.alias("__at")).persist()
    start, sizes = 0, []
    for p, n in sorted((r[0], r[1]) for r in placed.groupBy("__p").count().collect()):  # one row per task
        sizes.append((p, start))
        start += n
    starts = df.sparkSession.createDataFrame(sizes, T.StructType([T.StructField("__p", T.LongType()), T.StructField("__s", T.LongType())]))
    return placed.join(F.broadcast(starts), "__p").select(*df.columns, (F.col("__s") + F.col("__at")).alias(index))


def bounded(df: DataFrame, most: int = 1_000_000, otherwise: str | None = None) -> DataFrame:
    """df, to be broadcast if it has at most `most` rows, else with the hint `otherwise`."""
    if df.count() <= most:
        return F.broadcast(df)
    return df.hint(otherwise) if otherwise else df
