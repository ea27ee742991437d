"""The coded baseline: one parity band of rows and one of columns; lost cells of the grid are recovered by peeling."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .matrix import CoordMatrix

Cell = tuple[int, int]


class Undecodable(ValueError):
    """The losses hold a stopping set, at least the corners of a rectangle."""


def peel(lost: Iterable[Cell], rows: int, cols: int, strict: bool = True) -> list[tuple[Cell, str]]:
    """Steps that recover every lost cell of the (rows + 1) x (cols + 1) grid, each from its row or its column. A remainder of parity cells only is no failure."""
    left, steps = set(lost), []
    while left:
        done = None
        for cell in sorted(left):
            if sum(x[0] == cell[0] for x in left) == 1:
                done = (cell, "row")
            elif sum(x[1] == cell[1] for x in left) == 1:
                done = (cell, "col")
            if done:
                break
        if not done:
            if strict and any(r < rows and c < cols for r, c in left):
                raise Undecodable(f"{len(left)} cells remain")
            break
        steps.append(done)
        left.remove(done[0])
    return steps


def decodes(lost: Iterable[Cell], rows: int, cols: int) -> bool:
    try:
        peel(lost, rows, cols)
    except Undecodable:
        return False
    return True


def combination(lost: Iterable[Cell], rows: int, cols: int) -> dict[Cell, dict[Cell, int]]:
    """Each lost data cell as a signed sum of cells that arrived."""
    out: dict[Cell, dict[Cell, int]] = {}
    for (r, c), by in peel(lost, rows, cols):
        line = [(r, x) for x in range(cols + 1)] if by == "row" else [(x, c) for x in range(rows + 1)]
        parity = line[-1]
        terms: dict[Cell, int] = {}
        for cell in line:
            if cell == (r, c):
                continue
            # The parity cell is the sum of the others: a data cell is parity minus the rest.
            s = (1 if cell == parity else -1) if (r, c) != parity else 1
            for src, w in out.get(cell, {cell: 1}).items():
                terms[src] = terms.get(src, 0) + s * w
        out[(r, c)] = {k: w for k, w in terms.items() if w}
    return {(r, c): terms for (r, c), terms in out.items() if r < rows and c < cols}


def parity_cells(a: CoordMatrix, b: CoordMatrix, height: int) -> DataFrame:
    """(r, l, li, lj, v): the products of all bands, parity bands last."""
    rows, cols = -(-a.rows // height), -(-b.cols // height)
    left = a.df.select((F.col("i") / height).cast("int").alias("r"), (F.col("i") % height).cast("int").alias("li"), "c", "v")
    left = left.union(left.groupBy(F.lit(rows).alias("r"), "li", "c").agg(F.sum("v").alias("v")))
    right = b.df.select((F.col("c") / height).cast("int").alias("l"), (F.col("c") % height).cast("int").alias("lj"), F.col("i").alias("c"), F.col("v").alias("w"))
    right = right.union(right.groupBy(F.lit(cols).alias("l"), "lj", "c").agg(F.sum("w").alias("w")))
    return left.join(right, "c").groupBy("r", "l", "li", "lj").agg(F.sum(F.col("v") * F.col("w")).alias("v"))


def parity_multiply(a: CoordMatrix, b: CoordMatrix, height: int, lost: Iterable[Cell] = ()) -> CoordMatrix:
    """The exact product although the cells in `lost` never arrive. Peeling runs on the metadata of lost cells; the arithmetic is a join and a sum: each
    entry that arrived counts for its own cell and for the lost ones that need it."""
    rows, cols, lost = -(-a.rows // height), -(-b.cols // height), list(lost)
    needed: dict[Cell, list[tuple[int, int, int]]] = {}
    for (r, c), terms in combination(lost, rows, cols).items():
        for source, w in terms.items():
            needed.setdefault(source, []).append((r, c, w))
    spark = a.df.sparkSession
    plan = spark.createDataFrame([(r, c, to) for (r, c), to in needed.items()], "r int, l int, to array<struct<tr:int,tl:int,w:bigint>>")
    gone = spark.createDataFrame(lost, "r int, l int")
    arrived = parity_cells(a, b, height).join(F.broadcast(gone), ["r", "l"], "left_anti").join(F.broadcast(plan), ["r", "l"], "left")
    own = F.when((F.col("r") < rows) & (F.col("l") < cols), F.array(F.struct(F.col("r").alias("tr"), F.col("l").alias("tl"), F.lit(1).cast("long").alias("w"))))
    none = F.array().cast("array<struct<tr:int,tl:int,w:bigint>>")
    out = arrived.select("li", "lj", "v", F.inline(F.concat(F.coalesce(own, none), F.coalesce("to", none)))).groupBy("tr", "tl", "li", "lj").agg(F.sum(F.col("v") * F.col("w")).alias("v"))
    out = out.select((F.col("tr").cast("long") * height + F.col("li")).alias("i"), (F.col("tl").cast("long") * height + F.col("lj")).alias("c"), "v")
    return CoordMatrix(out.filter("v <> 0"), a.rows, b.cols)


def completion_time(times: dict[Cell, int], rows: int, cols: int) -> int:
    """The earliest time at which the cells that have arrived decode; decodability only grows with time."""
    at = sorted(set(times.values()))
    lo, hi = 0, len(at) - 1
    while lo < hi:
        mid = (lo + hi) // 2
        if decodes([c for c, t in times.items() if t > at[mid]], rows, cols):
            hi = mid
        else:
            lo = mid + 1
    return at[lo]


def decoder_memory(m: int, l: int) -> int:  # noqa: E741
    """Entries that a single master would hold to decode; the decoder here is distributed."""
    return m * l
