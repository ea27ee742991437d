"""Products of coordinate matrices: by bands, by blocks in two phases, and by redundant block sketches that tolerate lost tasks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import HashFamily
from . import coded, kernel, sketch, squares
from .losses import Losses
from .matrix import CoordMatrix
from .straggler import Policy, survivors


def _paired(a: CoordMatrix, b: CoordMatrix) -> DataFrame:
    """All products of entries that share the contraction index: (i, j, c, v)."""
    right = b.df.select(F.col("i").alias("c"), F.col("c").alias("j"), F.col("v").alias("w"))
    return a.df.join(right, "c").select("i", "j", "c", (F.col("v") * F.col("w")).alias("v"))


def multiply(a: CoordMatrix, b: CoordMatrix) -> CoordMatrix:
    """Exact, in one plan: join on the contraction index, map-side sums, one exchange on the cell."""
    out = _paired(a, b).groupBy("i", "j").agg(F.sum("v").alias("v"))
    return CoordMatrix(out.select("i", F.col("j").alias("c"), "v"), a.rows, b.cols)


def band_multiply(a: CoordMatrix, b: CoordMatrix, height: int) -> CoordMatrix:
    """Each task holds bands of `height` rows of A and of columns of B, whole along the contraction, which it goes through in runs; of B it gets the rows that its
    bands of A have entries for, and a cell is finished where it is computed."""
    return _linked(a, b, (height, 4096, height))


def _linked(a: CoordMatrix, b: CoordMatrix, sizes: tuple[int, int, int]) -> CoordMatrix:
    right = b.df.select(F.col("i").alias("c"), F.col("c").alias("j"), "v")
    out = kernel.linked(a.df, right, sizes, (-(-a.rows // sizes[0]), -(-b.cols // sizes[2])))
    return CoordMatrix(out.select("i", F.col("j").alias("c"), F.col("total").alias("v")), a.rows, b.cols)


def narrow_multiply(a: CoordMatrix, b: CoordMatrix, height: int = 64) -> CoordMatrix:
    """As band_multiply, for a B that is small beside A: what moves is A and a copy of B per 512 rows of A, no products."""
    return _linked(a, b, (height, 4096, height))


def gram(a: CoordMatrix, short: int = 2048) -> CoordMatrix:
    """A times its transpose. With up to `short` columns, bands of rows meet in squares and no product is shuffled; wider matrices are joined on the contraction index."""
    if a.cols > short or a.df.schema["v"].dataType.typeName() not in ("long", "integer", "double"):
        return multiply(a, a.t)
    return CoordMatrix(kernel.short_gram(a.df, a.rows, a.cols).select("i", F.col("j").alias("c"), F.col("total").alias("v")), a.rows, a.rows)


def block_partials(a: CoordMatrix, b: CoordMatrix, block: int | tuple[int, int, int]) -> DataFrame:
    """Computation phase: (bi, bj, k, i, j, v), the product of each pair of blocks. Blocks may be (p, q, r) rather than square."""
    p, q, r = (block,) * 3 if isinstance(block, int) else block
    e = _paired(a, b)
    key = [(F.col("i") / p).cast("int").alias("bi"), (F.col("j") / r).cast("int").alias("bj"), (F.col("c") / q).cast("int").alias("k")]
    return e.groupBy(*key, "i", "j").agg(F.sum("v").alias("v"))


def partial_sums(a: DataFrame, b: DataFrame, block: int | tuple[int, int, int]) -> DataFrame:
    """Of the computation phase, (bi, bj, k, n_entries, total) of whole numbers: how many entries each partial has and their sum, found in the task that multiplies the blocks.
    a and b have rows (i, c, v), of which a cell may have many."""
    return kernel.slice_sums(a, b.select(F.col("i").alias("c"), F.col("c").alias("j"), "v"), (block,) * 3 if isinstance(block, int) else block)


def reduce_partials(partials: DataFrame, a: CoordMatrix, b: CoordMatrix) -> CoordMatrix:
    """Reduction phase: the sum over the contraction blocks of each cell."""
    return CoordMatrix(partials.groupBy("i", F.col("j").alias("c")).agg(F.sum("v").alias("v")), a.rows, b.cols)


def block_multiply(a: CoordMatrix, b: CoordMatrix, block: int | tuple[int, int, int], fused: bool = False) -> CoordMatrix:
    return multiply(a, b) if fused else reduce_partials(block_partials(a, b, block), a, b)


def dense_block_multiply(a: CoordMatrix, b: CoordMatrix, block: int) -> CoordMatrix:
    """The two phases on blocks: each (bi, bj, k) is a dense product in NumPy, and the task that has all k of a cell sums them."""
    return _linked(a, b, (block,) * 3)


def sketched_partials(left: DataFrame, right: DataFrame, b: int, half: bool = False) -> DataFrame:
    """(bi, bj, k, i, j, v): each slice's estimate of each entry. left (i, k, h, v), right (k, h, j, v); half: only cells with bi <= bj."""
    right = right.select(F.col("k").alias("rk"), F.col("h").alias("rh"), "j", F.col("v").alias("w"))
    bi, bj = (F.col("i") / b).cast("int"), (F.col("j") / b).cast("int")
    on = (F.col("k") == F.col("rk")) & (F.col("h") == F.col("rh"))
    both = left.join(right, on & (bi <= bj) if half else on).select(bi.alias("bi"), bj.alias("bj"), "k", "i", "j", (F.col("v") * F.col("w")).alias("v"))
    return both.groupBy("bi", "bj", "k", "i", "j").agg(F.sum("v").alias("v"))


def _estimated(totals: DataFrame, provisioned: int | None = None) -> DataFrame:
    """(i, j, v_hat, n_survivors) from sums by entry."""
    by = F.col("n_survivors") if provisioned is None else F.lit(provisioned)
    return totals.select("i", "j", (F.col("total").cast("double") / by).alias("v_hat"), "n_survivors")


def rbs_multiply(a: CoordMatrix, b: CoordMatrix, width: int, family: HashFamily, log: DataFrame | None = None, policy: Policy | None = None, provisioned: int | None = None, ahead: bool = False) -> DataFrame:
    """Redundant block-sketch product: cell by cell and slice by slice, of blocks; each cell counts the slices that its policy waits for. A log covers
    every cell. The others are multiplied too and then ignored, as stragglers are; `ahead` leaves them out before."""
    chosen = survivors(log, policy) if log is not None else None
    left, right = sketch.stacked_sketch(a, width, family), sketch.sketch_right(b, width, family)
    totals = kernel.cells(left, right, family.slices, (width,) * 3, (-(-a.rows // width), -(-b.cols // width)), chosen=chosen, ahead=ahead)
    return _estimated(totals, provisioned)


def rbs_gram(a: CoordMatrix, width: int, family: HashFamily, log: DataFrame | Losses | None = None, policy: Policy | None = None, ahead: bool = False) -> DataFrame:
    """A times its transpose from one sketch: cells with bi <= bj are computed, the rest mirrored, so the estimate is symmetric. Losses hold their policy."""
    if isinstance(log, Losses):
        return squares.sketched_gram(a.df, a.rows, width, family, log, ahead)
    return gram_of_sketch(sketch.stacked_sketch(a, width, family), a.rows, width, family.slices, survivors(log, policy) if log is not None else None, ahead)


def gram_of_sketch(s: DataFrame, rows: int, width: int, slices: int, chosen: DataFrame | None = None, ahead: bool = False) -> DataFrame:
    """(i, j, v_hat, n_survivors) from a stacked sketch (i, k, h, v) and the slices that count in each cell."""
    right = s.select("k", "h", F.col("i").alias("j"), "v")
    cells = -(-rows // width)
    upper = _estimated(kernel.cells(s, right, slices, (width,) * 3, (cells, cells), half=True, chosen=chosen, ahead=ahead))
    mirrored = F.when((F.col("i") / width).cast("int") < (F.col("j") / width).cast("int"), F.array(F.struct("i", "j"), F.struct(F.col("j").alias("i"), F.col("i").alias("j")))).otherwise(F.array(F.struct("i", "j")))
    return upper.select(F.explode(mirrored).alias("at"), "v_hat", "n_survivors").select("at.i", "at.j", "v_hat", "n_survivors")


def rbs_parity_multiply(a: CoordMatrix, b: CoordMatrix, width: int, family: HashFamily, lost: list[tuple[int, int]] = ()) -> DataFrame:
    """(i, j, v_hat): the sketched product with a parity row block on the left sketch and a parity column block on the right one, so that the output
    cells in `lost`, which never leave the reduction, are decoded from the others. All slices count in every cell, as parity needs equal sets."""
    at = (F.col("k") * width + F.col("h")).cast("long")
    left = CoordMatrix(sketch.stacked_sketch(a, width, family).select("i", at.alias("c"), "v"), a.rows, family.slices * width)
    right = CoordMatrix(sketch.sketch_right(b, width, family).select(at.alias("i"), F.col("j").alias("c"), "v"), family.slices * width, b.cols)
    out = coded.parity_multiply(left, right, width, lost).df
    return out.select("i", F.col("c").alias("j"), (F.col("v").cast("double") / family.slices).alias("v_hat"))
