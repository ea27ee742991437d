"""Products of blocks: one task per pair of blocks and contraction slice, a dense product in NumPy there, and sums by cell.

`linked` is for sparse matrices with a long contraction. `cells` is for stacked sketches: few slices, many cells. A task there holds some row blocks and some column blocks with all their slices, so what is copied falls
with the number of blocks per task, and sums never move.

Blocks travel as index and value arrays, so what moves is their entries; they become dense only in the task that multiplies them. A left block
is copied once per column block and a right one once per row block, so tasks spread by (bi, bj, k) however few slices there are."""

from __future__ import annotations

import pickle
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Rows of survivors that may be broadcast.
SMALL = 1_000_000
_EXACT = float(1 << 53)


def tiles(entries: DataFrame, row: Column, col: Column, v: Column, *keys: Column) -> DataFrame:
    """A row per value of the keys: r, s and v, parallel arrays of the entries' places and values."""
    at = entries.select(*keys, F.struct(row.cast("int").alias("r"), col.cast("int").alias("s"), v.alias("v")).alias("e"))
    names = [c for c in at.columns if c != "e"]
    return at.groupBy(*names).agg(F.collect_list("e").alias("e")).select(*names, "e.r", "e.s", "e.v")


def filled(r: np.ndarray, s: np.ndarray, v: np.ndarray, rows: int, cols: int) -> tuple[np.ndarray, np.ndarray]:
    """The dense block, and which of its places have an entry."""
    x, has = np.zeros((rows, cols), np.asarray(v).dtype), np.zeros((rows, cols), bool)
    np.add.at(x, (r, s), v)
    has[r, s] = True
    return x, has


def _dot(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """The product, exact for integers: in doubles while all sums fit into 53 bits, else in 64-bit integers."""
    if x.dtype.kind == "f" or y.dtype.kind == "f":
        return x.astype(float) @ y.astype(float)
    if float(np.abs(x).max(initial=0)) * float(np.abs(y).max(initial=0)) * x.shape[1] < _EXACT:
        return (x.astype(float) @ y.astype(float)).astype(np.int64)
    return x @ y


def products(left: DataFrame, right: DataFrame, sizes: tuple[int, int | None, int], grid: tuple[int, int], half: bool = False, chosen: DataFrame | None = None, ahead: bool = False) -> DataFrame:
    """left (bi, k, r, s, v) and right (k, bj, r, s, v), blocks of sizes (p, q) and (q, w) on a grid of cells, to (bi, bj, i, j, total): the sums over slices of all
    entries that some slice has. q may be None: blocks then are as wide as the indices that both have. half: only cells with bi <= bj. chosen (bi, bj, k) has the slices that count; ahead drops the others before their
    products rather than after."""
    (p, q, w), (na, nb) = sizes, grid
    left = left.withColumn("bj", F.explode(F.sequence(F.col("bi") if half else F.lit(0), F.lit(nb - 1))))
    right = right.withColumn("bi", F.explode(F.sequence(F.lit(0), F.least(F.col("bj"), F.lit(na - 1)) if half else F.lit(na - 1))))
    if chosen is not None:
        few = chosen.count() <= SMALL
        counts = chosen.select("bi", "bj", "k", F.lit(True).alias("alive"))
        left = left.join(F.broadcast(counts) if few else counts, ["bi", "bj", "k"], "inner" if ahead else "left").fillna(False, ["alive"])
    else:
        left = left.withColumn("alive", F.lit(True))
    pairs = left.join(right.select("bi", "bj", "k", F.col("r").alias("r2"), F.col("s").alias("s2"), F.col("v").alias("v2")), ["bi", "bj", "k"])
    whole = all(df.schema["v"].dataType.elementType.typeName() in ("long", "integer") for df in (left, right))
    kind = "long" if whole else "double"
    schema = f"bi int, bj int, i long, at array<int>, total array<{kind}>"

    def multiplied(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            out = []
            for row in pdf.itertuples(index=False):
                s, r2, inner, one, two = row.s, row.r2, q, slice(None), slice(None)
                if q is None:
                    both = np.intersect1d(s, r2)
                    one, two, inner = np.isin(s, both), np.isin(r2, both), len(both)
                    s, r2 = np.searchsorted(both, s[one]), np.searchsorted(both, r2[two])
                (x, in_x), (y, in_y) = filled(row.r[one], s, row.v[one], p, inner), filled(r2, row.s2[two], row.v2[two], inner, w)
                z = _dot(x, y)
                if not row.alive:
                    continue  # computed, and not waited for
                on = np.ones(z.shape, bool) if z.size and inner and in_x.all() and in_y.all() else in_x.astype(np.float32) @ in_y.astype(np.float32) > 0
                for k in np.flatnonzero(on.any(1)):
                    at = np.flatnonzero(on[k])
                    out.append((row.bi, row.bj, row.bi * p + k, at.astype(np.int32), z[k, at]))
            yield pd.DataFrame(out, columns=["bi", "bj", "i", "at", "total"])

    partials = pairs.select("bi", "bj", "alive", "r", "s", "v", "r2", "s2", "v2").mapInPandas(multiplied, schema)
    return _summed(partials, kind, w)


def blocks_per_task(cells: int, width: int) -> int:
    """Blocks of `width` rows that one task holds: about twelve tasks' worth on a side, and at most 512 rows."""
    return max(1, min(512 // width, -(-cells // 12)))


def cells(left: DataFrame, right: DataFrame, slices: int, sizes: tuple[int, int, int], grid: tuple[int, int], half: bool = False, chosen: DataFrame | None = None, ahead: bool = False) -> DataFrame:
    """left (i, k, h, v) and right (k, h, j, v), stacked sketches with blocks of sizes (p, q) and (q, w) on a grid of cells, to (i, j, total, n_survivors): the sums
    over the slices that count. A task multiplies all slices of a square of cells. half: only cells with bi <= bj. chosen (bi, bj, k) has the slices
    that count; ahead drops those that count in no cell of the task before their products."""
    (p, q, w), (na, nb) = sizes, grid
    ga, gb = blocks_per_task(na, p), blocks_per_task(nb, w)
    if half:
        gb = ga
    tall, wide, inner = ga * p, gb * w, slices * q
    at = (F.col("k") * q + F.col("h")).cast("int")
    square = lambda c, n: F.floor(F.col(c) / n).cast("int")
    a = tiles(left, F.col("i") % tall, at, F.col("v"), square("i", tall).alias("gi"))
    b = tiles(right, at, F.col("j") % wide, F.col("v"), square("j", wide).alias("gj"))
    ta, tb = -(-na // ga), -(-nb // gb)
    a = a.withColumn("gj", F.explode(F.sequence(F.col("gi") if half else F.lit(0), F.lit(tb - 1))))
    b = b.withColumn("gi", F.explode(F.sequence(F.lit(0), F.least(F.col("gj"), F.lit(ta - 1)) if half else F.lit(ta - 1))))
    # Copies are made above the exchange that sizes are known of, so neither side may be broadcast.
    pairs = a.hint("merge").join(b.select("gi", "gj", F.col("r").alias("r2"), F.col("s").alias("s2"), F.col("v").alias("v2")), ["gi", "gj"])
    if chosen is not None:
        counts = chosen.groupBy(square("bi", ga).alias("gi"), square("bj", gb).alias("gj")).agg(F.collect_list(F.struct("bi", "bj", "k")).alias("e"))
        pairs = pairs.join(counts.select("gi", "gj", "e.bi", "e.bj", F.col("e.k").alias("k")).hint("merge"), ["gi", "gj"])
    else:
        none = F.array().cast("array<int>")
        pairs = pairs.select("*", none.alias("bi"), none.alias("bj"), none.alias("k"))
    whole = all(df.schema["v"].dataType.typeName() in ("long", "integer") for df in (left, right))
    kind, every = "long" if whole else "double", chosen is None

    def multiplied(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for row in pdf.itertuples(index=False):
                (x, in_x), (y, in_y) = filled(row.r, row.s, row.v, tall, inner), filled(row.r2, row.s2, row.v2, inner, wide)
                in_x, in_y = in_x.astype(np.float32), in_y.astype(np.float32)
                alive = np.full((slices, ga, gb), every)
                alive[row.k, row.bi - row.gi * ga, row.bj - row.gj * gb] = True
                if half:
                    alive &= (row.gi * ga + np.arange(ga))[:, None] <= (row.gj * gb + np.arange(gb))[None, :]
                total, has = np.zeros((tall, wide), np.int64 if whole else float), np.zeros((tall, wide), bool)
                for k in range(slices):
                    if ahead and not alive[k].any():
                        continue
                    of = slice(k * q, (k + 1) * q)
                    z, on = _dot(x[:, of], y[of]), in_x[:, of] @ in_y[of] > 0
                    counted = alive[k].repeat(p, 0).repeat(w, 1)
                    total += np.where(counted, z, 0)
                    has |= on & counted
                r, c = np.nonzero(has)
                yield pd.DataFrame({"i": row.gi * tall + r, "j": row.gj * wide + c, "total": total[r, c], "n_survivors": alive.sum(0)[r // p, c // w]})

    return pairs.select("gi", "gj", "bi", "bj", "k", "r", "s", "v", "r2", "s2", "v2").mapInPandas(multiplied, f"i long, j long, total {kind}, n_survivors long")


def linked(left: DataFrame, right: DataFrame, sizes: tuple[int, int, int], grid: tuple[int, int]) -> DataFrame:
    """left (i, c, v) and right (c, j, v) to (i, j, total), sums over the whole contraction, on a grid of cells of p by w. A task holds some bands of rows and some of
    columns; a right row goes only to the bands that have an entry for it. The dense products there are over q contracted indices at a time."""
    (p, q, w), (na, nb) = sizes, grid
    tall, wide = blocks_per_task(na, p) * p, blocks_per_task(nb, w) * w
    square = lambda c, n: F.floor(F.col(c) / n).cast("int")
    a = left.select(square("i", tall).alias("gi"), F.col("c"), (F.col("i") % tall).cast("int").alias("r"), "v").groupBy("gi", "c").agg(F.collect_list(F.struct("r", "v")).alias("e"))
    b = right.select("c", square("j", wide).alias("gj"), (F.col("j") % wide).cast("int").alias("s"), "v").groupBy("c", "gj").agg(F.collect_list(F.struct("s", "v")).alias("e"))
    pairs = a.hint("merge").join(b.select("c", "gj", F.col("e.s").alias("s"), F.col("e.v").alias("w")), "c")
    dealt = pairs.select("gi", "gj", "c", F.col("e.r").alias("r"), F.col("e.v").alias("v"), "s", "w").repartition("gi", "gj").sortWithinPartitions("gi", "gj", "c")
    whole = all(df.schema["v"].dataType.typeName() in ("long", "integer") for df in (left, right))
    kind = "long" if whole else "double"

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held, total, has = None, np.zeros((tall, wide), np.int64 if whole else float), np.zeros((tall, wide), bool)

        def done() -> pd.DataFrame:
            r, c = np.nonzero(has)
            out = pd.DataFrame({"i": held[0] * tall + r, "j": held[1] * wide + c, "total": total[r, c]})
            total[:], has[:] = 0, False
            return out

        for pdf in batches:
            for at, part in pdf.groupby(["gi", "gj"], sort=False):
                if held != at:
                    if held is not None:
                        yield done()
                    held = at
                for _, near in part.groupby(part["c"] // q, sort=False):
                    used = np.arange(len(near))
                    n, m = near["r"].map(len), near["s"].map(len)
                    x, in_x = filled(np.concatenate(near["r"].to_list()), used.repeat(n), np.concatenate(near["v"].to_list()), tall, len(near))
                    y, in_y = filled(used.repeat(m), np.concatenate(near["s"].to_list()), np.concatenate(near["w"].to_list()), len(near), wide)
                    total += _dot(x, y)
                    has |= in_x.astype(np.float32) @ in_y.astype(np.float32) > 0
        if held is not None:
            yield done()

    return dealt.mapInPandas(run, f"i long, j long, total {kind}")


def _packed(flat: np.ndarray, v: np.ndarray) -> bytes:
    """Entries by ascending place, as steps and values of few bytes."""
    order = np.argsort(flat)
    step, v = np.diff(flat[order], prepend=0), v[order]
    least = lambda x: x if x.dtype.kind == "f" else x.astype(np.result_type(np.min_scalar_type(x.min()), np.min_scalar_type(x.max())))
    return zlib.compress(pickle.dumps((least(step), least(v), v.dtype.str), 4), 1)


def _unpacked(data: bytes, rows: int, cols: int) -> tuple[np.ndarray, np.ndarray]:
    step, v, kind = pickle.loads(zlib.decompress(data))
    flat = np.cumsum(step.astype(np.int64))
    return filled(flat // cols, flat % cols, v.astype(kind), rows, cols)


def short_gram(entries: DataFrame, rows: int, cols: int, most: int = 2048) -> DataFrame:
    """entries (i, c, v) with few c to (i, j, total), all entries of the Gram matrix. A band of up to `most` rows is packed once and copied to every square that it is a
    side of; squares on and above the diagonal are multiplied, with the cells of their mirror images."""
    tall = max(1, min(most, -(-rows // 12)))
    bands = max(1, -(-rows // tall))
    whole = entries.schema["v"].dataType.typeName() in ("long", "integer")
    parts = entries.select(F.floor(F.col("i") / tall).cast("int").alias("g"), (F.col("i") % tall * cols + F.col("c")).alias("flat"), "v").repartition("g").sortWithinPartitions("g")

    def pack(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held, flat, v = None, [], []
        for pdf in batches:
            for g, part in pdf.groupby("g", sort=False):
                if g != held and flat:
                    yield pd.DataFrame({"g": [held], "data": [_packed(np.concatenate(flat), np.concatenate(v))]})
                    flat, v = [], []
                held = g
                flat.append(part["flat"].to_numpy())
                v.append(part["v"].to_numpy())
        if flat:
            yield pd.DataFrame({"g": [held], "data": [_packed(np.concatenate(flat), np.concatenate(v))]})

    packed = parts.mapInPandas(pack, "g int, data binary").withColumn("h", F.explode(F.sequence(F.lit(0), F.lit(bands - 1))))
    squares = packed.select(F.least("g", "h").alias("gi"), F.greatest("g", "h").alias("gj"), "g", "data")
    dealt = squares.repartition(min(bands * (bands + 1) // 2, 2000), "gi", "gj").sortWithinPartitions("gi", "gj", "g")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        side = None
        for pdf in batches:
            for row in pdf.itertuples(index=False):
                mine = _unpacked(row.data, tall, cols)
                if row.gi < row.gj and row.g == row.gi:
                    side = (row.gi, row.gj, *mine)
                    continue
                if row.gi < row.gj and (side is None or side[:2] != (row.gi, row.gj)):
                    continue  # the other band has no entries
                (x, in_x), (y, in_y) = (side[2:] if row.gi < row.gj else mine), mine
                total = _dot(x, y.T)
                has = total > 0 if (x[in_x] > 0).all() and (y[in_y] > 0).all() else in_x.astype(np.float32) @ in_y.T.astype(np.float32) > 0
                for first in range(0, tall, 128):
                    r, c = np.nonzero(has[first : first + 128])
                    i, j, v = row.gi * tall + first + r, row.gj * tall + c, total[first + r, c]
                    yield pd.DataFrame({"i": i, "j": j, "total": v})
                    if row.gi < row.gj:
                        yield pd.DataFrame({"i": j, "j": i, "total": v})

    return dealt.mapInPandas(run, f"i long, j long, total {'long' if whole else 'double'}")


def slice_sums(left: DataFrame, right: DataFrame, sizes: tuple[int, int, int]) -> DataFrame:
    """left (i, c, v) and right (c, j, v), whole numbers, to (bi, bj, k, n_entries, total): of each pair of blocks, how many cells their product has and their sum. A cell
    may have many rows. Both blocks of a contraction slice k meet in one task, so rows move once and products never do."""
    p, q, w = sizes
    place, dealt = (F.col("c") % q).cast("int"), lambda df: df.withColumn("k", F.floor(F.col("c") / q).cast("int")).drop("c").repartition("k")
    a = tiles(dealt(left.select(F.col("i").cast("int").alias("r"), place.alias("s"), "v", "c")), F.col("r"), F.col("s"), F.col("v"), F.col("k"))
    b = tiles(dealt(right.select(place.alias("r"), F.col("j").cast("int").alias("s"), "v", "c")), F.col("r"), F.col("s"), F.col("v"), F.col("k"))
    pairs = a.hint("merge").join(b.select("k", F.col("r").alias("r2"), F.col("s").alias("s2"), F.col("v").alias("v2")), "k")

    def starts(block: np.ndarray) -> np.ndarray:
        return np.flatnonzero(np.concatenate([[True], block[1:] != block[:-1]]))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for row in pdf.itertuples(index=False):
                both = np.intersect1d(row.s, row.r2)
                one, two = np.isin(row.s, both), np.isin(row.r2, both)
                if not len(both):
                    continue
                (i, r), (j, s2) = (np.unique(x, return_inverse=True) for x in (row.r[one], row.s2[two]))
                y, in_y = filled(np.searchsorted(both, row.r2[two]), s2, row.v2[two], len(both), len(j))
                bj, at_j = j // w, starts(j // w)
                y, in_y = np.add.reduceat(y, at_j, axis=1), in_y.astype(np.float32)
                s, v = np.searchsorted(both, row.s[one]), row.v[one]
                order = np.argsort(r, kind="stable")
                r, s, v = r[order], s[order], v[order]
                # Row blocks in runs, so that a slice with very many rows has only some of them dense at a time.
                edge = np.append(starts(i // p), len(i))
                for first in range(0, len(edge) - 1, 64):
                    cut = edge[first : first + 65]
                    lo, hi = np.searchsorted(r, (cut[0], cut[-1]))
                    x, in_x = filled(r[lo:hi] - cut[0], s[lo:hi], v[lo:hi], cut[-1] - cut[0], len(both))
                    at_i = cut[:-1] - cut[0]
                    cells = (in_x.astype(np.float32) @ in_y > 0).astype(np.int64)
                    n = np.add.reduceat(np.add.reduceat(cells, at_j, axis=1), at_i, axis=0)
                    total = _dot(np.add.reduceat(x, at_i, axis=0), y)
                    bi, on = i[cut[:-1]] // p, np.nonzero(n)
                    yield pd.DataFrame({"bi": bi[on[0]].astype(np.int32), "bj": bj[at_j][on[1]].astype(np.int32), "k": np.int32(row.k), "n_entries": n[on], "total": total[on]})

    return pairs.select("k", "r", "s", "v", "r2", "s2", "v2").mapInPandas(run, "bi int, bj int, k int, n_entries long, total long")


def squared_errors(left: DataFrame, right: DataFrame, exact: DataFrame, alive: DataFrame, seeds: list[int], es: list[int], slices: int, b: int, grid: tuple[int, int], half: bool = False) -> DataFrame:
    """left (seed, k, h, i, v) and right (seed, k, h, j, v), stacked sketches of width b under many seeds, exact (i, j, v) and alive (e, bi, bj, k) to
    (seed, e, err_sq, exact_sq) of each square of cells. half: cells with bi < bj count twice, those with bi > bj not."""
    na, nb = grid
    ga, gb = blocks_per_task(na, b), blocks_per_task(nb, b)
    if half:
        gb = ga
    tall, wide, inner = ga * b, gb * b, slices * b
    ta, tb = -(-na // ga), -(-nb // gb)
    at = (F.col("k") * b + F.col("h")).cast("int")
    square = lambda c, n: F.floor(F.col(c) / n).cast("int")
    x = tiles(left, F.col("i") % tall, at, F.col("v"), square("i", tall).alias("gi"), F.col("seed").cast("int").alias("seed"))
    y = tiles(right, at, F.col("j") % wide, F.col("v"), F.col("seed").cast("int").alias("seed"), square("j", wide).alias("gj"))
    x = x.withColumn("gj", F.explode(F.sequence(F.col("gi") if half else F.lit(0), F.lit(tb - 1))))
    y = y.withColumn("gi", F.explode(F.sequence(F.lit(0), F.least(F.col("gj"), F.lit(ta - 1)) if half else F.lit(ta - 1))))
    z = tiles(exact, F.col("i") % tall, F.col("j") % wide, F.col("v").cast("double"), square("i", tall).alias("gi"), square("j", wide).alias("gj"))
    if half:
        z = z.filter("gi <= gj")
    sets = alive.groupBy(square("bi", ga).alias("gi"), square("bj", gb).alias("gj")).agg(F.collect_list(F.struct("e", "bi", "bj", "k")).alias("a"))
    # Rows of four kinds meet by square: its cells' survivors, its exact entries, and its row and column sketches by seed.
    none, doubles = F.array().cast("array<int>"), "array<double>"
    ints = lambda c: F.col(c).cast("array<int>")
    parts = [
        sets.select("gi", "gj", F.lit(-2).alias("seed"), F.lit(0).alias("kind"), ints("a.bi").alias("r"), ints("a.bj").alias("s"), ints("a.k").alias("t"), F.col("a.e").cast(doubles).alias("v")),
        z.select("gi", "gj", F.lit(-1).alias("seed"), F.lit(1).alias("kind"), "r", "s", none.alias("t"), "v"),
        x.select("gi", "gj", F.lit(0).alias("seed") + F.col("seed"), F.lit(2).alias("kind"), "r", "s", none.alias("t"), F.col("v").cast(doubles).alias("v")),
        y.select("gi", "gj", F.lit(0).alias("seed") + F.col("seed"), F.lit(3).alias("kind"), "r", "s", none.alias("t"), F.col("v").cast(doubles).alias("v")),
    ]
    if min(seeds) < 0:
        raise ValueError("seeds are not negative")
    rows = parts[0].toDF(*"gi gj seed kind r s t v".split())
    for one in parts[1:]:
        rows = rows.unionByName(one.toDF(*rows.columns))
    dealt = rows.repartition("gi", "gj").sortWithinPartitions("gi", "gj", "seed", "kind")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held, keep, true, weight, sketch, todo = None, None, None, None, None, set()

        def errors(seed: int, u: np.ndarray | None, w: np.ndarray | None) -> pd.DataFrame:
            guess = np.zeros((len(es), tall, wide))
            for k in range(slices) if u is not None and w is not None else ():
                part = u[:, k * b : k * b + b] @ w[k * b : k * b + b]
                for n in range(len(es)):
                    if keep[n, k].any():
                        guess[n] += part * keep[n, k].repeat(b, 0).repeat(b, 1)
            number = np.maximum(keep.sum(1), 1).repeat(b, 1).repeat(b, 2)
            err = (weight * (true - guess / number) ** 2).sum((1, 2))
            return pd.DataFrame({"seed": seed, "e": es, "err_sq": err, "exact_sq": (weight * true * true).sum()})

        def ended() -> Iterator[pd.DataFrame]:
            for seed in sorted(todo):
                yield errors(seed, *((sketch[1], None) if sketch and sketch[0] == seed else (None, None)))

        for pdf in batches:
            for row in pdf.itertuples(index=False):
                if held != (row.gi, row.gj):
                    if held is not None:
                        yield from ended()
                    held, sketch, todo = (row.gi, row.gj), None, set(seeds)
                    keep, true = np.zeros((len(es), slices, ga, gb), bool), np.zeros((tall, wide))
                    bi, bj = (row.gi * ga + np.arange(ga))[:, None], (row.gj * gb + np.arange(gb))[None, :]
                    weight = (np.where(bi < bj, 2.0, np.where(bi == bj, 1.0, 0.0)) if half else np.ones((ga, gb))).repeat(b, 0).repeat(b, 1)
                if row.kind == 0:
                    keep[np.searchsorted(es, row.v.astype(int)), row.t, row.r - row.gi * ga, row.s - row.gj * gb] = True
                elif row.kind == 1:
                    true[row.r, row.s] = row.v
                elif row.kind == 2:
                    sketch = (row.seed, filled(row.r, row.s, row.v, tall, inner)[0])
                elif sketch and sketch[0] == row.seed:
                    todo.discard(row.seed)
                    yield errors(row.seed, sketch[1], filled(row.r, row.s, row.v, inner, wide)[0])
        if held is not None:
            yield from ended()

    return dealt.mapInPandas(run, "seed int, e int, err_sq double, exact_sq double")


def _summed(partials: DataFrame, kind: str, width: int) -> DataFrame:
    """(bi, bj, i, at, total) to entries (bi, bj, i, j, total): rows of one cell meet in one task, in order, and are added up one run at a time."""
    dealt = partials.repartition("bj", "i").sortWithinPartitions("bj", "i")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held, acc, has = None, np.zeros(width, np.int64 if kind == "long" else float), np.zeros(width, bool)

        def done(out: list) -> None:
            at = np.flatnonzero(has)
            out.append((np.full(len(at), held[0]), np.full(len(at), held[1]), np.full(len(at), held[2]), held[1] * width + at, acc[at]))

        def framed(out: list) -> pd.DataFrame:
            columns = [np.concatenate(c) for c in zip(*out, strict=True)]
            return pd.DataFrame(dict(zip(("bi", "bj", "i", "j", "total"), columns, strict=True)))

        for pdf in batches:
            out = []
            for bi, bj, i, at, total in zip(pdf["bi"], pdf["bj"], pdf["i"], pdf["at"], pdf["total"], strict=True):
                if held != (bi, bj, i):
                    if held is not None:
                        done(out)
                    held = (bi, bj, i)
                    acc[:] = 0
                    has[:] = False
                acc[at] += total
                has[at] = True
            if out:
                yield framed(out)
        if held is not None:
            out = []
            done(out)
            yield framed(out)

    return dealt.mapInPandas(run, f"bi int, bj int, i long, j long, total {kind}")
