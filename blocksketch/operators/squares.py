"""Gram matrices of very many rows by squares. Rows are packed by strips, each once, from entries that move once; a strip is copied to the squares that it is a side of. Products of entries,
sketched products, their errors and their survivors are made strip by strip within a square, so no product moves and a task holds one side of its square."""

from __future__ import annotations

import pickle
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import HashFamily, P
from .kernel import _dot, _packed, _unpacked
from .losses import Losses

#: Rows of a strip and strips of a square's side, at most.
STRIP, SIDE = 512, 16
_PATCH, _COLUMN, _ROW = 0, 1, 2
_ENTRIES, _SKETCH = 0, 1
_STRIPS = "g int, kind int, seed int, data binary"


def sides(rows: int, width: int, bands: int = 6) -> tuple[int, int]:
    """Rows of a strip, a multiple of the width, and strips of a side: about so many sides as long as none has more than SIDE strips."""
    strip = max(1, min(STRIP // width, -(-rows // (12 * width)))) * width
    return strip, max(1, min(SIDE, -(-rows // (bands * strip))))


def _whole(df: DataFrame) -> bool:
    return df.schema["v"].dataType.typeName() in ("long", "integer", "short", "byte")


def _bucket_sign(c: np.ndarray, row: tuple[int, ...], width: int) -> tuple[np.ndarray, np.ndarray]:
    _, u1, u0, w3, w2, w1, w0 = row
    q = w3 * c % P
    for w in (w2, w1):
        q = (q + w) % P * c % P
    return (u1 * c + u0) % P % width, 1 - 2 * ((q + w0) % P % 2)


def strips(entries: DataFrame, strip: int, width: int, families: list[HashFamily], keep: bool) -> DataFrame:
    """entries (i, c, v) to packed strips (g, kind, seed, data): the stacked sketch under each family, of the slices side by side, and with `keep` the entries by column."""
    whole = _whole(entries)
    dealt = entries.select(F.floor(F.col("i") / strip).cast("int").alias("g"), (F.col("i") % strip).cast("int").alias("r"), "c", F.col("v").cast("long" if whole else "double").alias("v"))
    dealt = dealt.repartition("g").sortWithinPartitions("g")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, parts = None, []

        def done() -> Iterator[pa.RecordBatch]:
            r, c, v = (np.concatenate(x) for x in zip(*parts, strict=True))
            order = np.argsort(c, kind="stable")
            r, c, v = r[order], c[order], v[order]
            first = np.concatenate([[True], c[1:] != c[:-1]])
            columns, of = c[first], np.cumsum(first) - 1
            if keep:
                yield made(_ENTRIES, -1, _packed_columns(c, r, v))
            exact = whole and float(np.abs(v).astype(float).sum()) >= float(1 << 53)
            for f in families:
                cells = f.slices * width
                acc, has = np.zeros(strip * cells, np.int64 if whole else float), np.zeros(strip * cells, bool)
                for row in f.rows:
                    h, s = (x[of] for x in _bucket_sign(columns, row, width))
                    flat = r.astype(np.int64) * cells + row[0] * width + h
                    has[flat] = True
                    if exact:
                        np.add.at(acc, flat, s * v)
                    else:
                        n = strip * cells
                        acc += np.bincount(flat, s * v, n).astype(acc.dtype)
                at = np.flatnonzero(has)
                yield made(_SKETCH, f.seed, _packed(at, acc[at]))

        def made(kind: int, seed: int, data: bytes) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([held], pa.int32()), pa.array([kind], pa.int32()), pa.array([seed], pa.int32()), pa.array([data], pa.binary())], ["g", "kind", "seed", "data"])

        for batch in batches:
            g, r, c, v = (x.to_numpy(zero_copy_only=False) for x in batch.columns)
            edge = np.flatnonzero(np.concatenate([[True], g[1:] != g[:-1]])) if len(g) else np.zeros(0, int)
            for a, b in zip(edge, [*edge[1:], len(g)], strict=True):
                if held != g[a]:
                    if parts:
                        yield from done()
                    held, parts = int(g[a]), []
                parts.append((r[a:b].astype(np.int32), c[a:b].copy(), v[a:b].copy()))
        if parts:
            yield from done()

    return dealt.mapInArrow(run, _STRIPS)


def _packed_columns(c: np.ndarray, r: np.ndarray, v: np.ndarray) -> bytes:
    """Entries by ascending column."""
    step = np.diff(c, prepend=0)
    least = lambda x: x if x.dtype.kind == "f" else x.astype(np.result_type(np.min_scalar_type(x.min()), np.min_scalar_type(x.max())))
    return zlib.compress(pickle.dumps((least(step), least(r), least(v)), 4), 1)


def _columns(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    step, r, v = pickle.loads(zlib.decompress(data))
    return np.cumsum(step.astype(np.int64)), r, v


def projected_strips(sketch: DataFrame, strip: int, width: int) -> DataFrame:
    """A sketch (i, r, v) as packed strips."""
    one = sketch.select(F.floor(F.col("i") / strip).cast("int").alias("g"), (F.col("i") % strip * width + F.col("r")).cast("long").alias("flat"), F.col("v").cast("double").alias("v")).groupBy("g").agg(F.collect_list(F.struct("flat", "v")).alias("e"))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for row in pdf.itertuples(index=False):
                yield pd.DataFrame({"g": [row.g], "kind": _SKETCH, "seed": 0, "data": [_packed(row.flat.astype(np.int64), row.v)]})

    return one.select("g", "e.flat", "e.v").mapInPandas(run, _STRIPS)


def dealt(packed: DataFrame, rows: int, strip: int, side: int, patches: DataFrame | None = None) -> DataFrame:
    """Squares on and above the diagonal with what they need, in order: survivors' patches, the strips of their columns, the strips of their rows."""
    n = -(-rows // (strip * side))
    band = F.floor(F.col("g") / side).cast("int")
    each = packed.withColumn("b", band).withColumn("o", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    role = F.when(F.col("b") == F.col("o"), F.array(F.lit(_COLUMN), F.lit(_ROW))).when(F.col("b") < F.col("o"), F.array(F.lit(_ROW))).otherwise(F.array(F.lit(_COLUMN)))
    out = each.select(F.least("b", "o").alias("gi"), F.greatest("b", "o").alias("gj"), F.explode(role).alias("role"), "g", "kind", "seed", F.lit(0).cast("long").alias("size"), "data")
    if patches is not None:
        none = F.lit(0)
        out = out.unionByName(patches.select("gi", "gj", F.lit(_PATCH).alias("role"), F.col("n").alias("g"), none.alias("kind"), none.alias("seed"), "size", "data"))
    at = (F.col("gi") * F.lit(n).cast("long") - F.col("gi") * (F.col("gi") + 1) / 2).cast("long") + F.col("gj")
    out = out.withColumn("q", at)
    return out.repartitionById(min(n * (n + 1) // 2, 4000), (F.col("q") % min(n * (n + 1) // 2, 4000)).cast("int")).sortWithinPartitions("q", "role", "g", "kind", "seed").drop("q")


class _Side:
    """The strips of a square's columns."""

    def __init__(self):
        self.sketches: dict[tuple[int, int], bytes] = {}
        self.entries: dict[int, tuple] = {}
        self._merged: tuple | None = None

    def merged(self, first: int, strip: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """The entries of all strips by contracted index: the indices, where each one's entries start, their columns within the square, their values."""
        if self._merged is None:
            c = np.concatenate([x[0] for x in self.entries.values()])
            order = np.argsort(c, kind="stable")
            c = c[order]
            place = np.concatenate([x[1].astype(np.int32) + (g - first) * strip for g, x in self.entries.items()])[order]
            v = np.concatenate([x[2] for x in self.entries.values()])[order]
            new = np.flatnonzero(np.concatenate([[True], c[1:] != c[:-1]]))
            self._merged = c[new], np.append(new, len(c)), place, v
            self.entries = dict.fromkeys(self.entries)
        return self._merged


def _squares(batches: Iterator[pd.DataFrame]) -> Iterator[tuple]:
    """(gi, gj, patches, columns, g, sketches by seed, entries) for each strip of rows of each square; patches are None after its first."""
    at, patches, side, strip = None, [], _Side(), None

    for pdf in batches:
        for row in pdf.itertuples(index=False):
            if at != (row.gi, row.gj):
                if strip is not None:
                    yield (*at, patches, side, *strip)
                at, patches, side, strip = (row.gi, row.gj), [], _Side(), None
            if row.role == _PATCH:
                patches.append((row.g, row.size, row.data))
            elif row.role == _COLUMN:
                if row.kind == _ENTRIES:
                    side.entries[row.g] = _columns(row.data)
                else:
                    side.sketches[row.g, row.seed] = row.data
            else:
                if strip is not None and strip[0] != row.g:
                    yield (*at, patches, side, *strip)
                    patches, strip = None, None
                strip = strip or (row.g, {}, [None])
                if row.kind == _ENTRIES:
                    strip[2][0] = _columns(row.data)
                else:
                    strip[1][row.seed] = row.data
    if strip is not None:
        yield (*at, patches, side, *strip)


def _products(own: tuple, side: _Side, first: int, strip: int, strips: int) -> np.ndarray:
    """Products of a strip's entries and those of all the square's columns, by pairs that share a contracted index."""
    columns, start, place, v = side.merged(first, strip)
    c, r, mine = own
    at = np.minimum(np.searchsorted(columns, c), len(columns) - 1)
    n = np.where(columns[at] == c, start[at + 1] - start[at], 0)
    total, ends, lo = np.zeros(strip * strips * strip), np.cumsum(n), 0
    while lo < len(n):
        hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + (1 << 20), "right")))
        m = n[lo:hi]
        if m.any():
            pair = np.arange(m.sum()) + (start[at[lo:hi]] - np.cumsum(m) + m).repeat(m)
            np.add.at(total, r[lo:hi].astype(np.int64).repeat(m) * (strips * strip) + place[pair], mine[lo:hi].astype(float).repeat(m) * v[pair])
        lo = hi
    return total.reshape(strip, strips * strip)


def sketched_gram(entries: DataFrame, rows: int, width: int, family: HashFamily, losses: Losses, ahead: bool = False) -> DataFrame:
    """(i, j, v_hat, n_survivors): the sketched Gram matrix of entries (i, c, v), with the first set of `losses`. ahead: slices that count in no cell of two strips are left out before their products."""
    strip, side = sides(rows, width, 12)
    ga, k, inner = strip * side // width, family.slices, family.slices * width
    read, per = losses.reader(ga, ga), strip // width
    packed = dealt(strips(entries, strip, width, [family], False), rows, strip, side, losses.ranked(ga, ga, True))
    names = ["i", "j", "v_hat", "n_survivors"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        moved = {}

        def out(i: np.ndarray, j: np.ndarray, v: np.ndarray, n: np.ndarray) -> Iterator[pa.RecordBatch]:
            for at in range(0, len(i), 1 << 16):
                x = slice(at, at + (1 << 16))
                yield pa.RecordBatch.from_arrays([pa.array(i[x]), pa.array(j[x]), pa.array(v[x]), pa.array(n[x])], names)

        for gi, gj, patches, columns, g, sketches, _ in _squares(x.to_pandas() for x in batches):
            if patches is not None:
                moved = read.moved(patches)
            x, in_x = _unpacked(sketches[family.seed], strip, inner)
            lo = (g - gi * side) * per
            keep = read.keep(gi, gj, lo, lo + per, moved)[0]
            for t in sorted(h for h, _ in columns.sketches if h >= g):
                y, in_y = (z.T for z in _unpacked(columns.sketches[t, family.seed], strip, inner))
                alive = keep[:, (t - gj * side) * per : (t - gj * side + 1) * per]
                if t == g:
                    alive = alive & np.triu(np.ones((per, per), bool))[:, :, None]
                full = in_x.all() and in_y.all()
                total, has = np.zeros((strip, strip), np.int64 if x.dtype.kind != "f" else float), np.zeros((strip, strip), bool)
                for s in range(k):
                    if ahead and not alive[:, :, s].any():
                        continue
                    of = slice(s * width, (s + 1) * width)
                    counted = alive[:, :, s].repeat(width, 0).repeat(width, 1)
                    total += _dot(x[:, of], y[of]) * counted
                    has |= counted if full else counted & (in_x[:, of].astype(np.float32) @ in_y[of].astype(np.float32) > 0)
                r, c = np.nonzero(has)
                n = alive.sum(2)[r // width, c // width]
                i, j, v = g * strip + r, t * strip + c, total[r, c].astype(float) / n
                yield from out(i, j, v, n)
                other = i // width < j // width
                yield from out(j[other], i[other], v[other], n[other])

    return packed.mapInArrow(run, "i long, j long, v_hat double, n_survivors long")


def _errors_by_sums(true: np.ndarray, left: np.ndarray, right: np.ndarray, share: np.ndarray, weight: np.ndarray, width: int) -> np.ndarray:
    """The weighted squared error of a strip by a strip for each set; share (set, row, column, slice) is what a slice counts in a cell. For few sets."""
    strip, low, sets = len(true), max(1, 64 // width), range(len(share))
    part, err = share.transpose(0, 3, 1, 2).repeat(width, 3), np.zeros(len(share))
    for cells in (slice(c, min(c + low, len(weight))) for c in range(0, len(weight), low)):
        rows = slice(cells.start * width, cells.stop * width)
        rest = np.repeat(true[rows].reshape(1, -1, width, strip), len(share), 0)
        for k in range(share.shape[3]):
            p = (left[rows, k * width : (k + 1) * width] @ right[k * width : (k + 1) * width]).reshape(-1, width, strip)
            for e in sets:
                rest[e] -= p * part[e, k, cells][:, None, :]
        rest *= rest
        err += (rest.sum(2) * weight[cells].repeat(width, 1)).sum((1, 2))
    return err


def _errors_by_cells(true: np.ndarray, left: np.ndarray, right: np.ndarray, share: np.ndarray, weight: np.ndarray, width: int) -> np.ndarray:
    """The same from the inner products of each cell's exact block and slices, so that the work hardly grows with the sets."""
    per, k = len(weight), share.shape[3]
    apart = lambda x: x.reshape(per, width, per, width).transpose(0, 2, 1, 3)
    blocks = np.empty((per, per, k + 1, width, width))
    blocks[:, :, 0] = apart(true)
    for n in range(k):
        blocks[:, :, n + 1] = apart(left[:, n * width : (n + 1) * width] @ right[n * width : (n + 1) * width])
    blocks = blocks.reshape(per * per, k + 1, width * width)
    by = np.concatenate([np.ones((per * per, 1, len(share))), -share.transpose(1, 2, 3, 0).reshape(per * per, k, -1)], 1)
    each = ((blocks @ blocks.transpose(0, 2, 1) @ by) * by).sum(1)
    return (np.maximum(each, 0) * weight.reshape(-1, 1)).sum(0)


def gram_errors(entries: DataFrame, rows: int, width: int, families: list[HashFamily], losses: Losses) -> DataFrame:
    """(seed, e, err_sq, exact_sq), one row a task: of the sketched Gram matrices under each family and set of losses, the squared error, and the squared norm of the exact one."""
    strip, side = sides(rows, width)
    ga, per, es = strip * side // width, strip // width, [e for e, _, _ in losses.sets]
    k, inner = families[0].slices, families[0].slices * width
    read, seeds = losses.reader(ga, ga), [f.seed for f in families]
    packed = dealt(strips(entries, strip, width, families, True), rows, strip, side, losses.ranked(ga, ga, True))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        moved, err, norm = {}, np.zeros((len(seeds), len(es))), 0.0
        for gi, gj, patches, columns, g, sketches, own in _squares(batches):
            if patches is not None:
                moved = read.moved(patches)
            first = (g - gi * side) * per
            keep = read.keep(gi, gj, first, first + per, moved)
            left = {s: _unpacked(sketches[s], strip, inner)[0].astype(float) for s in seeds}
            todo = sorted(h for h in columns.entries if h >= g)
            every = _products(own[0], columns, gj * side, strip, side) if todo else None
            for t in todo:
                true = np.ascontiguousarray(every[:, (t - gj * side) * strip : (t - gj * side + 1) * strip])
                weight = np.full((per, per), 2.0) if t > g else np.triu(np.full((per, per), 2.0), 1) + np.eye(per)
                alive = keep[:, :, (t - gj * side) * per : (t - gj * side + 1) * per]
                share = alive / np.maximum(alive.sum(3, keepdims=True), 1)
                norm += float((weight.repeat(width, 1)[:, None, :] * (true * true).reshape(per, width, strip)).sum())
                for n, s in enumerate(seeds):
                    right = np.ascontiguousarray(_unpacked(columns.sketches[t, s], strip, inner)[0].T.astype(float))
                    err[n] += (_errors_by_sums if len(es) < 3 else _errors_by_cells)(true, left[s], right, share, weight, width)
        yield pd.DataFrame([(s, e, err[n, m], norm) for n, s in enumerate(seeds) for m, e in enumerate(es)], columns=["seed", "e", "err_sq", "exact_sq"])

    return packed.select("gi", "gj", "role", "g", "kind", "seed", "size", "data").mapInPandas(run, "seed int, e int, err_sq double, exact_sq double")


def gram_against(entries: DataFrame, sketch: DataFrame, rows: int, width: int) -> DataFrame:
    """entries (i, c, v) of A and its sketch S (i, r, v), r below `width`, to one row (exact_sq, cross, guess_sq): the squared norms of A A^T and S S^T and their inner product.
    The error between the two is exact_sq - 2 cross + guess_sq; S S^T is only multiplied with A A^T where it is made, and its norm is that of S^T S."""
    strip, side = sides(rows, 64)
    packed = dealt(strips(entries, strip, 1, [], True).unionByName(projected_strips(sketch, strip, width)), rows, strip, side)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        exact, cross, small = 0.0, 0.0, np.zeros((width, width))
        for gi, gj, _, columns, g, sketches, own in _squares(batches):
            x = _unpacked(sketches[0], strip, width)[0]
            if gi == gj:
                small += x.T @ x
            todo = sorted(h for h in columns.entries if h >= g)
            every = _products(own[0], columns, gj * side, strip, side) if todo else None
            for t in todo:
                total, twice = every[:, (t - gj * side) * strip : (t - gj * side + 1) * strip], 1 if t == g else 2
                exact += twice * float((total * total).sum())
                cross += twice * float((total * (x @ _unpacked(columns.sketches[t, 0], strip, width)[0].T)).sum())
        yield pd.DataFrame({"key": np.arange(width * width + 2), "x": [*small.ravel(), exact, cross]})

    sums = packed.mapInPandas(run, "key int, x double").groupBy("key").agg(F.sum("x").alias("x"))
    of = lambda n: F.sum(F.when(F.col("key") == width * width + n, F.col("x")))
    return sums.agg(of(0).alias("exact_sq"), of(1).alias("cross"), F.sum(F.when(F.col("key") < width * width, F.col("x") * F.col("x"))).alias("guess_sq"))
