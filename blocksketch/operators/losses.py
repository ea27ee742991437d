"""Which slices count in each cell by simulated logs of very many tasks. A log is not a DataFrame here: a task's time follows from its place among all hashes, which a histogram gives
for nearly all of them. Only tasks in histogram bins that hold several times are ranked, and only their times move, to the square of cells that asks for them."""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import P
from . import straggler
from .straggler import Policy

#: Tasks hashed at a time, tasks by stripe of the grid, and tasks that are ranked together.
CHUNK, STRIPE, RANKED = 1 << 18, 1 << 22, 1 << 20
_MIXED = 0xFFFF


def _fold(x: np.ndarray) -> np.ndarray:
    """Remainders by 2^31 - 1 of numbers up to the square of 2^31 - 2."""
    x = (x & P) + (x >> 31)
    x -= P * (x >= P)
    return x


def hashed(bi: np.ndarray, bj: np.ndarray, k: int, w: list[int]) -> np.ndarray:
    """The hashes that a log's tasks are ranked by, of all bi by bj by k."""
    x = _fold(bi.astype(np.int64)[:, None, None] * 1000003 + bj.astype(np.int64)[None, :, None] * 1009 + np.arange(k)[None, None, :])
    q = _fold(w[0] * x)
    for y in w[1:3]:
        q = _fold(_fold(q + y) * x)
    return _fold(q + w[3])


@dataclass(frozen=True)
class Shape:
    """A log's numbers: `codes` stand for the times of log_sql, in their order."""

    bi: int
    bj: int
    k: int

    @property
    def total(self) -> int:
        return self.bi * self.bj * self.k

    @property
    def bits(self) -> int:
        return min(20, max(4, self.total.bit_length() - 2))

    def codes(self, rank: np.ndarray) -> np.ndarray:
        out, slow = 2 * self.total // 3000, self.total * 5 // 100
        usual = (rank - slow) * 20001 // max(self.total - slow, 1)
        return np.where(rank < out, 30002, np.where(rank < slow, 20001 + rank * 7919 % 10001, usual)).astype(np.uint16)

    def uniform(self, first: np.ndarray, last: np.ndarray) -> np.ndarray:
        """Whether all ranks from first to last have one time."""
        out, slow = 2 * self.total // 3000, self.total * 5 // 100
        return (first >= last) | (last < out) | ((first >= slow) & (self.codes(first) == self.codes(last)))


def times(codes: np.ndarray) -> np.ndarray:
    codes = codes.astype(np.int64)
    return np.where(codes > 30001, 375_000, np.where(codes > 20000, 95_000 - 20001 + codes, 30_000 + codes))


def _stripe(shape: Shape, n: int, stripes: int) -> Iterator[tuple[np.ndarray, int]]:
    """Row blocks of the n-th stripe, some at a time, with the number of the first task."""
    lo, hi = n * shape.bi // stripes, (n + 1) * shape.bi // stripes
    step = max(1, CHUNK // (shape.bj * shape.k))
    for at in range(lo, hi, step):
        yield np.arange(at, min(at + step, hi)), at * shape.bj * shape.k


@dataclass
class Losses:
    """Survivors of several logs over one grid: sets (e, slices, policy). Policies are those of straggler.survivors."""

    spark: SparkSession
    bi: int
    bj: int
    sets: list[tuple[int, int, Policy]]
    seed: int = 1
    bits: int | None = None
    _tables: list = field(default_factory=list)

    @property
    def slices(self) -> int:
        return max(k for _, k, _ in self.sets)

    def frame(self) -> DataFrame:
        """The same as a DataFrame (e, bi, bj, k), by the log in SQL."""
        out = None
        for e, k, policy in self.sets:
            one = straggler.survivors(straggler.task_log(self.spark, self.bi, self.bj, k, self.seed), policy).select(F.lit(e).alias("e"), "bi", "bj", "k")
            out = one if out is None else out.union(one)
        return out

    def select(self, *names: str) -> DataFrame:
        return self.frame().select(*names)

    def _work(self) -> tuple[DataFrame, list[Shape], list[int]]:
        shapes = [Shape(self.bi, self.bj, k) for _, k, _ in self.sets]
        stripes = [max(1, min(s.bi, 64, -(-s.total // STRIPE))) for s in shapes]
        n = max(1, sum(stripes))
        return self.spark.range(0, n, 1, min(n, 200)), shapes, stripes

    def _bits(self, shape: Shape) -> int:
        return self.bits or shape.bits

    def tables(self) -> list[tuple[bytes, np.ndarray, np.ndarray, np.ndarray]]:
        """Of each log: the codes of its bins, packed; the bins that hold several times, with the rank that each begins at; and the part that each is ranked in."""
        if self._tables:
            return self._tables
        work, shapes, stripes = self._work()
        ends, w, bits = np.cumsum(stripes), straggler._draws(self.seed), [self._bits(s) for s in shapes]

        def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                for x in pdf["id"]:
                    n = int(np.searchsorted(ends, x, "right"))
                    s, found = shapes[n], np.zeros(1 << bits[n], np.int32)
                    for rows, _ in _stripe(s, int(x - ends[n] + stripes[n]), stripes[n]):
                        found += np.bincount(hashed(rows, np.arange(s.bj), s.k, w).ravel() >> (31 - bits[n]), minlength=len(found)).astype(np.int32)
                    yield pd.DataFrame([(n, p, zlib.compress(part.tobytes(), 1)) for p, part in enumerate(np.split(found, 16))], columns=["n", "p", "data"])

        def add(pdf: pd.DataFrame) -> pd.DataFrame:
            total = sum(np.frombuffer(zlib.decompress(x), np.int32).astype(np.int64) for x in pdf["data"])
            return pd.DataFrame({"n": pdf["n"].iloc[:1], "p": pdf["p"].iloc[:1], "data": [zlib.compress(total.tobytes(), 1)]})

        kind = "n int, p int, data binary"
        got = sorted(map(tuple, work.mapInPandas(count, kind).groupBy("n", "p").applyInPandas(add, kind).collect()))
        for n, s in enumerate(shapes):
            counts = np.concatenate([np.frombuffer(zlib.decompress(x[2]), np.int64) for x in got if x[0] == n])
            first = np.cumsum(counts) - counts
            mixed = ~s.uniform(first, first + counts - 1)
            at = np.flatnonzero(mixed)
            codes = np.where(mixed, np.uint16(_MIXED), s.codes(first))
            self._tables.append((zlib.compress(codes.tobytes(), 1), at, first[at], (np.cumsum(counts[at]) - counts[at]) // RANKED))
        return self._tables

    def ranked(self, ga: int, gb: int, half: bool) -> DataFrame:
        """(gi, gj, n, data): for each square of ga by gb cells, the tasks of log n whose codes are not those of their bins. half: only squares with gi <= gj."""
        tables, w = self.tables(), straggler._draws(self.seed)
        work, shapes, stripes = self._work()
        ends, bits = np.cumsum(stripes), [self._bits(s) for s in shapes]

        def pick(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                for x in pdf["id"]:
                    n = int(np.searchsorted(ends, x, "right"))
                    s, (packed, bins, _, part) = shapes[n], tables[n]
                    mixed = np.frombuffer(zlib.decompress(packed), np.uint16) == _MIXED
                    out: dict[int, list] = {}
                    stripe = int(x - ends[n] + stripes[n])
                    for rows, start in _stripe(s, stripe, stripes[n]):
                        h = hashed(rows, np.arange(s.bj), s.k, w).ravel()
                        at = np.flatnonzero(mixed[h >> (31 - bits[n])])
                        h = h[at]
                        of = part[np.searchsorted(bins, h >> (31 - bits[n]))]
                        for p in np.unique(of):
                            out.setdefault(int(p), []).append((at[of == p] + start, h[of == p]))
                    for p, found in out.items():
                        place, h = (np.concatenate(c) for c in zip(*found, strict=True))
                        yield pd.DataFrame({"n": [n], "p": [p], "data": [zlib.compress(np.diff(place, prepend=0).tobytes(), 1) + h.astype(np.uint32).tobytes()], "size": [len(h)]})

        def rank(pdf: pd.DataFrame) -> pd.DataFrame:
            n = int(pdf["n"].iloc[0])
            s, (_, bins, first, _) = shapes[n], tables[n]
            place = np.concatenate([np.cumsum(np.frombuffer(zlib.decompress(x[: len(x) - 4 * m]), np.int64)) for x, m in zip(pdf["data"], pdf["size"], strict=True)])
            h = np.concatenate([np.frombuffer(x[len(x) - 4 * m :], np.uint32) for x, m in zip(pdf["data"], pdf["size"], strict=True)]).astype(np.int64)
            order = np.lexsort((place, h))
            place, of = place[order], np.searchsorted(bins, h[order] >> (31 - bits[n]))
            code = s.codes(first[of] + np.arange(len(of)) - np.searchsorted(of, of))
            bi, bj, k = place // (s.bj * s.k), place // s.k % s.bj, place % s.k
            gi, gj = bi // ga, bj // gb
            at = ((bi - gi * ga) * gb + bj - gj * gb) * s.k + k
            if half:
                upper = gi <= gj
                gi, gj, at, code = gi[upper], gj[upper], at[upper], code[upper]
            order = np.lexsort((at, gj, gi))
            gi, gj, at, code = gi[order], gj[order], at[order], code[order]
            edge = np.flatnonzero(np.concatenate([[True], (gi[1:] != gi[:-1]) | (gj[1:] != gj[:-1])])) if len(gi) else np.zeros(0, int)
            rows = [(int(gi[a]), int(gj[a]), n, len(at[a:b]), zlib.compress(np.diff(at[a:b], prepend=0).astype(np.uint32).tobytes(), 1) + code[a:b].tobytes()) for a, b in zip(edge, [*edge[1:], len(gi)], strict=True)]
            return pd.DataFrame(rows, columns=["gi", "gj", "n", "size", "data"])

        return work.mapInPandas(pick, "n int, p int, data binary, size long").groupBy("n", "p").applyInPandas(rank, "gi int, gj int, n int, size long, data binary")

    def reader(self, ga: int, gb: int) -> Reader:
        return Reader(self.bi, self.bj, ga, gb, [(k, p) for _, k, p in self.sets], self.slices, straggler._draws(self.seed), [(t[0], self._bits(Shape(self.bi, self.bj, k))) for t, (_, k, _) in zip(self.tables(), self.sets, strict=True)], self._shared())

    def _shared(self) -> dict[int, list[int]]:
        """The slices of logs with a shared policy: those whose slowest task over all cells ended first."""
        which = [n for n, (_, _, p) in enumerate(self.sets) if p.kind == "shared"]
        if not which:
            return {}
        ga = gb = 512
        read = Reader(self.bi, self.bj, ga, gb, [(k, p) for _, k, p in self.sets], self.slices, straggler._draws(self.seed), [(t[0], self._bits(Shape(self.bi, self.bj, k))) for t, (_, k, _) in zip(self.tables(), self.sets, strict=True)], {})
        ta, tb = -(-self.bi // ga), -(-self.bj // gb)
        every = self.spark.range(0, ta * tb, 1, min(ta * tb, 200)).select((F.col("id") / tb).cast("int").alias("gi"), (F.col("id") % tb).cast("int").alias("gj"), F.lit(-1).alias("n"), F.lit(0).cast("long").alias("size"), F.lit(None).cast("binary").alias("data"))

        def slowest(pdf: pd.DataFrame) -> pd.DataFrame:
            gi, gj = int(pdf["gi"].iloc[0]), int(pdf["gj"].iloc[0])
            moved = read.moved(x for x in zip(pdf["n"], pdf["size"], pdf["data"], strict=True) if x[0] >= 0)
            out = []
            for n in which:
                worst = np.full(read.sets[n][0], -1)
                for lo in range(0, ga, 32):
                    c = read.codes(n, gi, gj, lo, min(lo + 32, ga), moved)
                    if c.size:
                        worst = np.maximum(worst, c.reshape(-1, c.shape[2]).astype(int).max(0))
                out += [(n, k, int(x)) for k, x in enumerate(worst)]
            return pd.DataFrame(out, columns=["n", "k", "worst"])

        got = every.unionByName(self.ranked(ga, gb, False)).groupBy("gi", "gj").applyInPandas(slowest, "n int, k int, worst int").groupBy("n", "k").agg(F.max("worst").alias("worst")).collect()
        return {n: [r.k for r in sorted((r for r in got if r.n == n), key=lambda r: (r.worst, r.k))][: self.sets[n][2].n] for n in which}


@dataclass
class Reader:
    """Survivors of a square's cells, in the task that has the square."""

    bi: int
    bj: int
    ga: int
    gb: int
    sets: list[tuple[int, Policy]]
    slices: int
    w: list[int]
    packed: list[tuple[bytes, int]]
    shared: dict[int, list[int]]

    def __post_init__(self):
        self.held: dict[int, np.ndarray] = {}

    def moved(self, rows) -> dict[int, tuple[np.ndarray, np.ndarray]]:
        """Rows (n, size, data) of Losses.ranked to places and codes by log."""
        out: dict[int, list] = {}
        for n, m, x in rows:
            out.setdefault(int(n), []).append((np.cumsum(np.frombuffer(zlib.decompress(x[: len(x) - 2 * m]), np.uint32).astype(np.int64)), np.frombuffer(x[len(x) - 2 * m :], np.uint16)))
        whole = {n: tuple(np.concatenate(c) for c in zip(*parts, strict=True)) for n, parts in out.items()}
        return {n: (at[o], code[o]) for n, (at, code) in whole.items() for o in [np.argsort(at)]}

    def codes(self, n: int, gi: int, gj: int, lo: int, hi: int, moved: dict) -> np.ndarray:
        """Of log n, the codes of the square's rows of cells lo to hi, as far as the grid goes."""
        if n not in self.held:
            self.held[n] = np.frombuffer(zlib.decompress(self.packed[n][0]), np.uint16)
        k, bits = self.sets[n][0], self.packed[n][1]
        rows, cols = np.arange(gi * self.ga + lo, min(gi * self.ga + hi, self.bi)), np.arange(gj * self.gb, min((gj + 1) * self.gb, self.bj))
        out = np.empty((max(len(rows), 0), len(cols), k), np.uint16)
        step = max(1, CHUNK // max(1, len(cols) * k))
        for at in range(0, len(rows), step):
            out[at : at + step] = self.held[n][hashed(rows[at : at + step], cols, k, self.w) >> (31 - bits)]
        if n in moved and out.size:
            at, code = moved[n]
            a, b = np.searchsorted(at, (lo * self.gb * k, (lo + len(rows)) * self.gb * k))
            place = at[a:b] - lo * self.gb * k
            out[place // (self.gb * k), place // k % self.gb, place % k] = code[a:b]
        return out

    def keep(self, gi: int, gj: int, lo: int, hi: int, moved: dict) -> np.ndarray:
        """(log, row, column, slice): whether it counts. Cells beyond the grid have none."""
        out = np.zeros((len(self.sets), hi - lo, self.gb, self.slices), bool)
        for n, (k, policy) in enumerate(self.sets):
            if policy.kind == "shared":
                rows, cols = max(0, min(hi, self.bi - gi * self.ga) - lo), max(0, min(self.gb, self.bj - gj * self.gb))
                out[n, :rows, :cols, self.shared[n]] = True
                continue
            c = self.codes(n, gi, gj, lo, hi, moved)
            order = np.argsort(c, axis=2, kind="stable")
            rank = np.empty(c.shape, np.int16)
            np.put_along_axis(rank, order, np.arange(k, dtype=np.int16)[None, None, :], 2)
            alive = {"all": lambda: rank >= 0, "first": lambda: rank < policy.n, "drop": lambda: rank < k - policy.n, "deadline": lambda: (times(c) <= policy.n) | (rank < policy.least)}[policy.kind]()
            out[n, : c.shape[0], : c.shape[1], :k] = alive
        return out
