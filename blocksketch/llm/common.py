"""What the operators share: reading tables, results kept in the shared folder, fast hashing of byte windows."""

from __future__ import annotations

import atexit
import ctypes
import functools
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

U64 = np.uint64


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or one of our own where that is unset (local runs)."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        jsc = spark.sparkContext._jsc.sc()
        if jsc.getCheckpointDir().isDefined():
            return jsc.getCheckpointDir().get()
        found = tempfile.mkdtemp(prefix="blocksketch-")
        atexit.register(shutil.rmtree, found, True)
        spark.sparkContext.setCheckpointDir(f"file://{found}")
        return f"file://{found}"
    return found


class Kept:
    """Intermediate results as Parquet in the shared folder: they cut lineage and survive lost executors."""

    def __init__(self, spark: SparkSession):
        self.spark, self.root = spark, f"{shared_dir(spark).rstrip('/')}/blocksketch-{uuid.uuid4().hex}"
        self.n = 0

    def keep(self, df: DataFrame) -> DataFrame:
        self.n += 1
        path = f"{self.root}/{self.n}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._kept_path = path
        return out

    def drop(self, df: DataFrame | None) -> None:
        """Removes a result that nothing will read again."""
        path = getattr(df, "_kept_path", None)
        if path:
            jvm = self.spark._jvm
            p = jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(p, True)


def released(run: Callable[..., Iterator]) -> Callable[..., Iterator]:
    """`run`, a generator over a task's batches, after which the worker gives free memory back to the system: Spark keeps workers for later tasks, of any stage."""

    @functools.wraps(run)
    def task(batches):
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of glibc only
            if trim:
                trim(0)

    return task


def mix(h: np.ndarray) -> np.ndarray:
    """The splitmix64 finaliser, element by element, on uint64."""
    h = h ^ (h >> U64(30))
    h = h * U64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> U64(27))
    h = h * U64(0x94D049BB133111EB)
    return h ^ (h >> U64(31))


def seeds(name: str, n: int) -> np.ndarray:
    """n fixed pseudo-random odd 64-bit numbers."""
    start = int.from_bytes(name.encode()[:7].ljust(7, b"."), "little")
    return mix(np.arange(1, n + 1, dtype=np.uint64) * U64(0x9E3779B97F4A7C15) + U64(start)) | U64(1)


_PAGE = 1 << 20


class _Field:
    """Powers of a fixed base modulo a prime below 2^31, and of its inverse. Tables reach to _PAGE; farther powers are products of two."""

    def __init__(self, prime: int, name: str):
        self.prime = U64(prime)
        base = int(seeds(name, 1)[0]) % (prime - 512) + 256
        self.ahead, self.back = base, pow(base, -1, prime)
        self.powers, self.inverses = (self._table(b, _PAGE) for b in (self.ahead, self.back))

    def _table(self, base: int, size: int) -> np.ndarray:
        out = np.ones(size, np.uint64)
        n = 1
        while n < size:
            out[n : 2 * n] = out[:n] * U64(pow(base, n, int(self.prime))) % self.prime
            n *= 2
        return out.astype(np.uint32)

    def unshift(self, at: np.ndarray) -> np.ndarray:
        """The inverse base to the power of each position."""
        low = self.inverses[at & (_PAGE - 1)].astype(np.uint64)
        if not len(at) or at.max() < _PAGE:
            return low
        pages = at >> 20
        high = np.array([pow(self.back, int(k) * _PAGE, int(self.prime)) for k in range(int(pages.max()) + 1)], np.uint64)
        return low * high[pages] % self.prime


class Windows:
    """Hashes of any windows of one sequence of bytes, or of 64-bit symbols, in constant time each: polynomial prefix sums modulo two primes near 2^31 in random bases,
    so that two given windows of n bytes agree with probability (n / 2^31)^2 at most, whatever their structure."""

    _fields: list[_Field] = []

    def __init__(self, data: np.ndarray):
        if not self._fields:  # on first use: 16 MB of tables for each worker
            self._fields.extend((_Field((1 << 31) - 1, "base 1"), _Field((1 << 31) - 19, "base 2")))
        self.sums = []
        for f in self._fields:
            sums = np.zeros(len(data) + 1, np.uint64)
            for page, begin in enumerate(range(0, len(data), _PAGE)):
                part = data[begin : begin + _PAGE]
                if data.dtype == np.uint8:
                    part = (part.astype(np.uint64) + U64(1)) * f.powers[: len(part)]  # below 2^40, so a page sums up below 2^60
                else:
                    part = (part % f.prime + U64(1)) * f.powers[: len(part)] % f.prime
                if page:
                    part = part % f.prime * U64(pow(f.ahead, begin, int(f.prime))) % f.prime
                np.cumsum(part, out=sums[begin + 1 : begin + 1 + len(part)])
                if page:
                    sums[begin + 1 : begin + 1 + len(part)] += sums[begin] % f.prime
            self.sums.append(sums)

    def hash(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        parts = []
        for f, s in zip(self._fields, self.sums, strict=True):
            d = s[end] - s[start] if len(s) <= _PAGE else s[end] % f.prime + f.prime - s[start] % f.prime
            parts.append(d % f.prime * f.unshift(start) % f.prime)
        one, two = parts
        return mix((one << U64(31) | two) + (end - start).astype(np.uint64) * U64(0x9E3779B97F4A7C15))


def fingerprints(data: np.ndarray, width: int) -> np.ndarray:
    """A pseudo-random number for each string of `width` (8 or more) bytes in data, from its 8-byte words."""
    m = len(data) - width + 1
    if m <= 0:
        return np.zeros(0, np.uint64)
    padded = np.concatenate([data, np.zeros(8, np.uint8)])
    words = np.ndarray((m + width - 8,), "<u8", padded.tobytes(), strides=(1,)).copy()
    words ^= words >> U64(32)  # so that high bytes reach low bits
    h = np.zeros(m, np.uint64)
    for at, by in zip([*range(0, width - 8, 8), width - 8], seeds("grams", 64 + width // 8), strict=False):
        h += words[at : at + m] * by
    return mix(h)
