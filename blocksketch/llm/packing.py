"""Packing by power-of-two decomposition: a document's ids are cut into pieces of binary length, and pieces of equal length form a bucket.

A document of n ids gives n // size pieces of `size` and one for each set bit of the rest, the longest first, so every sequence is one
piece, lies within one document, has a power of two of ids and no padding. A trainer draws batches bucket by bucket.

Ids are those of the byte-level BPE file at `vocabulary`, followed by one separator id per document. Texts in Latin-1 below a million
characters go through a faster encoder built from the same file (same merges, same splitting); all others, and any file whose
merges are not in the order of their ids, through the `tokenizers` library itself.

Defined results: null or empty text gives the separator only; repeated rows are packed each for itself; tables without rows give none.
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import released, table

VOCABULARY = "byte_bpe_50k.json"
SIZE = 1024
_ENCODERS: dict[str, object] = {}


class Encoder:
    def __init__(self, vocabulary: str):
        import public_tokenizers
        from tokenizers import Tokenizer

        path = public_tokenizers.path(vocabulary) if "/" not in vocabulary else vocabulary
        self.slow = Tokenizer.from_file(path)
        self.fast = self._fast(path, public_tokenizers.PATTERN)

    @staticmethod
    def _fast(path: str, pattern: str):
        import tiktoken

        with open(path, encoding="utf-8") as f:
            said = json.load(f)
        vocab, merges = said["model"]["vocab"], said["model"]["merges"]
        plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
        byte = {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(b for b in range(256) if b not in set(plain))}
        merged = ["".join(m if isinstance(m, list) else m.split(" ")) for m in merges]
        if said.get("normalizer") or any(vocab[m] != 256 + k for k, m in enumerate(merged)):
            return None
        special = {t["content"]: t["id"] for t in said["added_tokens"]}
        ranks = {bytes(byte[c] for c in t): i for t, i in vocab.items() if t not in special}
        return tiktoken.Encoding("packing", pat_str=pattern, mergeable_ranks=ranks, special_tokens=special)

    def ids(self, text: str) -> np.ndarray:
        if not text:
            return np.zeros(0, np.uint32)
        if self.fast is not None and len(text) < 1_000_000:
            try:
                text.encode("latin-1")
            except UnicodeEncodeError:
                pass
            else:
                return self.fast.encode_to_numpy(text, allowed_special="all")
        return np.array(self.slow.encode(text, add_special_tokens=False).ids, np.uint32)


def encoder(vocabulary: str) -> Encoder:
    """One for each worker process."""
    if vocabulary not in _ENCODERS:
        _ENCODERS[vocabulary] = Encoder(vocabulary)
    return _ENCODERS[vocabulary]


def lengths(n: int, size: int = SIZE) -> list[int]:
    """The lengths of the pieces of n ids."""
    rest = n % size
    return [size] * (n // size) + [1 << b for b in range(size.bit_length() - 2, -1, -1) if rest >> b & 1]


def pack(docs: DataFrame, vocabulary: str = VOCABULARY, size: int = SIZE, separator: int = 0, with_ids: bool = False) -> DataFrame:
    """docs(doc_id, text) to a row per piece: doc_id, start, length, ids_crc32, doc_tokens, bucket (log2 of length), sequence_id,
    offset (always 0), and with with_ids the ids. sequence_id is unique within one run. size must be a power of two."""
    if size < 1 or size & (size - 1):
        raise ValueError("size must be a power of two")

    @released
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        enc = encoder(vocabulary)
        end = np.array([separator], np.uint32)
        for pdf in batches:
            doc, start, length, crc, total, ids = [], [], [], [], [], []
            for i, text in enumerate(pdf["text"]):
                x = np.concatenate([enc.ids(text), end])
                raw, n, at = memoryview(x.astype("<u4", copy=False).tobytes()), len(x), 0
                for k in lengths(n, size):
                    doc.append(i)
                    start.append(at)
                    length.append(k)
                    crc.append(zlib.crc32(raw[4 * at : 4 * (at + k)]))
                    total.append(n)
                    if with_ids:
                        ids.append(x[at : at + k].astype(np.int32))
                    at += k
            long = lambda x: np.array(x, np.int64)
            out = {"doc_id": pdf["doc_id"].to_numpy()[doc], "start": long(start), "length": long(length), "ids_crc32": long(crc), "doc_tokens": long(total)}
            yield pd.DataFrame(out | ({"ids": ids} if with_ids else {}))

    schema = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long" + ", ids array<int>" * with_ids
    pieces = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInPandas(run, schema)
    return pieces.withColumns({"bucket": F.log2("length").cast("int"), "sequence_id": F.monotonically_increasing_id(), "offset": F.lit(0).cast("long")})


def write_buckets(pieces: DataFrame, path: str) -> None:
    """Pieces with ids as Parquet, a folder for each length, to be read in batches of equal lengths."""
    pieces.write.partitionBy("bucket").mode("overwrite").parquet(path)


def op2_binary_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))


def pack_stage(spark: SparkSession, docs: DataFrame, sf_dir: str | None = None) -> DataFrame:
    """Pipeline stage, the last: a row per piece."""
    return pack(docs)
