"""The corpus pipeline: language ID, near-duplicate removal, masking of personal data, mixing, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from blocksketch.llm.common import Kept
from blocksketch.llm.language_id import reject_unknown
from blocksketch.llm.mixing import mix_sources
from blocksketch.llm.near_dup import drop_near_duplicates
from blocksketch.llm.packing import pack_stage
from blocksketch.llm.pii import mask

STAGES = [
    ("language_id", reject_unknown),
    ("near_duplicates", drop_near_duplicates),
    ("personal_data", mask),
    ("mixing", mix_sources),
    ("packing", pack_stage),
]
#: Sketches, Bloom filters and tokenizers have no SQL; tests hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies the stages to documents, each on all that the one before kept, written and read again in between."""
    keep = Kept(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        docs = keep.keep(out) if k + 1 < len(STAGES) else out
    return docs
