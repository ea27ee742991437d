"""The registered corpus queries and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import corpus_pipeline
from pyspark.sql import DataFrame, SparkSession

from . import chat, top_k
from .chat import op7_perspective_rotation
from .language_id import op8_language_bitmask
from .mixing import op1_raked_mixture
from .near_dup import op10_fast_similarity
from .packing import op2_binary_lengths
from .pii import op9_bootstrapped_context
from .quality import op3_likelihood_ratio
from .repeats import op5_columnwise_order
from .top_k import op6_tiled_top_k
from .toxicity import op4_positive_unlabelled


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = (
        op1_raked_mixture, op2_binary_lengths, op3_likelihood_ratio, op4_positive_unlabelled, op5_columnwise_order,
        op6_tiled_top_k, op7_perspective_rotation, op8_language_bitmask, op9_bootstrapped_context, op10_fast_similarity,
    )
    return {f.__name__: f for f in found} | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    return {"op6_tiled_top_k": top_k.ORACLE, "op7_perspective_rotation": chat.ORACLE}
