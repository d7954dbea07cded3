"""Queries and oracle SQL of the text operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

import corpus_pipeline

from .decontamination import op7_decontamination
from .html import op8_html
from .jaccard import op4_jaccard
from .packing import op5_packing
from .quality import op6_quality
from .secrets import op2_secrets
from .sharding import op3_sharding
from .suffix_dedup import op10_suffix_dedup
from .topk import ORACLE as _TOPK
from .topk import op9_topk
from .toxicity import op1_toxicity

_OPS = (op1_toxicity, op2_secrets, op3_sharding, op4_jaccard, op5_packing, op6_quality, op7_decontamination, op8_html, op9_topk, op10_suffix_dedup)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in _OPS} | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    return {"op9_topk": _TOPK}
