"""The registered queries of the training-data operators and their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .bpe_automaton import op5_bpe
from .licenses import op1_licenses
from .metric_tree import op4_top_k
from .mixing import op8_mix
from .ngram_join import op3_ngram_join
from .pii import op2_pii
from .quality import op10_quality_rules
from .toxicity import op6_toxicity
from .twins import SQL  # noqa: F401
from .url_trust import op9_url_trust
from .warc import op7_warc

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_licenses": op1_licenses,
    "op2_pii": op2_pii,
    "op3_ngram_join": op3_ngram_join,
    "op4_top_k": op4_top_k,
    "op5_bpe": op5_bpe,
    "op6_toxicity": op6_toxicity,
    "op7_warc": op7_warc,
    "op8_mix": op8_mix,
    "op9_url_trust": op9_url_trust,
    "op10_quality_rules": op10_quality_rules,
}
