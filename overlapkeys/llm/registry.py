"""Queries of this subpackage. None of the operators' results is expressible in the oracle's SQL within
its means (tokenizers, 64-bit hashes, learnt models, global string search), so they are held against
brute-force versions in ``tests/llm``."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .bpe_replay import op5_bpe_merge_replay
from .html_trees import op7_html_trees
from .langid import op8_langid
from .latent_decontam import op10_latent_decontam
from .pii_crf import op9_pii_crf
from .sentence_spans import op1_sentence_spans
from .simhash_golay import op6_simhash_golay
from .simple8b import op3_simple8b
from .spotsigs import op2_spotsigs
from .suffix_groups import op4_suffix_groups

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_sentence_spans, op2_spotsigs, op3_simple8b, op4_suffix_groups, op5_bpe_merge_replay,
        op6_simhash_golay, op7_html_trees, op8_langid, op9_pii_crf, op10_latent_decontam,
    )
}
ORACLES: dict[str, str] = {}
