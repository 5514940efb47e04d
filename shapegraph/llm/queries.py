"""Queries of this subpackage for the driver's registry, and SQL for those that SQL can express."""

from __future__ import annotations

import corpus_pipeline

from .bpe import op2_bpe_transducer
from .decontaminate import op1_pigeonhole_decontamination
from .jaccard import op7_signature_tree_join
from .langid import op3_language_ppm
from .personal import op6_personal_crf
from .quality import op9_quality_rules
from .sharding import op10_flow_resharding
from .substrings import op8_suffix_dedup
from .tokencount import op5_token_counts
from .urls import op4_redirect_filter

QUERIES = {
    "op1_pigeonhole_decontamination": op1_pigeonhole_decontamination,
    "op2_bpe_transducer": op2_bpe_transducer,
    "op3_language_ppm": op3_language_ppm,
    "op4_redirect_filter": op4_redirect_filter,
    "op5_token_counts": op5_token_counts,
    "op6_personal_crf": op6_personal_crf,
    "op7_signature_tree_join": op7_signature_tree_join,
    "op8_suffix_dedup": op8_suffix_dedup,
    "op9_quality_rules": op9_quality_rules,
    "op10_flow_resharding": op10_flow_resharding,
    "pipeline": corpus_pipeline.run,
}

ORACLE_SQL: dict[str, str] = {} if corpus_pipeline.ORACLE_SQL is None else {"pipeline": corpus_pipeline.ORACLE_SQL}
