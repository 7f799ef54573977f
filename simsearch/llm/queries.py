"""The queries of this subpackage and their SQL, by name."""

from __future__ import annotations

from . import decontaminate, jaccard, mixing, pitman_yor, quality, repair, rules, separators, suffixes, toxicity

QUERIES = {f.__name__: f for f in (suffixes.op1_repeated_strings, quality.op2_line_quality, decontaminate.op3_decontaminate, pitman_yor.op4_pitman_yor, mixing.op5_source_mixture, repair.op6_token_shards, rules.op7_robust_rules, jaccard.op8_shingle_join, separators.op9_separator_scan, toxicity.op10_toxicity)}
ORACLE: dict[str, str] = {**suffixes.ORACLE, **quality.ORACLE, **decontaminate.ORACLE, **pitman_yor.ORACLE, **mixing.ORACLE, **repair.ORACLE, **rules.ORACLE, **jaccard.ORACLE, **separators.ORACLE, **toxicity.ORACLE}
