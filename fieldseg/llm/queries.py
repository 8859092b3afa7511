"""Queries and SQL of the operators for training text."""

from __future__ import annotations

from collections.abc import Callable

from fieldseg.llm import decontaminate, language_id, line_dedup, packing, quality_classifier, quality_rules, sharding, simhash, suffix_dedup, url_filter

QUERIES: dict[str, Callable] = {
    "op1_quality_classifier": quality_classifier.op1,
    "op2_sharding": sharding.op2,
    "op3_decontamination": decontaminate.op3,
    "op4_language_id": language_id.op4,
    "op5_quality_rules": quality_rules.op5,
    "op6_simhash": simhash.op6,
    "op7_url_filter": url_filter.op7,
    "op8_suffix_dedup": suffix_dedup.op8,
    "op9_line_dedup": line_dedup.op9,
    "op10_packing": packing.op10,
}
ORACLES: dict[str, str] = {
    "op3_decontamination": decontaminate.OP3_SQL,
    "op5_quality_rules": quality_rules.OP5_SQL,
    "op7_url_filter": url_filter.OP7_SQL,
    "op9_line_dedup": line_dedup.OP9_SQL,
}
