"""Operators of a training-data pipeline, and their registry. Nothing outside this subpackage imports it."""

from importlib import import_module

_QUERIES = {
    "op1_ppm_scores": ("ppm", "op1_ppm_scores"),
    "op2_surrogates": ("surrogates", "op2_surrogates"),
    "op3_chat_format": ("chat", "op3_chat_format"),
    "op4_secret_scan": ("secrets", "op4_secret_scan"),
    "op5_pack": ("packing", "op5_pack"),
    "op6_language_id": ("langid", "op6_language_id"),
    "op7_exact_topk": ("topk", "op7_exact_topk"),
    "op8_mix": ("mixing", "op8_mix"),
    "op9_near_duplicates": ("neardup", "op9_near_duplicates"),
    "op10_quality_rules": ("quality", "op10_quality_rules"),
}
_SQL = {"op3_chat_format": ("chat", "OP3_SQL"), "op7_exact_topk": ("topk", "OP7_SQL")}


def _get(places: dict) -> dict:
    return {name: getattr(import_module(f"{__name__}.{module}"), attr) for name, (module, attr) in places.items()}


def queries() -> dict:
    return _get(_QUERIES)


def oracle_sql() -> dict:
    return _get(_SQL)
