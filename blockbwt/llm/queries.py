"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from importlib import import_module

#: Query: the module that has it.
_WHERE = {
    "op1_token_output": "token_output",
    "op2_byte_bpe": "byte_bpe",
    "op3_brown_lm": "brown_lm",
    "op4_cover_tree": "cover_tree",
    "op5_license_scan": "license_scan",
    "op6_merkle": "merkle",
    "op7_chat_format": "chat_format",
    "op8_language_id": "language_id",
    "op9_lsh_forest": "lsh_forest",
    "op10_mixing": "mixing",
}


def queries() -> dict:
    found = {name: getattr(import_module(f"{__package__}.{module}"), name) for name, module in _WHERE.items()}
    found["pipeline"] = import_module("corpus_pipeline").run
    return found


def oracle_sql() -> dict[str, str]:
    found = {name: import_module(f"{__package__}.{_WHERE[name]}").SQL for name in ("op4_cover_tree", "op7_chat_format", "op9_lsh_forest")}
    if import_module("corpus_pipeline").ORACLE_SQL is not None:
        found["pipeline"] = import_module("corpus_pipeline").ORACLE_SQL
    return found
