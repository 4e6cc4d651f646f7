"""The operators' queries over the given tables, and their SQL where SQL can express them."""

from __future__ import annotations

from importlib import import_module

_MODULES = {
    "op1_pack": "packing",
    "op2_mix": "mixing",
    "op3_lines": "lines",
    "op4_language": "langid",
    "op5_token_store": "tokenstore",
    "op6_substrings": "substrings",
    "op7_exact": "exact",
    "op8_near_duplicates": "hyperminhash",
    "op9_media": "media",
    "op10_quality": "quality",
}


def queries() -> dict:
    return {name: getattr(import_module(f".{module}", __package__), name) for name, module in _MODULES.items()}


def oracle_sql() -> dict[str, str]:
    from . import exact, lines, mixing

    return {"op2_mix": mixing.OP2_SQL, "op3_lines": lines.OP3_SQL, "op7_exact": exact.OP7_SQL}
