"""Registered queries of the operators of this package, and their SQL."""

from __future__ import annotations

from importlib import import_module

#: (module, query, attribute with its SQL or None)
_REGISTER = [
    ("toxicity", "op1_toxicity", None),
    ("decontamination", "op3_decontamination", "OP3_SQL"),
    ("urls", "op4_url_filter", "OP4_SQL"),
    ("quality", "op5_quality", None),
    ("repeats", "op6_suffix_dedup", None),
    ("bpe", "op7_bpe", None),
    ("minhash", "op10_minhash", "OP10_SQL"),
    ("scoring", "op9_lm_scoring", None),
    ("crosspolytope", "op2_embedding_dedup", "OP2_SQL"),
    ("seekable", "op8_token_output", None),
]


def queries() -> dict:
    found = {query: getattr(import_module(f"weft.llm.{module}"), query) for module, query, _ in _REGISTER}
    import corpus_pipeline

    return found | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    import corpus_pipeline

    found = {query: getattr(import_module(f"weft.llm.{module}"), sql) for module, query, sql in _REGISTER if sql}
    return found | ({"pipeline": corpus_pipeline.ORACLE_SQL} if corpus_pipeline.ORACLE_SQL else {})
