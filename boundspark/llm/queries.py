"""Queries and oracle SQL of the training-data operators, for the driver's entry module."""

from __future__ import annotations

import importlib

#: Modules that register an opN query of their own; each has ORACLE, and functions named op<N>_<name>.
MODULES = ("quality_rules", "simhash", "suffix_dedup", "substring_dedup", "sharding", "weak_label_classifier", "bpe", "exact_dedup", "chat_template", "packing")


def queries() -> dict:
    out = {}
    for name in MODULES:
        module = importlib.import_module(f"boundspark.llm.{name}")
        out |= {k: v for k, v in vars(module).items() if k.startswith("op") and k[2].isdigit()}
    import corpus_pipeline

    return out | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    for name in MODULES:
        out |= importlib.import_module(f"boundspark.llm.{name}").ORACLE
    return out
