"""Queries of the corpus operators by name."""

from __future__ import annotations

import importlib

#: Query name to module; each module has ``query`` and, where SQL can express it, ``ORACLE``.
MODULES = {
    "op1_line_frequency": "line_frequency",
    "op2_bootstrap_identifiers": "identifiers",
    "op3_context_tree": "context_tree",
    "op4_nbsvm": "nbsvm",
    "op5_factorization_machine": "factorization",
    "op6_winnowing": "winnowing",
    "op7_poisson_mix": "poisson_mix",
    "op8_near_duplicates": "near_duplicates",
    "op9_wordpiece_counts": "wordpiece",
    "op10_url_templates": "url_templates",
}


def _module(name: str):
    return importlib.import_module(f"bucketseed.llm.{MODULES[name]}")


def _pipeline(spark, sf_dir: str):
    from corpus_pipeline import run

    return run(spark, sf_dir)


def queries() -> dict:
    return {name: _module(name).query for name in MODULES} | {"pipeline": _pipeline}


def oracle_sql() -> dict[str, str]:
    found = {name: getattr(_module(name), "ORACLE", None) for name in MODULES}
    return {name: sql for name, sql in found.items() if sql}
