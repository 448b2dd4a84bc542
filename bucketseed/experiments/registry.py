"""Queries of the clustering engine by name, and their SQL twins."""

from __future__ import annotations

import importlib

PARTS = ("blocks", "phases", "compared", "surface")


def _modules():
    return [importlib.import_module(f"bucketseed.experiments.{name}") for name in PARTS]


def queries() -> dict:
    return {name: query for part in _modules() for name, query in part.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for part in _modules() for name, sql in part.ORACLES.items()}


def flagship(spark, sf_dir: str):
    """Documents seeded, assigned once and measured: one row of the run's figures."""
    return queries()["w_sparse_docs"](spark, sf_dir)
