"""The queries and SQL of all operators in this folder, by name."""

from __future__ import annotations

from importlib import import_module

MODULES = (
    "secrets", "decontaminate", "packing", "token_files", "langid",
    "suffix_dedup", "pii", "token_counts", "simhash", "exact_dedup",
)


def queries() -> dict:
    """Name -> callable(spark, sf_dir)."""
    return {m.NAME: m.query for m in (import_module(f"predmap.llm.{x}") for x in MODULES)}


def oracle_sql() -> dict[str, str]:
    """Name -> DuckDB SQL, for the operators that SQL expresses."""
    return {m.NAME: m.SQL for m in (import_module(f"predmap.llm.{x}") for x in MODULES) if m.SQL}
