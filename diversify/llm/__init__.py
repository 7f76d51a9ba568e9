"""Operators of a training-data pipeline. Nothing else in the library imports this subpackage."""

from importlib import import_module

MODULES = ("pii", "toxicity", "repeats", "licences", "mixing", "vectors", "wrappers", "fingerprints", "leaks", "quality")


def _all(what: str) -> dict:
    return {k: v for m in MODULES for k, v in getattr(import_module(f"{__name__}.{m}"), what).items()}


def queries() -> dict:
    return _all("QUERIES")


def oracle_sql() -> dict:
    return _all("SQL")
