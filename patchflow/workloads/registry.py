"""All queries of the library by name, and the SQL of those that SQL can express."""

from __future__ import annotations

from importlib import import_module

MODULES = ("tokens", "features", "curation", "neardups", "captions", "recipes", "balances", "streams", "gates", "scores", "surface", "extras", "sequences")


def _all(what: str) -> dict:
    out = {}
    for m in MODULES:
        out |= getattr(import_module(f"{__package__}.{m}"), what)
    return out


def queries() -> dict:
    return _all("QUERIES")


def oracle_sql() -> dict[str, str]:
    return _all("SQL")
