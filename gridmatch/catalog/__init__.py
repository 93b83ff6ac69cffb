"""All queries of the library and the SQL that checks them."""

from __future__ import annotations

from importlib import import_module

MODULES: tuple[str, ...] = ("regions", "searches", "experiments", "relational", "streams", "files")


def _gather(what: str) -> dict:
    out: dict = {}
    for name in MODULES:
        out |= getattr(import_module(f"{__package__}.{name}"), what)
    return out


def queries() -> dict:
    return _gather("QUERIES")


def oracles() -> dict:
    return _gather("ORACLES")
