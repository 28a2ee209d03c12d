"""Registered queries, each with the SQL that checks it."""

from __future__ import annotations

from importlib import import_module

MODULES = ("fills", "trees", "rowsets", "claiming", "runs", "surface", "works")


def queries() -> dict:
    out: dict = {}
    for m in MODULES:
        out |= import_module(f"frontfill.catalog.{m}").QUERIES
    return dict(sorted(out.items()))


def oracles() -> dict:
    out: dict = {}
    for m in MODULES:
        out |= import_module(f"frontfill.catalog.{m}").ORACLES
    return dict(sorted(out.items()))
