"""Registered queries: logical plans over the given tables, with their SQL beside them."""

from __future__ import annotations

from importlib import import_module

from lakeadapt.session import REGISTRY, Registry

MODULES = ("queries_lake", "queries_core", "queries_chain", "queries_general", "queries_learned")


def registered() -> Registry:
    for name in MODULES:
        import_module(f"lakeadapt.plans.{name}")
    return REGISTRY
