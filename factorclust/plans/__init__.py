"""Registered queries: pieces of the solver, formulation and measures, fits and workloads, and what surrounds them."""

from __future__ import annotations

import importlib
from types import ModuleType

MODULES = ("pieces", "formulation", "fits", "variants", "surround", "scalars", "streams")


def load() -> ModuleType:
    """The registry with all queries in it."""
    for name in MODULES:
        importlib.import_module(f"factorclust.plans.{name}")
    return importlib.import_module("factorclust.registry")
