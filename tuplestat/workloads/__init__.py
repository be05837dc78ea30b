"""Named queries over the given tables, each with SQL written from the definitions."""

from __future__ import annotations

import importlib

MODULES = ("estimator_queries", "kernel_queries", "variance_queries", "learning_queries", "relational_queries", "function_queries", "experiment_queries", "whole_queries")


def _loaded():
    from . import base

    for name in MODULES:
        importlib.import_module(f"{__name__}.{name}")
    return base


def all_queries() -> dict:
    return dict(_loaded().QUERIES)


def all_oracles() -> dict[str, str]:
    return dict(_loaded().ORACLES)
