"""Whole plans: the track pipeline, its registered queries and their oracles."""

from __future__ import annotations

from importlib import import_module

_MODULES = ("acquisition", "tracks", "texts", "whole", "relational")


def _registry():
    for name in _MODULES:
        import_module(f"crawltracks.plans.{name}")
    return import_module("crawltracks.plans.registry")


def all_queries() -> dict:
    return dict(_registry().QUERIES)


def all_oracles() -> dict[str, str]:
    return dict(_registry().ORACLES)
