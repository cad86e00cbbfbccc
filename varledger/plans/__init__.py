"""Registered workloads, each with its DuckDB counterpart."""

from importlib import import_module

NAMES = ("profiles", "archive", "recovery", "papers", "graphs", "ledgers", "statistics")


def modules():
    return [import_module(f"{__name__}.{n}") for n in NAMES]
