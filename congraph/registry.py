"""Queries and oracles of the engine by name."""

from __future__ import annotations

from congraph import workloads
from congraph.operators import catalogue
from congraph.streaming import streams


def queries() -> dict:
    return {**workloads.workload_queries()[0], **catalogue.QUERIES, **streams.QUERIES}


def oracles() -> dict[str, str]:
    found, base = workloads.workload_queries()
    return {k: workloads.ORACLES[base[k]] for k in found if base[k] in workloads.ORACLES} | catalogue.ORACLES | streams.ORACLES
