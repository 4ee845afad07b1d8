"""The workloads behind queries() and their SQL."""

from __future__ import annotations


def queries():
    from standq.workloads import cases, flows, guards, sources, tasks  # noqa: F401
    from standq.workloads.registry import QUERIES

    return QUERIES


def oracles():
    from standq.workloads.registry import ORACLES

    queries()
    return ORACLES
