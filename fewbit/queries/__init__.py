"""Queries of the engine by name, and their SQL for an independent engine."""

from __future__ import annotations


def _homes():
    from fewbit.queries import methods, relational, stores, streams, theory, workloads

    return methods, theory, workloads, relational, streams, stores


def queries() -> dict:
    return {k: v for home in _homes() for k, v in home.QUERIES.items()}


def oracles() -> dict:
    return {k: v for home in _homes() for k, v in home.ORACLES.items()}
