"""Registered queries, each next to the SQL that gives the same rows."""

from __future__ import annotations

from deltahop.queries.registry import ORACLES, QUERIES


def load() -> tuple[dict, dict]:
    from deltahop.queries import forward, graph, plan, relational, sampling, scalar, streams, training  # noqa: F401

    return QUERIES, ORACLES
