"""Registered queries and their SQL oracles, by family."""

from __future__ import annotations


def families():
    from . import core, relational, streams, windows

    return (core, relational, windows, streams)


def queries() -> dict:
    return {k: f for m in families() for k, f in m.QUERIES.items()}


def oracles() -> dict:
    return {k: s for m in families() for k, s in m.ORACLES.items()}
