"""Registered queries and their SQL twins."""

from __future__ import annotations


def _load() -> None:
    from coloc.catalog import methods, relational, streams, workloads  # noqa: F401


def queries() -> dict:
    from coloc.catalog.registry import QUERIES

    _load()
    return dict(QUERIES)


def oracles() -> dict[str, str]:
    from coloc.catalog.registry import ORACLES

    _load()
    return dict(ORACLES)
