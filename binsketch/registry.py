"""``queries()`` and ``oracle_sql()`` pairs of the methods of the reference."""

from __future__ import annotations

from .plans import base, generic, grids, laws, learning, search, sketches, streams, surfaces, toy

__all__ = ["generic", "grids", "laws", "learning", "oracles", "queries", "search", "sketches", "streams", "surfaces", "toy"]


def queries() -> dict:
    return dict(base.QUERIES)


def oracles() -> dict:
    return dict(base.ORACLES)
