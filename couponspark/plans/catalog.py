"""All registered queries."""

from __future__ import annotations

from . import extras, reports, sketches, streams, surface, theory  # noqa: F401
from .registry import ORACLES, QUERIES


def queries():
    return dict(QUERIES)


def oracle_sql():
    return dict(ORACLES)
