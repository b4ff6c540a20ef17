"""Query catalog: every key with its Spark query and, where SQL can say the same, its oracle."""

from __future__ import annotations

from ..streaming import queries as streaming
from . import methods, relational, surface

_PARTS = (methods, relational, surface, streaming)


def queries():
    return {k: q for part in _PARTS for k, q in part.queries().items()}


def oracle_sql():
    return {k: q for part in _PARTS for k, q in part.oracle_sql().items()}
