"""All queries of the library outside the training-data operators."""

from __future__ import annotations

from pantry.plans import extraction, methods, relational, results, streams

MODULES = (extraction, methods, results, relational, streams)


def queries() -> dict:
    return {k: f for m in MODULES for k, f in m.Q.items()}


def oracle_sql() -> dict[str, str]:
    return {k: s for m in MODULES for k, s in m.O.items()}
