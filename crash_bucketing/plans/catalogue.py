"""All named queries: the method's own, the operators around it, and the streams."""

from __future__ import annotations

from . import registry, relational


def queries() -> dict[str, registry.Query]:
    return {**registry.QUERIES, **relational.QUERIES}


def oracle_sql() -> dict[str, str]:
    return {**registry.ORACLES, **relational.ORACLES}
