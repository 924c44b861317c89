"""All queries of the engine and their SQL twins."""

from __future__ import annotations

from prefixcode.workloads import core, surround


def queries() -> dict:
    return {**core.QUERIES, **surround.QUERIES}


def oracle_sql() -> dict[str, str]:
    return {**core.SQL, **surround.SQL}
