"""Registry of the engine's queries and their DuckDB oracles.

Every query runs over its whole tables. Floats leave as millionths (``fixed``), so the
two engines' results compare by value.
"""

from __future__ import annotations

from prunegraph.plans import headline, measures, surround, training


def queries() -> dict:
    found: dict = {}
    for module in (headline, measures, training, surround):
        found.update(module.queries())
    return found


def oracle_sql() -> dict[str, str]:
    found: dict = {}
    for module in (headline, measures, training, surround):
        found.update(module.oracle_sql())
    return found
