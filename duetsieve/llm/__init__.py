"""Training-data operators: ten corpus operators and their queries.

Nothing outside this subpackage imports it.  ``queries()`` and ``oracle_sql()`` gather what
``__spark_entry__`` registers.
"""

from __future__ import annotations

from importlib import import_module

_MODULES = ("pii", "quality", "pieces", "tokenfile", "ann", "linedup", "rules", "setjoin", "mixing", "substring")


def queries() -> dict:
    found = {}
    for name in _MODULES:
        found.update(import_module(f"{__name__}.{name}").QUERIES)
    return found


def oracle_sql() -> dict:
    found = {}
    for name in _MODULES:
        found.update(getattr(import_module(f"{__name__}.{name}"), "ORACLES", {}))
    return found
