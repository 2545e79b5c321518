"""Names of the engine's own queries and the DuckDB SQL that they are held against."""

from __future__ import annotations

import importlib
import pkgutil

from . import workloads
from .workloads import base


def _loaded() -> None:
    for m in pkgutil.iter_modules(workloads.__path__):
        importlib.import_module(f"{workloads.__name__}.{m.name}")


def queries() -> dict:
    _loaded()
    return dict(base.QUERIES)


def oracle_sql() -> dict[str, str]:
    _loaded()
    return dict(base.SQL)
