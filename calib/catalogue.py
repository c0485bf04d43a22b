"""Every query of the engine, with its DuckDB equivalent where there is one."""

from __future__ import annotations

from calib import queries_experiments, queries_methods, queries_surface  # noqa: F401  they register themselves
from calib.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
