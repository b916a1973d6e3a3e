"""Registered queries: every method, baseline, measure and experiment on the given tables, with DuckDB SQL where SQL can say it."""

from . import experiments, operators, scaling
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "experiments", "operators", "scaling"]
