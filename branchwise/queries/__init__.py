"""Queries of the matching engine over the given tables, each with its SQL where SQL can say it, the light ones first."""

from . import patterns, surface, filters, engines, experiments  # noqa: F401, I001  # in the order of their cost
from .registry import ORACLE_SQL, QUERIES  # noqa: F401
