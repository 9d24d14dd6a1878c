"""Schemas of schema-on-read applications from their source code, on Spark."""

from .api import analyze, logical_schema, plans, remove_join
from .plans import Options, paper_options

__all__ = ["Options", "analyze", "logical_schema", "paper_options", "plans", "remove_join"]
