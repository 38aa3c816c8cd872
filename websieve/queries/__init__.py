"""Registry of queries: one module for each family, each with CALLS and ORACLES."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import corpora, dedups, models, preprocess, relational, streams

FAMILIES = (preprocess, dedups, models, corpora, relational, streams)

CALLS: dict[str, Callable[[SparkSession, str], DataFrame]] = {name: call for family in FAMILIES for name, call in family.CALLS.items()}
ORACLES: dict[str, str] = {name: sql for family in FAMILIES for name, sql in family.ORACLES.items()}
