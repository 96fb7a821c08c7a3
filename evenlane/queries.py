"""Registry of the engine's queries: name -> callable, name -> DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from evenlane.plans import catalogue_measures, catalogue_relational, catalogue_sorts, catalogue_theory

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}

for _part in (catalogue_sorts, catalogue_measures, catalogue_theory, catalogue_relational):
    QUERIES |= _part.QUERIES
    ORACLE_SQL |= _part.ORACLE_SQL
