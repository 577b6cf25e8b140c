"""Registered queries and their SQL: name -> callable(spark, sf_dir), name -> DuckDB text."""

from . import engine, experiments, relational, streams

QUERIES = engine.QUERIES | experiments.QUERIES | relational.QUERIES | streams.QUERIES
ORACLES = engine.ORACLES | experiments.ORACLES | relational.ORACLES | streams.ORACLES
