"""Registered queries with the SQL of each."""

from . import core, experiments, measured, rewriting, streams, surround

QUERIES = core.QUERIES | rewriting.QUERIES | surround.QUERIES | streams.QUERIES | experiments.QUERIES | measured.QUERIES
SQL = core.SQL | rewriting.SQL | surround.SQL | streams.SQL | experiments.SQL | measured.SQL
