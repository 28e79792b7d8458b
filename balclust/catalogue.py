"""All queries of the engine by name, with the SQL that recomputes them."""

from __future__ import annotations

from balclust import queries_measures, queries_methods, queries_relational, queries_streaming  # noqa: F401  (they fill the register)
from balclust import register
from balclust import workloads as WL


def flagship(spark, sf_dir):
    """The weighted summary of the two-column lineitem lattice."""
    return queries_methods.built(spark, sf_dir, WL.W01).coreset


def queries():
    return dict(register.QUERIES)


def oracle_sql():
    return dict(register.SQL)
