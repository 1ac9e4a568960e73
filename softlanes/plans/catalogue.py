"""Registered queries of the engine and the SQL of those that SQL expresses."""

from __future__ import annotations

from softlanes.plans import accuracy, experiments, identities, ranking, relational, structures
from softlanes.streaming import heartbeats

MODULES = [structures, ranking, accuracy, identities, experiments, relational, heartbeats]


def queries():
    return {name: run for m in MODULES for name, (run, _) in m.QUERIES.items()}


def oracle_sql():
    return {name: sql for m in MODULES for name, (_, sql) in m.QUERIES.items() if sql is not None}
