"""Registered queries over the given tables, with SQL that says the same where SQL can."""

from __future__ import annotations

from . import methods, streams, surrounding, workloads

QUERIES = methods.QUERIES | workloads.QUERIES | surrounding.QUERIES | streams.QUERIES
ORACLES = methods.ORACLES | workloads.ORACLES | surrounding.ORACLES | streams.ORACLES
