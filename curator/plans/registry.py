"""Registered queries by name, and the SQL that checks them."""

from __future__ import annotations

from curator.plans import methods, relational, workloads

QUERIES = methods.QUERIES | workloads.QUERIES | relational.QUERIES
ORACLES = methods.ORACLES | workloads.ORACLES | relational.ORACLES
