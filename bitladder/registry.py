"""All registered queries of the paper's own methods, and their SQL."""

from __future__ import annotations

from . import oracles, reports, trained, workloads

QUERIES = workloads.QUERIES | trained.QUERIES | reports.QUERIES
ORACLES = oracles.ORACLES | reports.ORACLES
