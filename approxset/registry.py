"""All queries outside the optional subpackage, with their SQL."""

from __future__ import annotations

from .workloads import base, baselines, experiments, membership, relational, sqlfunctions, storage, streams, throughput, tiers  # noqa: F401

QUERIES = base.QUERIES
ORACLES = base.ORACLES
