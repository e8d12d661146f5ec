"""All queries of the library: importing it fills the registry."""

from __future__ import annotations

from pairlab.operators import workloads, workloads_data, workloads_general, workloads_judges, workloads_policy, workloads_rl  # noqa: F401
from pairlab.registry import ORACLE_SQL, QUERIES  # noqa: F401
from pairlab.streaming import workloads as _streams  # noqa: F401
