"""All queries of the engine; importing the workload modules registers them."""

from __future__ import annotations

from evograph.registry import ORACLES, QUERIES
from evograph.functions import udfs  # noqa: F401
from evograph.ops import relational, scalar  # noqa: F401
from evograph.streaming import online  # noqa: F401
from evograph.workloads import experiments, methods  # noqa: F401

__all__ = ["ORACLES", "QUERIES"]
