"""Workloads, registered queries and their SQL twins."""

from warpspan.plans import experiments, methods  # noqa: F401
from warpspan.plans.registry import ORACLES, QUERIES  # noqa: F401
