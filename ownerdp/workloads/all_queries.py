"""Every query of the library and its SQL."""

from ownerdp.workloads import comparisons, operators  # noqa: F401  these add their queries to the same tables
from ownerdp.workloads.queries import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
