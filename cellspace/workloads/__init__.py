"""The experiment workloads on the given tables, with their SQL."""

from cellspace.workloads import methods, relational, streams  # noqa: F401
from cellspace.workloads.base import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
