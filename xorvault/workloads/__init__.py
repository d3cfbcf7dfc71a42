"""The experiment workloads on the given tables, as named queries with SQL twins."""

from xorvault.workloads import catalog, dedup, models, storage, streams  # noqa: F401
from xorvault.workloads.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
