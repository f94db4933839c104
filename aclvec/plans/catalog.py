"""All queries of the catalogue with their SQL."""

from aclvec.plans import catalog_parts, catalog_policy, catalog_relational, catalog_search, catalog_stream, experiments, experiments_tables  # noqa: F401
from aclvec.plans.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
