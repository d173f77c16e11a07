"""Every batch and stream query over the given tables, by name."""

from factlake.registry import extras, ranking, streams, surroundings, upkeep, workloads  # noqa: F401
from factlake.registry.base import QUERIES  # noqa: F401
