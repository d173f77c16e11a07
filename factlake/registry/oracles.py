"""DuckDB SQL that must return the same rows as the query of the same name."""

from factlake.registry import queries  # noqa: F401
from factlake.registry.base import ORACLES  # noqa: F401
