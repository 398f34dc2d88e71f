"""Registry of the engine's own queries and their SQL oracles."""

from .queries import adversarial, around, protected, sketches, surface  # noqa: F401
from .queries.base import ORACLE_SQL, QUERIES

__all__ = ["ORACLE_SQL", "QUERIES"]
