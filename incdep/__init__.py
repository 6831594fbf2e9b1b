"""Discovery of inclusion dependencies across many tables, on Spark."""

from .catalog import Catalog
from .discover import discover, flatten, profile

__all__ = ["Catalog", "discover", "flatten", "profile"]
