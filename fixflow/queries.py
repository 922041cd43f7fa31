"""All queries of the engine, registered by importing the modules that define them."""

from __future__ import annotations

from .catalog import ORACLE, QUERIES
from .operators import relational
from .plans import queries as rules
from .streaming import windows
from .tasks import queries as tasks

__all__ = ["ORACLE", "QUERIES", "relational", "rules", "tasks", "windows"]
