"""All registered queries of the engine."""

from . import checked, methods, relational, variants, workloads  # noqa: F401
from .registry import QUERIES, SQL  # noqa: F401
