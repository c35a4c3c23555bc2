"""Functions around the evaluators: prefix sums and ranks, table functions, SQL text."""

from .prefix import dense_rank, running_total
from .tables import degree_profile, register, sql

__all__ = ["degree_profile", "dense_rank", "register", "running_total", "sql"]
